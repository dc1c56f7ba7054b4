"""Pairs of properties of one class from different sources, and their features.

Pairs are unordered: source_a < source_b. A join on the class alone has few, hot keys; so properties are hashed into
blocks, and each is sent to the blocks that it meets (a salted join). For small profiles one side is broadcast, after a
count.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from propalign.functions.strings import all_eight, distances, normal_py
from propalign.model import PAIR_KEY, FeatureConfig
from propalign.operators.profile import vector_of

#: Profiles of at most so many properties (about 3 kB each) have one side broadcast.
BROADCAST_PROPERTIES = 20_000
#: Properties of a block.
BLOCK = 512


def candidates(profile: DataFrame, columns: list[str] | None = None, strategy: str = "auto", blocks: int | None = None, blocking: DataFrame | None = None) -> DataFrame:
    """PAIR rows, with columns of both sides as <column>_a and <column>_b. strategy: auto, broadcast or blocks.

    blocking: PAIR rows to keep (by words or LSH); None: all pairs.
    """
    columns = columns or []
    side = lambda s: profile.select("cls", *[F.col(c).alias(f"{c}_{s}") for c in ["source", "prop", *columns]])
    if strategy == "auto" or (strategy == "blocks" and blocks is None):
        n = profile.count()
        if strategy == "auto":
            strategy = "broadcast" if n <= BROADCAST_PROPERTIES else "blocks"
        blocks = blocks or max(1, -(-n // BLOCK))
    a, b = side("a"), side("b")
    if strategy == "broadcast":
        pairs = a.join(F.broadcast(b), "cls").where("source_a < source_b")
    else:
        block = lambda s: F.pmod(F.xxhash64(f"source_{s}", f"prop_{s}"), F.lit(blocks)).cast("int")
        every = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
        a = a.withColumn("_i", block("a")).withColumn("_j", every)
        b = b.withColumn("_j", block("b")).withColumn("_i", every)
        pairs = a.join(b, ["cls", "_i", "_j"]).where("source_a < source_b").drop("_i", "_j")
    order = [*PAIR_KEY, *[f"{c}_{s}" for c in columns for s in "ab"]]
    return (pairs if blocking is None else pairs.join(blocking.select(*PAIR_KEY).distinct(), PAIR_KEY, "left_semi")).select(*order)


def combine(a: Column, b: Column, mode: str = "abs_diff") -> Column:
    """Two property vectors as one: abs_diff, diff, mean or concat."""
    if mode == "concat":
        return F.concat(a, b)
    f = {"abs_diff": lambda x, y: F.abs(x - y), "diff": lambda x, y: x - y, "mean": lambda x, y: (x + y) / 2}[mode]
    return F.zip_with(a, b, f)


def assemble(profile: DataFrame, mode: str = "abs_diff", config: FeatureConfig = FeatureConfig(), d: int | None = None) -> DataFrame:
    """PAIR rows with features: the combined vectors and the eight name distances, cut to the configuration.

    For inspection and for ML pipelines; the matcher itself scores tiles without this table.
    """
    vectors = profile.withColumn("vec", vector_of(profile))
    d = d if d is not None else profile.select(F.size("name_emb")).first()[0]
    pairs = candidates(vectors, ["vec"])
    pairs = distances(pairs.withColumn("features", combine(F.col("vec_a"), F.col("vec_b"), mode)))
    from propalign.functions.strings import DISTANCES

    whole = F.concat("features", F.array(*[F.col(f"dist_{k}") for k in DISTANCES]))
    if mode == "concat":
        if config != FeatureConfig():
            raise ValueError("concatenated vectors have no feature configurations")
        return pairs.select(*PAIR_KEY, whole.alias("features"))
    cut = F.concat(*[F.slice(whole, a + 1, b - a) for a, b in config.slices(d)])
    return pairs.select(*PAIR_KEY, cut.alias("features"))


def combine_np(a: np.ndarray, b: np.ndarray, mode: str) -> np.ndarray:
    if mode == "concat":
        return np.concatenate([a, b], -1)
    return {"abs_diff": lambda: np.abs(a - b), "diff": lambda: a - b, "mean": lambda: (a + b) / 2}[mode]()


def pair_matrix(va: np.ndarray, vb: np.ndarray, names_a: list[str], names_b: list[str], mode: str = "abs_diff") -> np.ndarray:
    """Features of aligned rows of two sides, as assemble() has them; distances once for each pair of different names."""
    ids: dict[tuple[str, str], int] = {}
    norm = {x: normal_py(x) for x in {*names_a, *names_b}}
    at = np.array([ids.setdefault((norm[x], norm[y]), len(ids)) for x, y in zip(names_a, names_b, strict=True)], dtype=int)
    table = np.array([all_eight(*k) for k in ids]).reshape(-1, 8)
    return np.concatenate([combine_np(va, vb, mode), table[at]], 1)
