"""The property-pair classifier: profiles, labelled pairs, a trained network, a scored similarity graph.

Pairs are scored in tiles. The properties of a class are dealt to blocks of some hundred; each pair of blocks becomes one
row that carries both blocks' vectors, and a task forms the tile's features, runs the network and emits pairs whose score is
high enough. So a property's vector is moved once for each block that it meets, and pair features are never written.
"""

from __future__ import annotations

import json
from collections.abc import Iterator
from dataclasses import asdict, dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from propalign.model import PAIR_KEY, PROPERTY_KEY, FeatureConfig
from propalign.operators.network import Network, NetworkSpec, fit
from propalign.operators.pairs import BLOCK, pair_matrix
from propalign.operators.profile import profile, vector_of

#: Labelled pairs that one task can hold for training; more are an error, to be sampled first.
MOST_TRAINING = 2_000_000


@dataclass(frozen=True)
class MatcherSpec:
    config: FeatureConfig = FeatureConfig()
    network: NetworkSpec = NetworkSpec()
    mode: str = "abs_diff"
    aggregate: str = "mean"
    distinct_values: bool = False
    numeric_missing: float | None = -1.0
    trainer: str = "minibatch"


def _cut(x: np.ndarray, spec: MatcherSpec, d: int) -> np.ndarray:
    if spec.mode == "concat":
        return x
    return np.concatenate([x[:, a:b] for a, b in spec.config.slices(d)], 1)


@dataclass
class PropertyPairModel:
    spec: MatcherSpec
    network: Network
    d: int
    profile: DataFrame | None = field(default=None, repr=False)

    def save(self, path: str) -> None:
        """One JSON file, on any file system that Spark reaches where path names one."""
        text = json.dumps({"d": self.d, "spec": asdict(self.spec) | {"network": None}, "network": self.network.to_json()})
        SparkSession.getActiveSession().createDataFrame([(text,)], "value string").coalesce(1).write.mode("overwrite").text(path)

    @staticmethod
    def load(path: str) -> PropertyPairModel:
        x = json.loads("".join(r["value"] for r in SparkSession.getActiveSession().read.text(path).collect()))  # one line
        network = Network.from_json(x["network"])
        spec = MatcherSpec(**x["spec"] | {"config": FeatureConfig(**x["spec"]["config"]), "network": network.spec})
        return PropertyPairModel(spec, network, x["d"])

    def score(self, profile_: DataFrame | None = None, exclude: DataFrame | None = None, threshold: float = 0.5, min_score: float = 0.0, include_labelled: bool = False, blocks: int | None = None) -> DataFrame:
        """SIM rows of all pairs but exclude (PAIR rows, usually the labelled ones).

        include_labelled: exclude's pairs come too, with their label as the score and a column given = true.
        """
        prof = profile_ if profile_ is not None else self.profile
        sim = score_tiles(prof, self, min_score, blocks)
        if exclude is not None:
            sim = sim.join(exclude.select(*PAIR_KEY), PAIR_KEY, "left_anti")
        sim = sim.withColumn("is_match", F.col("score") > threshold)
        if include_labelled:
            given = exclude.select(*PAIR_KEY, F.col("label").cast("double").alias("score"), (F.col("label") == 1).alias("is_match"), F.lit(True).alias("given"))
            sim = sim.withColumn("given", F.lit(False)).unionByName(given)
        return sim


def _blocks_of(properties: int, cores: int) -> int:
    """Blocks of about BLOCK properties, or as many more of 32 or more as give every core some tiles."""
    return max(1, -(-properties // BLOCK), min(-(-properties // 32), int((8 * cores) ** 0.5)))


def score_tiles(prof: DataFrame, model: PropertyPairModel, min_score: float = 0.0, blocks: int | None = None) -> DataFrame:
    """(PAIR, score) of all pairs of a class from different sources with at least min_score."""
    spark = prof.sparkSession
    cores = spark.sparkContext.defaultParallelism
    sizes = prof.groupBy("cls").count().agg(F.count("*"), F.max("count")).first()
    if blocks is None:
        blocks = _blocks_of(sizes[1] or 0, cores)
    rows = prof.select("cls", "source", "prop", vector_of(prof).alias("vec"), F.pmod(F.xxhash64("cls", "source", "prop"), F.lit(blocks)).cast("int").alias("b"))
    packed = rows.groupBy("cls", "b").agg(F.collect_list(F.struct("source", "prop", "vec")).alias("members"))  # about BLOCK of them
    # A block goes to each of its tiles, and tiles are dealt to tasks by their own key; the class alone would be one hot key.
    # The number is given, so that adaptive execution doesn't put small but costly tiles together again.
    tiles = sizes[0] * blocks * (blocks + 1) // 2
    tasks = max(1, min(tiles, max(int(spark.conf.get("spark.sql.shuffle.partitions")), 4 * cores)))
    side = lambda own, other, places, name: (
        packed.select("cls", F.col("b").alias(own), F.explode(places).alias(other), F.col("members").alias(name)).repartition(tasks, "cls", "i", "j")
    )
    left = side("i", "j", F.sequence(F.col("b"), F.lit(blocks - 1)), "left")
    right = side("j", "i", F.sequence(F.lit(0), F.col("b")), "right")
    tiles = left.hint("merge").join(right, ["cls", "i", "j"]).select("cls", "i", "j", "left", "right")
    network, spec, d = model.network, model.spec, model.d

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in range(batch.num_rows):
                cls, i, j = (batch.column(k)[r].as_py() for k in range(3))
                sides = []
                for k in (3, 4):
                    m = batch.column(k)[r].values
                    sides.append((np.array(m.field("source").to_pylist()), np.array(m.field("prop").to_pylist()), np.array(m.field("vec").to_pylist(), dtype=float)))
                (sa, pa_, va), (sb, pb, vb) = sides
                for at in range(0, len(sa), max(1, 20_000 // max(1, len(sb)))):
                    stop = at + max(1, 20_000 // max(1, len(sb)))
                    x, y = np.meshgrid(np.arange(at, min(stop, len(sa))), np.arange(len(sb)), indexing="ij")
                    x, y = x.ravel(), y.ravel()
                    # Within one block, each unordered pair stands twice; the order of sources picks one.
                    ok = sa[x] < sb[y] if i == j else sa[x] != sb[y]
                    x, y = x[ok], y[ok]
                    if not len(x):
                        continue
                    flip = sa[x] > sb[y]
                    one = lambda p, q: np.where(flip, q, p)  # noqa: B023, E731
                    fv = lambda p, q: np.where(flip[:, None], q, p)  # noqa: B023, E731
                    na, nb = one(pa_[x], pb[y]), one(pb[y], pa_[x])
                    feats = pair_matrix(fv(va[x], vb[y]), fv(vb[y], va[x]), na.tolist(), nb.tolist(), spec.mode)
                    s = network.score(_cut(feats, spec, d))
                    keep = s >= min_score
                    cols = [one(sa[x], sb[y])[keep], na[keep], one(sb[y], sa[x])[keep], nb[keep]]
                    yield pa.RecordBatch.from_arrays([pa.array([cls] * int(keep.sum()), pa.string()), *[pa.array(c.tolist(), pa.string()) for c in cols], pa.array(s[keep])], names=[*PAIR_KEY, "score"])

    return tiles.mapInArrow(run, "cls string, source_a string, prop_a string, source_b string, prop_b string, score double")


def labelled_features(prof: DataFrame, labels: DataFrame, spec: MatcherSpec, d: int) -> tuple[np.ndarray, np.ndarray]:
    """Features and labels of the labelled pairs, in the order of their keys. They are bounded by MOST_TRAINING."""
    n = labels.count()
    if n > MOST_TRAINING:
        raise ValueError(f"{n} labelled pairs; sample at most {MOST_TRAINING} (sampling.training_pairs)")
    width = spec.config.width(d) if spec.mode != "concat" else 2 * (29 + 2 * d) + 8
    # Names of the pairs, and each property's vector once, however many pairs it is in.
    pairs = labels.select(*PAIR_KEY, "label").orderBy(*PAIR_KEY).toPandas()
    ends = labels.select("cls", F.inline(F.array(*[F.struct(F.col(f"source_{s}").alias("source"), F.col(f"prop_{s}").alias("prop")) for s in "ab"]))).distinct()
    held = prof.select(*PROPERTY_KEY, vector_of(prof).alias("vec")).join(ends, PROPERTY_KEY, "left_semi").toArrow().combine_chunks()
    at = {k: i for i, k in enumerate(zip(*[held.column(c).to_pylist() for c in PROPERTY_KEY], strict=True))}
    a, b = (np.array([at.get(k, -1) for k in zip(pairs["cls"], pairs[f"source_{s}"], pairs[f"prop_{s}"], strict=True)], dtype=int) for s in "ab")
    known = (a >= 0) & (b >= 0)
    if not known.any():
        return np.zeros((0, width)), np.zeros(0, dtype=int)
    vectors = pa.concat_arrays(held.column("vec").chunks).flatten().to_numpy(zero_copy_only=False).astype(float).reshape(held.num_rows, -1)
    pairs, a, b = pairs[known], a[known], b[known]
    names_a, names_b = pairs["prop_a"].tolist(), pairs["prop_b"].tolist()
    x = np.empty((len(pairs), width))
    for i in range(0, len(pairs), 20_000):
        j = i + 20_000
        x[i:j] = _cut(pair_matrix(vectors[a[i:j]], vectors[b[i:j]], names_a[i:j], names_b[i:j], spec.mode), spec, d)
    return x, pairs["label"].to_numpy(int)


class PropertyPairClassifier:
    """fit(instances, lexicon, labels) -> model; model.score() -> SIM."""

    def __init__(self, spec: MatcherSpec = MatcherSpec()):
        self.spec = spec

    def fit(self, instances: DataFrame, lexicon: DataFrame, labels: DataFrame) -> PropertyPairModel:
        s = self.spec
        return self.fit_profile(profile(instances, lexicon, s.aggregate, s.distinct_values, s.numeric_missing), labels)

    def fit_profile(self, prof: DataFrame, labels: DataFrame) -> PropertyPairModel:
        first = prof.select(F.size("name_emb")).first()
        d = first[0] if first else 0
        if self.spec.trainer == "mllib":
            return fit_mllib(prof, labels, self.spec, d)
        x, y = labelled_features(prof, labels, self.spec, d)
        if self.spec.mode in ("diff", "concat") and len(x):
            # These depend on the order of a pair; both orders are learned from.
            z = _mirrored(x, self.spec, d)
            x, y = np.concatenate([x, z]), np.concatenate([y, y])
        return PropertyPairModel(self.spec, fit(x, y, self.spec.network), d, prof)


def _mirrored(x: np.ndarray, spec: MatcherSpec, d: int) -> np.ndarray:
    if spec.mode == "concat":
        w = 29 + 2 * d
        return np.concatenate([x[:, w : 2 * w], x[:, :w], x[:, 2 * w :]], 1)
    plain = np.ones(29 + 2 * d + 8)
    plain[: 29 + 2 * d] = -1
    return x * _cut(plain[None, :], spec, d)


def fit_mllib(prof: DataFrame, labels: DataFrame, spec: MatcherSpec, d: int) -> PropertyPairModel:
    """The same layers trained by Spark's own perceptron (l-bfgs, sigmoid hidden units, no schedule): an approximation that
    trains over distributed rows. Its weights are read into the same scorer through an equal network."""
    from pyspark.ml.classification import MultilayerPerceptronClassifier
    from pyspark.ml.functions import array_to_vector

    from propalign.operators.pairs import assemble

    rows = assemble(prof, spec.mode, spec.config, d).join(labels.select(*PAIR_KEY, "label"), PAIR_KEY)
    width = spec.config.width(d)
    stats = rows.select(*[F.avg(F.col("features")[i]).alias(f"m{i}") for i in range(width)], *[F.stddev_pop(F.col("features")[i]).alias(f"s{i}") for i in range(width)]).first()
    mean = np.array([stats[f"m{i}"] or 0.0 for i in range(width)])
    scale = np.array([stats[f"s{i}"] if stats[f"s{i}"] and stats[f"s{i}"] > 1e-9 else 1.0 for i in range(width)])
    unit = F.zip_with(F.zip_with("features", F.array(*map(F.lit, mean.tolist())), lambda x, m: x - m), F.array(*map(F.lit, scale.tolist())), lambda x, s: x / s)
    layers = [width, *spec.network.hidden, 2]
    model = MultilayerPerceptronClassifier(layers=layers, blockSize=spec.network.batch, seed=spec.network.seed, maxIter=60).fit(rows.select(array_to_vector(unit).alias("features"), F.col("label").cast("double")))
    flat, at, weights, biases = model.weights.toArray(), 0, [], []
    for a, b in zip(layers, layers[1:], strict=False):
        weights.append(flat[at : at + a * b].reshape((b, a), order="F").T)
        at += a * b
        biases.append(flat[at : at + b])
        at += b
    return PropertyPairModel(spec, Network(spec.network, mean, scale, weights, biases, "sigmoid"), d, prof)

