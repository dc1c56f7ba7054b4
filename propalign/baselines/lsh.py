"""Instance matchers by locality-sensitive hashing: MinHash of value words, and random projections of word counts.

Hashes are built from md5, which other SQL engines have. Signatures are folded in tasks before they are shuffled.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from propalign.functions.formats import pieces
from propalign.model import PAIR_KEY, PROPERTY_KEY

HASHES = {"minhash": 500, "projection": 1000}
#: Band sizes of the sweep.
BANDS = [*range(1, 11), *range(15, 55, 5)]
PRIME = (1 << 31) - 1
#: States that a task holds at a time: of 1000 numbers each, 32 MB.
HELD = 4_000
#: Words that a task gathers before it folds them, and those it hashes at a time (a block that stays in the cache).
GATHERED, BLOCK = 200_000, 128


def coefficients(n: int) -> list[tuple[int, int]]:
    """Multipliers and offsets below PRIME, from a rule."""
    a, out = 48271, []
    for _ in range(n):
        b = a * 48271 % PRIME
        out.append((a, b))
        a = b * 48271 % PRIME
    return out


def word_hash(word: str) -> int:
    """A number below PRIME, from the first 32 bits of the md5."""
    return int.from_bytes(hashlib.md5(word.encode("utf-8", "surrogatepass")).digest()[:4], "big") % PRIME


def occurrences(instances: DataFrame, element: str = "token") -> DataFrame:
    """(property, word, n = 1): a property's value words (or whole values), as often as they occur. Signatures are the same as from
    elements, since minima don't mind repeats and sums of signs add up; nothing is shuffled for them."""
    if element != "token":
        return instances.select(*PROPERTY_KEY, F.col("value").alias("word"), F.lit(1).cast("bigint").alias("n"))
    return instances.select(*PROPERTY_KEY, F.explode(pieces(F.col("value"))).alias("word"), F.lit(1).cast("bigint").alias("n")).where("word != ''")


def elements(instances: DataFrame, element: str = "token") -> DataFrame:
    """(property, word, n): the set of a property's value words (or whole values), with counts."""
    return occurrences(instances, element).groupBy(*PROPERTY_KEY, "word").agg(F.sum("n").alias("n"))


def signatures(elements_: DataFrame, hashes: dict[str, int]) -> DataFrame:
    """(property, state): for each variant in hashes, in one pass, so many minima or sums of signs over a property's words; one
    variant's numbers after the other's.

    Tasks fold their rows into states of some properties at a time, which are then brought together in the order of the
    properties and folded again: hundreds of plain aggregates would make code too large to compile.
    """
    n_hash = sum(hashes.values())
    upto = np.cumsum([0, *hashes.values()]).tolist()
    cuts = [(v, slice(i, j), np.minimum if v == "minhash" else np.add) for v, i, j in zip(hashes, upto, upto[1:], strict=False)]
    a, b = (np.array([x[k] for n in hashes.values() for x in coefficients(n)], dtype=np.uint64) for k in (0, 1))

    def states(h: np.ndarray, n: np.ndarray) -> np.ndarray:
        x = h.astype(np.uint64)[:, None] * a + b
        x -= x // np.uint64(PRIME) * np.uint64(PRIME)  # division by a constant is vectorised, the remainder isn't
        out = x.view(np.int64)
        for variant, cut, _ in cuts:
            if variant != "minhash":
                out[:, cut] = np.where(out[:, cut] & 1 == 0, n[:, None], -n[:, None])
        return out

    def fold(x: np.ndarray, y: np.ndarray) -> np.ndarray:
        return np.concatenate([f(x[cut], y[cut]) for _, cut, f in cuts])

    def batch_of(held: dict[tuple, np.ndarray]) -> pa.RecordBatch:
        keys = list(held)
        columns = [pa.array([k[i] for k in keys], pa.string()) for i in range(3)]
        values = pa.array(np.concatenate(list(held.values())) if held else np.zeros(0, dtype=np.int64), pa.int64())
        return pa.RecordBatch.from_arrays([*columns, pa.ListArray.from_arrays(pa.array(np.arange(len(keys) + 1) * n_hash, pa.int32()), values)], names=[*PROPERTY_KEY, "state"])

    def put(held: dict[tuple, np.ndarray], keys: list[tuple], code: np.ndarray, x: np.ndarray) -> None:
        """Folds the rows x, which are in the order of their codes, into the states of their keys."""
        starts = np.flatnonzero(np.concatenate([[True], np.diff(code) > 0]))
        for c, row in zip(code[starts], np.concatenate([f.reduceat(x[:, cut], starts) for _, cut, f in cuts], 1), strict=True):
            k = keys[c]
            held[k] = fold(held[k], row) if k in held else row

    def hashed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple, np.ndarray] = {}
        ids: dict[tuple, int] = {}
        parts: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []

        def take() -> Iterator[pa.RecordBatch]:
            code, h, n = (np.concatenate(x) for x in zip(*parts, strict=True))
            parts.clear()
            # A word that a property has many times is hashed once.
            both, place = np.unique(code << 31 | h, return_inverse=True)
            times = np.zeros(len(both), dtype=np.int64)
            np.add.at(times, place, n)
            keys = list(ids)
            for at in range(0, len(both), BLOCK):
                code = both[at : at + BLOCK] >> 31
                put(held, keys, code, states(both[at : at + BLOCK] & PRIME, times[at : at + BLOCK]))
                if len(held) > HELD:
                    yield batch_of(held)
                    held.clear()
            ids.clear()

        for batch in batches:
            if not batch.num_rows:
                continue
            columns = [batch.column(i).dictionary_encode() for i in range(3)]
            code = np.zeros(batch.num_rows, dtype=np.int64)
            for x in columns:
                code = code * len(x.dictionary) + x.indices.to_numpy()
            _, first, place = np.unique(code, return_index=True, return_inverse=True)
            keys = [tuple(x[int(i)].as_py() for x in columns) for i in first]
            known = np.array([ids.setdefault(k, len(ids)) for k in keys], dtype=np.int64)
            words = batch.column(3).dictionary_encode()
            h = np.array([word_hash(w) for w in words.dictionary.to_pylist()], dtype=np.int64)
            parts.append((known[place], h[words.indices.to_numpy()], batch.column(4).to_numpy()))
            if sum(len(p[0]) for p in parts) >= GATHERED:
                yield from take()
        if parts:
            yield from take()
        yield batch_of(held)

    def folded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple, np.ndarray] = {}
        for whole in batches:
            for at in range(0, whole.num_rows, 2000):
                batch = whole.slice(at, 2000)
                rows = list(zip(*[batch.column(i).to_pylist() for i in range(3)], strict=True))
                ids: dict[tuple, int] = {}
                code = np.array([ids.setdefault(k, len(ids)) for k in rows])
                # Rows come in order, so codes do, and only the last property can have more rows.
                put(held, list(ids), code, batch.column(3).flatten().to_numpy().reshape(-1, n_hash))
                if len(held) > HELD:
                    rest = {rows[-1]: held.pop(rows[-1])}
                    yield batch_of(held)
                    held = rest
        yield batch_of(held)

    schema = "cls string, source string, prop string, state array<bigint>"
    part = elements_.select(*PROPERTY_KEY, "word", "n").where("word is not null").mapInArrow(hashed, schema)
    return part.repartition(*PROPERTY_KEY).sortWithinPartitions(*PROPERTY_KEY).mapInArrow(folded, schema)


def signature_of(states: DataFrame, variant: str, hashes: dict[str, int]) -> DataFrame:
    """(property, sig array<bigint>) of one variant, from the states of signatures: minima, or signs (0 and 1) of the word counts
    projected on random +-1 vectors."""
    before = sum(list(hashes.values())[: list(hashes).index(variant)])
    own = F.slice("state", before + 1, hashes[variant])
    return states.select(*PROPERTY_KEY, (own if variant == "minhash" else F.transform(own, lambda s: (s >= 0).cast("bigint"))).alias("sig"))


def minhash(elements_: DataFrame, n_hash: int = HASHES["minhash"]) -> DataFrame:
    """(property, sig array<bigint>)."""
    return signature_of(signatures(elements_, {"minhash": n_hash}), "minhash", {"minhash": n_hash})


def projection(elements_: DataFrame, n_hash: int = HASHES["projection"]) -> DataFrame:
    """(property, sig array<bigint> of 0 and 1): signs of the word counts projected on random +-1 vectors."""
    return signature_of(signatures(elements_, {"projection": n_hash}), "projection", {"projection": n_hash})


def _bands_of(r: int, n_hash: int) -> Column:
    """The size, number and hash of each band of r rows."""
    band = lambda i: F.struct(F.lit(r).alias("band"), i.alias("no"), F.md5(F.array_join(F.slice(F.col("sig"), i * r + 1, F.lit(r)).cast("array<string>"), ",")).alias("key"))
    return F.transform(F.sequence(F.lit(0), F.lit(n_hash // r - 1)), band)


def banded(signatures: DataFrame, bands: list[int], n_hash: int) -> DataFrame:
    """(band, PAIR) of pairs that agree in a whole band, for each band size; a last partial band is left out.

    Bands are joined on their hash: no pair is looked at that shares none. All sizes go through one explode and one join, so the
    plan is as small for many sizes as for one.
    """
    rows = signatures.select(*PROPERTY_KEY, F.inline(F.concat(*[_bands_of(r, n_hash) for r in bands])))
    side = lambda s: rows.select("cls", "band", "no", "key", F.col("source").alias(f"source_{s}"), F.col("prop").alias(f"prop_{s}"))
    return side("a").join(side("b"), ["cls", "band", "no", "key"]).where("source_a < source_b").select("band", *PAIR_KEY).distinct()


def match(instances: DataFrame, variant: str = "minhash", n_hash: int | None = None, band: int = 1, element: str = "token") -> DataFrame:
    """SIM rows of the matching pairs: all pairs with a band in common. Score: the share of equal minima, or the cosine that
    the differing signs stand for."""
    n_hash = n_hash or HASHES[variant]
    sig = (minhash if variant == "minhash" else projection)(occurrences(instances, element), n_hash)
    pairs = banded(sig, [band], n_hash).drop("band")
    a = sig.withColumnsRenamed({"source": "source_a", "prop": "prop_a", "sig": "sa"})
    b = sig.withColumnsRenamed({"source": "source_b", "prop": "prop_b", "sig": "sb"})
    both = pairs.join(a, ["cls", "source_a", "prop_a"]).join(b, ["cls", "source_b", "prop_b"])
    equal = F.aggregate(F.zip_with("sa", "sb", lambda x, y: (x == y).cast("int")), F.lit(0), lambda s, x: s + x)
    score = equal / n_hash if variant == "minhash" else F.round(F.cos(F.lit(3.141592653589793) * (n_hash - equal) / n_hash), 9)
    return both.select(*PAIR_KEY, score.alias("score"), F.lit(True).alias("is_match"))


def candidate_chance(similarity: float, band: int, n_hash: int) -> float:
    """The chance that a pair of such similarity shares a band."""
    return 1 - (1 - similarity**band) ** (n_hash // band)
