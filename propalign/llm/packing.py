"""Best-fit packing: length patterns fitted to the histogram by non-negative least squares.

Documents are tokenised once; from then on only their pieces' lengths matter. A piece as long as a sequence is a sequence.
For the others, a histogram of lengths (as many numbers as a sequence has tokens, whatever the corpus) goes to the driver:

1. Patterns of at most three lengths that fill a sequence are enumerated.
2. Repeat counts x >= 0 that minimise the weighted squared difference between the pieces that the patterns use and the
   histogram are found by an accelerated projected gradient; short lengths weigh little, since they fill gaps.
3. The counts are rounded and cut to what there is of each length.
4. What remains is packed by best fit, longest first, for all pieces of a length at once.

The plan is a list of slots (length, range of ranks, first sequence, place), bounded by the number of patterns. Pieces
get their rank among those of their length from counts by input partition, and look up their slot.

Edge cases: a null or empty text is one piece, its end token. Repeated rows and ids are documents of their own, null ids
too. No documents give no pieces. Documents of any length are cut into whole sequences; their first piece may be shorter.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from propalign.llm.tables import materialise

LENGTH = 1024
END = 2
#: Weight of lengths under a 16th of the sequence in the fit.
SHORT_WEIGHT = 0.09
#: Words whose tokens a worker keeps.
CACHE = 400_000
_ODD_SPACE = re.compile(r"\s\s")


class Encoder(dict):
    """Tokens of whole texts as little-endian unsigned 32-bit bytes, with the tokens of words kept.

    A single space between two characters that aren't space always begins a token of this vocabulary's pattern, so texts
    are cut there and each part is encoded once. Other texts are encoded whole.
    """

    def __init__(self, path: str, special: str = "<|endoftext|>"):
        import base64

        import public_tokenizers
        import tiktoken

        super().__init__()
        with open(path.replace(".json", ".tiktoken"), "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.special = special
        self.of = tiktoken.Encoding("words", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={special: len(ranks)})

    def plain(self, text: str) -> bytes:
        return np.asarray(self.of.encode(text, allowed_special="all"), dtype="<u4").tobytes()

    def __missing__(self, part: str) -> bytes:
        ids = np.asarray(self.of.encode_ordinary(part), dtype="<u4").tobytes()
        if len(part) < 40:
            if len(self) >= CACHE:
                self.clear()
            self[part] = ids
        return ids

    def encode(self, text: str) -> bytes:
        if self.special in text:
            return self.plain(text)
        if _ODD_SPACE.search(text):
            # Cut only at single spaces.
            parts, at = [], 0
            for m in re.finditer(r"(?<=\S) (?=\S)", text):
                parts.append(text[at : m.start()])
                at = m.start()
            return b"".join(map(self.__getitem__, [*parts, text[at:]]))
        first, *rest = text.split(" ")
        if first == "" and rest:  # a leading space belongs to the word behind it
            first, rest = " " + rest[0], rest[1:]
        return b"".join(map(self.__getitem__, [first, *[" " + x for x in rest]]))


_encoders: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    if path not in _encoders:
        _encoders[path] = Encoder(path)
    return _encoders[path]


def pieces(docs: DataFrame, text: str = "text", key: str = "doc_id", path: str | None = None, length: int = LENGTH, end: int = END, keep_ids: bool = False) -> DataFrame:
    """(key, piece, start, length, ids_crc32, part, nth[, ids]): nth counts the pieces of a length within a partition."""
    if path is None:
        import public_tokenizers

        path = public_tokenizers.path("byte_bpe_50k.json")
    kind = docs.schema[key].dataType.simpleString()
    schema = f"`{key}` {kind}, piece int, start long, length long, ids_crc32 long, part int, nth long" + ", ids array<int>" * keep_ids

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, seen, tail = encoder(path), np.zeros(length + 1, dtype=np.int64), np.asarray([end], dtype="<u4").tobytes()
        for batch in batches:
            rows: list[list] = [[] for _ in range(6)]
            ids: list = []
            for i, doc in enumerate(batch.column(1).to_pylist()):
                b = (enc.encode(doc) if doc else b"") + tail
                n = len(b) // 4
                start, size, k = 0, (n - 1) % length + 1, 0
                while start < n:
                    own = b[4 * start : 4 * (start + size)]
                    for col, v in zip(rows, (i, k, start, size, zlib.crc32(own), seen[size]), strict=True):
                        col.append(v)
                    if keep_ids:
                        ids.append(np.frombuffer(own, dtype="<i4"))
                    seen[size] += 1
                    start, size, k = start + size, length, k + 1
            at = pa.array(rows[0], pa.int64())
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).take(at), pa.array(rows[1], pa.int32()), *[pa.array(rows[j], pa.int64()) for j in (2, 3, 4)], batch.column(2).take(at), pa.array(rows[5], pa.int64())]
                + ([pa.array(ids, pa.list_(pa.int32()))] if keep_ids else []),
                names=[key, "piece", "start", "length", "ids_crc32", "part", "nth"] + ["ids"] * keep_ids,
            )

    return docs.select(F.col(key), F.col(text), F.spark_partition_id().alias("part")).mapInArrow(run, schema)


def patterns(length: int) -> np.ndarray:
    """All sets of at most three lengths with the sum length, as rows of a <= b <= c; a missing length is 0."""
    b = np.arange(1, length // 2 + 1)
    two = np.stack([np.zeros_like(b), b, length - b], 1)
    three = []
    for a in range(1, length // 3 + 1):
        m = np.arange(a, (length - a) // 2 + 1)
        three.append(np.stack([np.full_like(m, a), m, length - a - m], 1))
    return np.concatenate([two, *three])


def fit_counts(rows: np.ndarray, histogram: np.ndarray, steps: int = 400) -> np.ndarray:
    """Repeat counts x >= 0 of the patterns: least weighted squares of (A x - histogram), by accelerated projected gradient."""
    length = len(histogram) - 1
    weight = np.where(np.arange(length + 1) < length // 16, SHORT_WEIGHT, 1.0)
    weight[0] = 0
    flat = rows.ravel()

    def used(x: np.ndarray) -> np.ndarray:
        return np.bincount(flat, weights=np.repeat(x, rows.shape[1]), minlength=length + 1)

    # The norm of A' W A by a few power steps.
    v = np.ones(len(rows))
    for _ in range(20):
        v = (weight * used(v))[rows].sum(1)
        norm = np.linalg.norm(v)
        v /= max(norm, 1e-300)
    # Starting from the pairs alone, each with the smaller of its two counts.
    x = np.where(rows[:, 0] == 0, np.minimum(histogram[rows[:, 1]], histogram[rows[:, 2]]), 0).astype(float)
    y, t = x.copy(), 1.0
    for _ in range(steps):
        grad = (weight * (used(y) - histogram))[rows].sum(1)
        new = np.maximum(0.0, y - grad / (1.05 * norm))
        t_new = (1 + np.sqrt(1 + 4 * t * t)) / 2
        y, x, t = new + (t - 1) / t_new * (new - x), new, t_new
    return x


def plan_slots(histogram: np.ndarray, length: int = LENGTH) -> tuple[list[tuple], int]:
    """((length, first rank, number, first sequence, place), ...) for all pieces shorter than a sequence, and the number of
    sequences. histogram: pieces of each length from 0 to length - 1."""
    left = np.zeros(length + 1, dtype=np.int64)
    left[: len(histogram)] = histogram
    left[length] = 0
    done, slots, sequences = np.zeros(length + 1, dtype=np.int64), [], 0

    def place(sizes: list[int], first: int, n: int) -> None:
        at = 0
        for size in sizes:
            slots.append((size, int(done[size]), n, first, at))
            done[size] += n
            left[size] -= n
            at += size

    if left.sum() == 0:
        return [], 0
    rows = patterns(length)
    counts = np.floor(fit_counts(rows, left.astype(float)) + 0.5).astype(np.int64)
    for i in np.argsort(-counts, kind="stable")[: int((counts > 0).sum())]:
        sizes = [int(s) for s in rows[i][::-1] if s]
        need = {s: sizes.count(s) for s in sizes}
        n = min(int(counts[i]), *(int(left[s]) // k for s, k in need.items()))
        if n > 0:
            place(sizes, sequences, n)
            sequences += n
    # The rest, longest first: gaps[g]: runs of (first sequence, number) with g tokens free.
    gaps: dict[int, list[tuple[int, int]]] = {}
    free = np.zeros(length + 1, dtype=bool)
    for size in range(length - 1, 0, -1):
        while left[size] > 0:
            fits = np.flatnonzero(free[size:])
            if len(fits):
                gap = size + int(fits[0])
                first, n = gaps[gap].pop()
                if not gaps[gap]:
                    free[gap] = False
                per = 1
            else:
                gap, per = length, max(1, min(length // size, int(left[size])))
                n = max(1, int(left[size]) // per)
                first, sequences = sequences, sequences + n
            take = min(n, int(left[size]) // per)
            for k in range(per):
                slots.append((size, int(done[size]), take, first, length - gap + k * size))
                done[size] += take
                left[size] -= take
            for g, f, m in ((gap - per * size, first, take), (gap, first + take, n - take)):
                if g > 0 and m > 0:
                    gaps.setdefault(g, []).append((f, m))
                    free[g] = True
    return slots, sequences


def pack(cut: DataFrame, length: int = LENGTH) -> DataFrame:
    """The pieces with ``sequence_id`` and ``offset``. cut: what pieces() gives; it is written once, since it is read thrice."""
    cut = materialise(cut)
    counts = cut.where(F.col("length") < length).groupBy("length", "part").agg(F.count("*").alias("n"))
    histogram = np.zeros(length, dtype=np.int64)
    for row in counts.groupBy("length").agg(F.sum("n").alias("n")).collect():  # at most a row for each length
        histogram[row["length"]] = row["n"]
    slots, sequences = plan_slots(histogram, length)
    ranked = counts.select(
        F.col("length").alias("_length"), F.col("part").alias("_part"),
        (F.sum("n").over(Window.partitionBy("length").orderBy("part")) - F.col("n")).alias("_before"),
    )
    table = np.array(sorted(slots) or [(0, 0, 0, 0, 0)], dtype=np.int64)
    # Sorted by length and rank: one search finds the slot of a piece.
    keys = table[:, 0] << 44 | table[:, 1]
    shared = cut.sparkSession.sparkContext.broadcast((table, keys))
    names = [c for c in cut.columns if c not in ("part", "nth")]
    short = cut.where(F.col("length") < length).join(ranked, (F.col("length") == F.col("_length")) & (F.col("part") == F.col("_part")))
    short = short.select(*names, (F.col("_before") + F.col("nth")).alias("rank"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        slot, key = shared.value
        at = names.index("length")
        for batch in batches:
            size, rank = batch.column(at).to_numpy(), batch.column(len(names)).to_numpy()
            k = np.searchsorted(key, size << 44 | rank, side="right") - 1
            yield pa.RecordBatch.from_arrays(
                [*batch.columns[:-1], pa.array(slot[k, 3] + rank - slot[k, 1]), pa.array(slot[k, 4])], names=[*names, "sequence_id", "offset"]
            )

    kinds = ", ".join(f"`{c}` {cut.schema[c].dataType.simpleString()}" for c in names)
    packed = short.mapInArrow(run, f"{kinds}, sequence_id long, offset long")
    whole = cut.where(F.col("length") >= length).select(
        *names,
        (F.lit(-1).cast("long") - (F.col("part").cast("long") * F.lit(1 << 33) + F.col("nth"))).alias("sequence_id"),
        F.lit(0).cast("long").alias("offset"),
    )
    return packed.unionByName(whole)


def sequences(packed: DataFrame, length: int = LENGTH) -> DataFrame:
    """(sequence_id, ids, doc_starts): the token sequences themselves, from pieces cut with keep_ids."""
    rows = packed.groupBy("sequence_id").agg(F.sort_array(F.collect_list(F.struct("offset", "ids"))).alias("x"))
    return rows.select("sequence_id", F.flatten(F.col("x.ids")).alias("ids"), F.col("x.offset").alias("doc_starts"))


def best_fit_packing(docs: DataFrame, text: str = "text", key: str = "doc_id", path: str | None = None, length: int = LENGTH, end: int = END, keep_ids: bool = False) -> DataFrame:
    return pack(pieces(docs, text, key, path, length, end, keep_ids), length)
