"""Suffix-array dedup: every byte that a string of ``LENGTH`` bytes covers which also starts elsewhere; and passages, runs of
``WORDS`` whole words or more that also stand elsewhere, many of which are shorter in bytes.

A sorted list of all suffixes of a corpus would be many times its size. So suffixes are sorted only where a repeat can be:

1. *Anchors.* Each window of ``LENGTH`` bytes is owned by the leftmost smallest of the hashes of its ``GRAM``-byte
   substrings. Equal windows have equal owners at equal places. An anchor owns a run of windows; a corpus has about one anchor
   for 150 bytes, and only an anchor's hashes are shuffled. Anchors whose hash occurs once own no repeated window.
2. *Classes.* Occurrences of an anchor whose whole stretch (all bytes of the windows that it owns) is equal are one class, by
   the anchor's hash and a cryptographic digest of the stretch. A class of two or more is repeated throughout.
3. *Suffix sort.* One stretch of each class is brought to the others of its anchor. There, suffixes that start at the same
   distance from the anchor are sorted by mergesort; two are compared by prefix hashes, with binary search for their
   common extension, and neighbours that agree in LENGTH bytes are verified byte by byte.
4. *Large anchors.* An anchor with more than ``FEW`` different stretches is split into shorter runs of windows, keyed also by
   the hash of the bytes that all windows of the run share; these go through 2 and 3 again, down to single windows, which
   step 2 decides alone. So no group is large, and nothing is capped.

For passages, a text is also read as a sequence of words, each a 64-bit hash, and goes through the same steps with words in
the place of bytes. Space between words doesn't matter there.

Edge cases: a null text is empty; texts shorter than LENGTH keep all bytes. Repeated rows are repeats of each other (they
start elsewhere). Matches don't cross documents. Ids may be null or repeat, since texts are known by their md5 here. Texts of
any length are taken whole. No documents give no rows. Columns kept whose names are those of results are replaced; others may
have any name.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from propalign.llm.bytes_np import Prefix, mix, slices, word_codes, word_hashes
from propalign.llm.tables import kept_columns, materialise, release, schema_with

LENGTH = 400
GRAM = 100
#: Words of a passage, of the substrings whose hashes are anchors, and the bytes of a word's hash.
WORDS, WORD_GRAM, CODE = 50, 10, 8
FEW = 48
#: Windows in a run, level by level, for anchors with many stretches: of bytes, and of words.
RUNS, WORD_RUNS = (301, 40, 6, 1), (41, 12, 3, 1)
#: Bytes of text that are hashed at a time.
BLOCK = 1_000_000


def _slide_min(x: np.ndarray, width: int) -> np.ndarray:
    """Minima of all runs of so many numbers, from minima to both sides of every width-th place."""
    n = len(x)
    pad = -n % width
    y = np.concatenate([x, np.full(pad, np.iinfo(np.uint64).max, dtype=np.uint64)]).reshape(-1, width)
    ahead = np.minimum.accumulate(y, 1).ravel()
    back = np.minimum.accumulate(y[:, ::-1], 1)[:, ::-1].ravel()
    return np.minimum(back[: n - width + 1], ahead[width - 1 : n])


def anchors_of(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, length: int, gram: int) -> tuple[np.ndarray, ...]:
    """(text, anchor, first window, last window, hash of the gram), places in data. Texts lie at [starts, ends) of data, which
    holds bytes or words' hashes."""
    width = length - gram + 1
    n = len(data)
    if n < length:
        return (*(np.zeros(0, dtype=np.int64) for _ in range(4)), np.zeros(0, dtype=np.uint64))
    prefix = Prefix(data)
    at = np.arange(n - gram + 1)
    grams = mix(prefix.of(at, at + gram))
    low = np.uint64((1 << 34) - 1)  # place; 30 bits of hash decide before it, so equal windows have equal owners
    packed = grams & ~low | at.astype(np.uint64)
    owner = (_slide_min(packed, width) & low).astype(np.int64)  # of the window that starts at each place
    window = np.arange(len(owner))
    text = np.searchsorted(starts, window, side="right") - 1
    inside = window + length <= ends[text]
    new = np.ones(len(owner), dtype=bool)
    new[1:] = (owner[1:] != owner[:-1]) | ~inside[:-1] | (text[1:] != text[:-1])
    first = np.flatnonzero(new & inside)
    # A run ends before the next run's first window, or where its text's last window is.
    after = np.append(np.flatnonzero(new | ~inside), len(owner))
    last = after[np.searchsorted(after, first, side="right")] - 1
    a = owner[first]
    return text[first], a, first, last, grams[a]


def _digest(stretch: bytes, at: int) -> int:
    """A number for a stretch and where the anchor lies in it; 64 bits, beside the 64 of the anchor's own hash."""
    return int.from_bytes(hashlib.blake2b(stretch, digest_size=8, salt=at.to_bytes(8, "little")).digest(), "little", signed=True)


@dataclass(frozen=True)
class _Kind:
    """What texts are sequences of: bytes, or words. A sequence of words has its text's tid and a letter more."""

    mark: bytes
    length: int
    gram: int
    unit: int  # bytes of a symbol

    def symbols(self, raw: bytes) -> np.ndarray:
        return np.frombuffer(raw, dtype=np.uint8 if self.unit == 1 else np.uint64)

    def cut(self, raw: bytes | memoryview, start: int, stop: int) -> bytes | memoryview:
        return raw[start * self.unit : stop * self.unit]


def _is_words(tid: bytes) -> bool:
    return len(tid) > 16


def _anchor_rows(raw: list[bytes], tids: list[bytes], kind: _Kind) -> pa.RecordBatch:
    """The anchors of sequences that hold a window."""
    data = b"".join(raw)
    stops = np.cumsum([len(r) // kind.unit for r in raw])
    begins = np.concatenate([[0], stops[:-1]])
    text, a, first, last, g = anchors_of(kind.symbols(data), begins, stops, kind.length, kind.gram)
    view = memoryview(data)
    digests = [_digest(kind.cut(view, f, e + kind.length), k) for f, e, k in zip(first.tolist(), last.tolist(), (a - first).tolist(), strict=True)]
    return pa.RecordBatch.from_arrays(
        [
            pa.array(tids, pa.binary()).take(pa.array(text)), pa.array((first - begins[text]).astype(np.int64)), pa.array((a - first).astype(np.int32)),
            pa.array((last - first).astype(np.int32)), pa.array(g.view(np.int64)), pa.array(digests, pa.int64()),
        ],
        names=["tid", "first", "at", "more", "gram", "stretch"],
    )


def _anchors(raw: DataFrame, kinds: list[_Kind]) -> DataFrame:
    """raw: one binary column."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in slices(whole, 0, BLOCK):
                texts = [x or b"" for x in b.column(0).to_pylist()]
                tids = [hashlib.md5(x).digest() for x in texts]
                for kind in kinds:
                    raws = texts if kind.unit == 1 else word_codes(texts)
                    # Empty texts share their start with the next one; only texts that hold a window count.
                    real = [i for i, r in enumerate(raws) if len(r) >= kind.length * kind.unit]
                    if real:
                        yield _anchor_rows([raws[i] for i in real], [tids[i] + kind.mark for i in real], kind)

    return raw.mapInArrow(run, "tid binary, first long, at int, more int, gram long, stretch long")


# --- the suffix sort -------------------------------------------------------------------------------------------------


def extension(prefix: Prefix, a: np.ndarray, b: np.ndarray, limit: int) -> np.ndarray:
    """Bytes, up to limit, that the suffixes at a and b have in common: binary search over equal prefix hashes."""
    low, high = np.zeros(len(a), dtype=np.int64), np.full(len(a), limit, dtype=np.int64)
    while True:
        open_ = low < high
        if not open_.any():
            return low
        mid = (low + high + 1) >> 1
        same = prefix.of(a, a + mid) == prefix.of(b, b + mid)
        low = np.where(open_ & same, mid, low)
        high = np.where(open_ & ~same, mid - 1, high)


def suffix_less(data: np.ndarray, prefix: Prefix, a: np.ndarray, b: np.ndarray, limit: int) -> np.ndarray:
    """Whether the suffix at a sorts strictly before that at b, by their first limit bytes."""
    e = extension(prefix, a, b, limit)
    inside = e < limit
    k = np.minimum(e, limit - 1)
    return inside & (data[a + k] < data[b + k])


def suffix_sort(data: np.ndarray, prefix: Prefix, start: np.ndarray, group: np.ndarray, limit: int) -> np.ndarray:
    """The order of suffixes: by group (sorted already), then by their first limit bytes; a stable bottom-up mergesort.

    All runs of one size in all groups are merged together: an element's place is its own rank plus the number of elements
    of the other run before it, which a binary search over suffix comparisons finds.
    """
    n = len(start)
    order = np.arange(n)
    begin = np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1]]))
    size = np.diff(np.append(begin, n))
    base, total = np.repeat(begin, size), np.repeat(size, size)
    rank = np.arange(n) - base
    width = 1
    while width < (size.max() if n else 0):
        pair = rank // (2 * width)
        left = rank % (2 * width) < width
        mine = rank % width
        other = base + pair * 2 * width + np.where(left, width, 0)
        stop = np.minimum(other + width, base + total)
        low, high = np.zeros(n, dtype=np.int64), np.maximum(0, stop - other)
        while (live := np.flatnonzero(low < high)).size:
            mid = (low[live] + high[live]) >> 1
            x, y = start[order[live]], start[order[other[live] + mid]]
            # Equal suffixes: those of the left run come first.
            lf = left[live]
            before = np.zeros(len(live), dtype=bool)
            before[lf] = suffix_less(data, prefix, y[lf], x[lf], limit)
            before[~lf] = ~suffix_less(data, prefix, x[~lf], y[~lf], limit)
            low[live] = np.where(before, mid + 1, low[live])
            high[live] = np.where(before, high[live], mid)
        place = base + pair * 2 * width + mine + low
        merged = np.empty_like(order)
        merged[place] = order
        order = merged
        width *= 2
    return order


def repeated_starts(stretches: list[bytes], at: np.ndarray, more: np.ndarray, group: np.ndarray, kind: _Kind) -> tuple[np.ndarray, np.ndarray]:
    """(stretch, window within it) for each window that another stretch of its group has at the same distance from its anchor."""
    length = kind.length
    sizes = np.array([len(x) // kind.unit for x in stretches], dtype=np.int64)
    off = np.cumsum(sizes) - sizes
    data = kind.symbols(b"".join(stretches))
    prefix = Prefix(data)
    which = np.repeat(np.arange(len(stretches)), more + 1)
    window = np.arange(len(which)) - np.repeat(np.cumsum(more + 1) - (more + 1), more + 1)
    start = off[which] + window
    bucket = group[which].astype(np.int64) << 32 | (at[which] - window + (1 << 20))
    by = np.argsort(bucket, kind="stable")
    which, window, start, bucket = which[by], window[by], start[by], bucket[by]
    alone = np.ones(len(bucket), dtype=bool)
    same = bucket[1:] == bucket[:-1]
    alone[1:] &= ~same
    alone[:-1] &= ~same
    which, window, start, bucket = (x[~alone] for x in (which, window, start, bucket))
    order = suffix_sort(data, prefix, start, bucket, length)
    s, b = start[order], bucket[order]
    near = np.flatnonzero(b[1:] == b[:-1])
    equal = near[extension(prefix, s[near], s[near + 1], length) >= length]
    # Verification of what the hashes say; neighbouring windows overlap, so bytes are compared by stretches of equal shift.
    good = np.zeros(len(equal), dtype=bool)
    for at_ in range(0, len(equal), 4_000):
        part = equal[at_ : at_ + 4_000]
        span = np.arange(length)
        good[at_ : at_ + 4_000] = (data[s[part][:, None] + span] == data[s[part + 1][:, None] + span]).all(1)
    hit = np.zeros(len(order), dtype=bool)
    hit[equal[good]] = True
    hit[equal[good] + 1] = True
    return which[order[hit]], window[order[hit]]


def _sorted_spans(pool: DataFrame, kinds: list[_Kind]) -> DataFrame:
    """(tid, start, stop) of windows that the suffix sort finds. pool: (gram, tid, first, at, more, n, bytes), few of a gram."""

    def found(rows: list[tuple], kind: _Kind) -> pa.RecordBatch:
        tid, start, stop = [], [], []
        if rows:
            grams = np.array([r[0] for r in rows])
            group = np.concatenate([[0], np.cumsum(grams[1:] != grams[:-1])])
            w, k = repeated_starts([r[6] for r in rows], np.array([r[3] for r in rows]), np.array([r[4] for r in rows]), group, kind)
            by = np.lexsort((k, w))
            w, k = w[by], k[by]
            cut = np.flatnonzero(np.concatenate([[True], (w[1:] != w[:-1]) | (k[1:] > k[:-1] + 1)])) if len(w) else np.zeros(0, dtype=int)
            for i, j in zip(cut, np.append(cut[1:], len(w))[: len(cut)], strict=True):
                r = rows[w[i]]
                if r[5] == 1:
                    tid.append(r[1])
                    start.append(r[2] + int(k[i]))
                    stop.append(r[2] + int(k[j - 1]) + kind.length)
        return pa.RecordBatch.from_arrays([pa.array(tid, pa.binary()), pa.array(start, pa.int64()), pa.array(stop, pa.int64())], names=["tid", "start", "stop"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # Bytes and words apart; both come in the order of their grams.
        rows: list[list] = [[] for _ in kinds]
        held = [0] * len(kinds)
        for batch in batches:
            for row in zip(*[c.to_pylist() for c in batch.columns], strict=True):
                k = int(_is_words(row[1]))
                if held[k] >= BLOCK and rows[k][-1][0] != row[0]:
                    yield found(rows[k], kinds[k])
                    rows[k].clear()
                    held[k] = 0
                rows[k].append(row)
                held[k] += len(row[6])
        for own, kind in zip(rows, kinds, strict=True):
            yield found(own, kind)

    return pool.repartition("gram").sortWithinPartitions("gram").select("gram", "tid", "first", "at", "more", "n", "bytes").mapInArrow(run, "tid binary, start long, stop long")


def _finer(pool: DataFrame, kinds: list[_Kind], run_sizes: list[int]) -> DataFrame:
    """pool's stretches cut into runs of at most run_size windows, keyed by anchor, distance and the bytes all windows share."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[list] = [[] for _ in range(8)]
            for gram, tid, first, at, more, n, raw in zip(*[c.to_pylist() for c in batch.columns], strict=True):
                kind, run_size = kinds[_is_words(tid)], run_sizes[_is_words(tid)]
                prefix = Prefix(kind.symbols(raw))
                # Runs are cut at multiples of run_size of the distance from window to anchor, the same for all stretches.
                d_high, d_low = at, at - more
                for q in range(d_low // run_size, d_high // run_size + 1):
                    hi, lo = min(d_high, q * run_size + run_size - 1), max(d_low, q * run_size)
                    w0, w1 = at - hi, at - lo  # first and last window of the run
                    # All windows of a run share these bytes, also where the stretch has only a part of the run.
                    a, b = at - q * run_size, at - q * run_size - run_size + 1 + kind.length
                    core = int(prefix.of(np.array([a]), np.array([b]))[0])
                    key = int(mix(np.array([(gram & (2**64 - 1)) ^ core], dtype=np.uint64) + np.uint64(q % 2**32))[0])
                    cut = kind.cut(raw, w0, w1 + kind.length)
                    for col, v in zip(out, (key, tid, first + w0, at - w0, w1 - w0, n, cut, _digest(cut, at - w0)), strict=True):
                        col.append(v)
            signed = lambda xs: pa.array(np.array(xs, dtype=np.uint64).view(np.int64))
            yield pa.RecordBatch.from_arrays(
                [signed(out[0]), pa.array(out[1], pa.binary()), pa.array(out[2], pa.int64()), pa.array(out[3], pa.int32()), pa.array(out[4], pa.int32()), pa.array(out[5], pa.int64()), pa.array(out[6], pa.binary()), pa.array(out[7], pa.int64())],
                names=["gram", "tid", "first", "at", "more", "n", "bytes", "stretch"],
            )

    return pool.select("gram", "tid", "first", "at", "more", "n", "bytes").mapInArrow(run, "gram long, tid binary, first long, at int, more int, n long, bytes binary, stretch long")


def repeated_spans(docs: DataFrame, text: str = "text", length: int = LENGTH, gram: int = GRAM, words: int = WORDS) -> DataFrame:
    """(tid, start, stop): repeated byte ranges of the text whose md5 is tid; they may overlap or touch. Where tid has a letter
    more, they are ranges of the sequence of its words. words: 0 for no passages."""
    kinds_of = [_Kind(b"", length, gram, 1)] + ([_Kind(b"w", words, min(WORD_GRAM, words), CODE)] if words else [])
    raw = docs.select(F.coalesce(F.col(text), F.lit("")).cast("binary").alias("raw"))
    every = materialise(_anchors(raw, kinds_of))
    often = every.groupBy("gram").agg(F.count("*").alias("k")).where("k > 1").select("gram")
    # Written, so that the join has an exchange on both sides and its large keys can be split.
    often = materialise(often)
    # Occurrences in equal texts are told once, with their number.
    seen = materialise(every.join(often, "gram").groupBy("tid", "first", "at", "more", "gram", "stretch").agg(F.count("*").alias("n")))
    release(every, often)
    size = F.when(F.length("tid") > 16, words).otherwise(length)
    spans = None
    for level in range(len(RUNS)):
        last = RUNS[level] == 1
        kinds = seen.groupBy("gram", "stretch").agg(F.sum("n").alias("total"), F.min(F.struct("tid", "first", "at", "more")).alias("x"))
        kinds = materialise(kinds)
        whole = seen.where("n = 1" if level else "true").join(kinds.where("total > 1").select("gram", "stretch"), ["gram", "stretch"])
        # tid's own copies counted with n; a class is repeated if it has two occurrences anywhere.
        got = whole.select("tid", F.col("first").alias("start"), (F.col("first") + F.col("more") + size).alias("stop"))
        spans = got if spans is None else spans.unionByName(got)
        if last:
            break
        groups = kinds.groupBy("gram").agg(F.count("*").alias("classes"), F.min("total").alias("least")).where("classes > 1 and least = 1").drop("least")
        groups = materialise(groups)
        pool = kinds.join(groups, "gram").select("gram", "x.*", F.col("total").alias("n"), "classes")
        if level == 0:
            pool = _with_bytes(raw, materialise(pool), kinds_of)
        else:
            pool = pool.join(seen.select("gram", "tid", "first", "at", "more", "bytes"), ["gram", "tid", "first", "at", "more"])
        pool = materialise(pool)
        spans = spans.unionByName(_sorted_spans(pool.where(F.col("classes") <= FEW), kinds_of))
        large = pool.where(F.col("classes") > FEW)
        if large.isEmpty():
            break
        seen = materialise(_finer(large, kinds_of, [RUNS[level + 1], WORD_RUNS[level + 1]]))
    return spans.distinct()


def _with_bytes(raw: DataFrame, pool: DataFrame, kinds: list[_Kind]) -> DataFrame:
    """pool with the bytes of each stretch. Of equal texts, one is read."""
    # What is wanted of a text is bounded by its length.
    fields = ["tid", "first", "at", "more", "gram", "n", "classes"]
    asked = materialise(pool.groupBy(F.substring("tid", 1, 16).alias("md5")).agg(F.collect_list(F.struct(*fields)).alias("asked")))
    texts = raw.withColumn("md5", F.unhex(F.md5("raw"))).join(asked.select("md5"), "md5", "left_semi").dropDuplicates(["md5"])
    schema = pool.select(*fields).schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for x, found in zip(batch.column(0), batch.column(1), strict=True):
                sequences, rows = {False: x.as_py()}, found.values
                cut = []
                for tid, first, more in zip(*[rows.field(f).to_pylist() for f in ("tid", "first", "more")], strict=True):
                    k = _is_words(tid)
                    if k not in sequences:
                        sequences[k] = word_codes([sequences[False]])[0]
                    cut.append(kinds[k].cut(sequences[k], first, first + more + kinds[k].length))
                yield pa.RecordBatch.from_arrays([*[rows.field(f) for f in fields], pa.array(cut, pa.binary())], names=[*fields, "bytes"])

    return texts.join(asked, "md5").select("raw", "asked").mapInArrow(run, schema_with(schema.fields, "bytes binary"))


def _merged(spans: list[dict] | None) -> list[list[int]]:
    """Sorted spans that overlap or touch, as one each."""
    out: list[list[int]] = []
    for s in spans or ():
        if out and s["start"] <= out[-1][1]:
            out[-1][1] = max(out[-1][1], s["stop"])
        else:
            out.append([s["start"], s["stop"]])
    return out


def _passages(raw: bytes, spans: list[dict]) -> list[list[int]]:
    """Byte ranges of the text for spans of its words."""
    _, start, stop, _ = word_hashes([raw])
    return [[int(start[a]), int(stop[b - 1])] for a, b in _merged(spans)]


def suffix_dedup(docs: DataFrame, text: str = "text", keep: tuple[str, ...] = ("doc_id",), length: int = LENGTH, gram: int = GRAM, words: int = WORDS) -> DataFrame:
    """The columns keep, with kept (bytes that remain), n_bytes, spans (array of removed [start, stop), maximal) and passages
    (array of [start, stop) in bytes: maximal runs of at least so many words that also stand elsewhere; words: 0 for none)."""
    found = repeated_spans(docs, text, length, gram, words)
    spans_of = lambda kind: F.sort_array(F.collect_list(F.when((F.length("tid") > 16) == kind, F.struct("start", "stop"))))
    # A text's spans are bounded by its own length.
    per = materialise(found.groupBy(F.substring("tid", 1, 16).alias("md5")).agg(spans_of(False).alias("spans"), spans_of(True).alias("runs")))
    keep = kept_columns(docs, keep, ("kept", "n_bytes", "spans", "passages"))
    rows = docs.select(F.struct(*keep).alias("row"), F.coalesce(F.col(text), F.lit("")).cast("binary").alias("raw"))
    rows = rows.withColumn("md5", F.unhex(F.md5("raw"))).join(per, "md5", "left").select("row", "raw", "spans", "runs")
    span = pa.list_(pa.struct([("start", pa.int64()), ("stop", pa.int64())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        told = lambda xs: pa.array([[{"start": s, "stop": e} for s, e in x] for x in xs], span)
        for b in (s for whole in batches for s in slices(whole, 1, BLOCK)):
            kept, sizes, out, passages = [], [], [], []
            for raw, spans, runs in zip(*[b.column(k).to_pylist() for k in (1, 2, 3)], strict=True):
                merged = _merged(spans)
                at, parts = 0, []
                for start, stop in merged:
                    parts.append(raw[at:start])
                    at = stop
                parts.append(raw[at:])
                kept.append(b"".join(parts))
                sizes.append(len(raw))
                out.append(merged)
                passages.append(_passages(raw, runs) if runs else [])
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(kept, pa.binary()), pa.array(sizes, pa.int64()), told(out), told(passages)], names=["row", "kept", "n_bytes", "spans", "passages"])

    spans = "array<struct<start: bigint, stop: bigint>>"
    return rows.mapInArrow(run, schema_with([rows.schema["row"]], f"kept binary, n_bytes long, spans {spans}, passages {spans}")).select("row.*", "kept", "n_bytes", "spans", "passages")
