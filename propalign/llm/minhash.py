"""MinHash near-duplicates by a multi-index Hamming join, with links confirmed on whole shingle sets.

A signature has ``HASHES`` symbols of ``BITS`` bits, the low bits of minima over a document's shingle hashes. It is split
into ``CHUNKS`` chunks, and each chunk is looked up with every way of leaving out up to ``ERRORS`` symbols. By pigeonhole
two signatures that differ in at most ``CHUNKS * (ERRORS + 1) - 1`` symbols (31 of 80) share one of these keys, so every
such pair is found. Pairs beyond are found too if any one chunk is close enough: of pairs with similarity 0.75, all but
one in ten million. The threshold on signatures is ``LOOSE`` symbols (similarity 0.75 has 20 on average with a deviation of
3.9, so one pair in 10^15 lies beyond; ``loose=HASHES`` drops none); all candidates within it are confirmed on the full sets.
No partner or bucket is capped.

Only components matter, so pairs are not expanded:

1. Documents with equal sets are one class.
2. A bucket's leader is its class that meets most others over all buckets. Two classes that share a bucket share its leader,
   so the groups of classes by leader hold every candidate pair, most of them once. Each class is tried against the closest
   of its leaders.
3. Groups that still hold two components are compared across components in blocks (pairs of blocks, where they are large),
   inside tasks: first by signatures, to find the classes that have a near partner in another component at all; then
   exactly, by the sets of those. A task returns only links that join two components.

Edge cases: a null or empty text or one without words has no shingle and links with nothing, its component is its own id;
fewer words than a shingle make one of all. Repeated rows are exact copies; a repeated id keeps all its rows, and a row
with a null id joins its component but is kept only if its component has no id at all. Texts of any length are taken whole;
no documents give no rows. Only the key and the text are read, so other columns may have any name.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from itertools import combinations

import hashlib

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from propalign.llm.bytes_np import give_back, mix, shingle_sets, slices
from propalign.llm.components import components, roots
from propalign.llm.tables import materialise, release, schema_with

WORDS = 5
SHARE = (75, 100)
HASHES, BITS, CHUNKS, ERRORS = 80, 16, 16, 1
LOOSE = 56
#: Leaders of open groups (some 20 bytes each), of which so many are broadcast; more are shuffled.
BROADCAST_LEADERS = 1_000_000
#: Members of a block.
BLOCK = 512
#: Classes whose bucket keys a task makes.
TASK_CLASSES = 50_000

_rng = np.random.default_rng(911)
_MULTIPLY = _rng.integers(1, 2**63, size=HASHES, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_ADD = _rng.integers(1, 2**63, size=HASHES, dtype=np.uint64)


def signature(shingles: np.ndarray) -> np.ndarray:
    """HASHES symbols of BITS bits. Minima over hashes of the upper 32 bits; then the minima's low bits."""
    least = np.full(HASHES, np.iinfo(np.uint64).max, dtype=np.uint64)
    for at in range(0, len(shingles), 512):  # blocks that stay in the cache
        x = shingles[at : at + 512, None] * _MULTIPLY[None, :] + _ADD[None, :]
        np.minimum(least, x.min(0), out=least)
    # The multiply's low bits are weak, so the minimum as a whole is mixed before it is cut.
    return (mix(least) >> np.uint64(64 - BITS)).astype(np.uint16)


_WIDTH = HASHES // CHUNKS
_MASKS = [np.array(m) for m in combinations(range(_WIDTH), _WIDTH - ERRORS)]


def keys_of(sig: np.ndarray) -> np.ndarray:
    """The bucket keys of a signature: of every chunk, every choice of all but ERRORS symbols."""
    parts = sig.reshape(CHUNKS, _WIDTH).astype(np.uint64)
    out = []
    for m, mask in enumerate(_MASKS):
        packed = np.zeros(CHUNKS, dtype=np.uint64)
        for j in mask:
            packed = packed << np.uint64(BITS) | parts[:, j]
        tag = np.arange(CHUNKS, dtype=np.uint64) * np.uint64(len(_MASKS)) + np.uint64(m + 1)
        out.append(mix(packed ^ mix(tag * np.uint64(0x9E3779B97F4A7C15))))
    return np.concatenate(out).view(np.int64)


def signed(docs: DataFrame) -> DataFrame:
    """(id, uid, digest: of the text, n_shingles, same: digest of the set, sig): uid numbers the rows. docs: (id, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in slices(whole, 1):
                texts = b.column(1).to_pylist()
                sets = shingle_sets(texts, WORDS)
                yield pa.RecordBatch.from_arrays(
                    [
                        b.column(0),
                        pa.array([None if t is None else hashlib.md5(t.encode("utf-8", "surrogatepass")).digest() for t in texts], pa.binary()),
                        pa.array([len(s) for s in sets], pa.int64()),
                        pa.array([hashlib.blake2b(s.tobytes(), digest_size=16).digest() if len(s) else None for s in sets], pa.binary()),
                        pa.array([signature(s).tobytes() if len(s) else None for s in sets], pa.binary()),
                    ],
                    names=["id", "digest", "n_shingles", "same", "sig"],
                )
        give_back()

    rows = docs.mapInArrow(run, schema_with([docs.schema["id"]], "digest binary, n_shingles long, same binary, sig binary"))
    return rows.withColumn("uid", F.monotonically_increasing_id())


def _bucket_keys(classes: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            sig = np.array([np.frombuffer(x, dtype=np.uint16) for x in b.column(1).to_pylist()]).reshape(-1, HASHES)
            keys = np.concatenate([keys_of(s) for s in sig]) if len(sig) else np.zeros(0, dtype=np.int64)
            per = len(_MASKS) * CHUNKS
            yield pa.RecordBatch.from_arrays([pa.array(keys), pa.array(np.repeat(b.column(0).to_numpy(), per))], names=["bucket", "c"])
        give_back()

    return classes.select("c", "sig").mapInArrow(run, "bucket long, c long")


def _differ(a: pa.Array, b: pa.Array) -> np.ndarray:
    x = np.array([np.frombuffer(v, dtype=np.uint16) for v in a.to_pylist()]).reshape(-1, HASHES)
    y = np.array([np.frombuffer(v, dtype=np.uint16) for v in b.to_pylist()]).reshape(-1, HASHES)
    return (x != y).sum(1)


def _near(pairs: DataFrame, classes: DataFrame, loose: int) -> DataFrame:
    """(a, b, apart) of pairs whose signatures differ in at most loose symbols."""
    sig = classes.select("c", "sig")
    both = pairs.join(sig.withColumnsRenamed({"c": "a", "sig": "sa"}), "a").join(sig.withColumnsRenamed({"c": "b", "sig": "sb"}), "b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            apart = pa.array(_differ(b.column(2), b.column(3)).astype(np.int32), pa.int32())
            out = pa.RecordBatch.from_arrays([b.column(0), b.column(1), apart], names=["a", "b", "apart"])
            yield out.filter(pa.compute.less_equal(apart, loose))

    return both.select("a", "b", "sa", "sb").mapInArrow(run, "a long, b long, apart int")


def _sets(wanted: DataFrame, docs: DataFrame, members: DataFrame) -> DataFrame:
    """(c, shingles) of the classes wanted (c), from their documents' whole texts. members: (c, same, m_id), one document of
    each class."""
    known = wanted.distinct().join(members, "c")
    texts = docs.join(known, F.col("id").eqNullSafe(F.col("m_id"))).select("c", "same", "text")

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in slices(whole, 2):
                found = [s.tobytes() for s in shingle_sets(b.column(2).to_pylist(), WORDS)]
                # An id may have several texts; only that of the class counts.
                right = [hashlib.blake2b(s, digest_size=16).digest() == d for s, d in zip(found, b.column(1).to_pylist(), strict=True)]
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(found, pa.binary())], names=["c", "shingles"]).filter(pa.array(right))
        give_back()

    # Rows that repeat an id and its text give the same set again.
    return materialise(texts.mapInArrow(sets, "c long, shingles binary").dropDuplicates(["c"]))


def _confirmed(pairs: DataFrame, full: DataFrame) -> DataFrame:
    """Those of pairs (a, b) whose full shingle sets (c, shingles) are similar enough."""

    def agree(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        up, down = SHARE
        for b in batches:
            ok = []
            for x, y in zip(b.column(2).to_pylist(), b.column(3).to_pylist(), strict=True):
                x, y = np.frombuffer(x, dtype=np.uint64), np.frombuffer(y, dtype=np.uint64)
                both = len(np.intersect1d(x, y, assume_unique=True))
                ok.append(down * both >= up * (len(x) + len(y) - both))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1)], names=["a", "b"]).filter(pa.array(ok, pa.bool_()))

    joined = pairs.join(full.withColumnsRenamed({"c": "a", "shingles": "xa"}), "a").join(full.withColumnsRenamed({"c": "b", "shingles": "xb"}), "b")
    return joined.select("a", "b", "xa", "xb").mapInArrow(agree, "a long, b long")


def _block_pairs(rows: DataFrame, carried: str, few: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """(g, lead, c, label, carried): rows (lead, c, label, carried) dealt to groups g that hold two blocks of a leader's group.
    few: what to do with a table of one row a leader before it is joined.

    A component with more than a block's members gets blocks of its own, the others share blocks. Every pair of blocks
    that may hold two components is a group; a row goes once to each pair of blocks that it is in.
    """
    size = rows.groupBy("lead", "label").agg(F.count("*").alias("n"))
    rest = size.where(F.col("n") <= BLOCK).groupBy("lead").agg(F.ceil(F.sum("n") / BLOCK).cast("int").alias("pools"))
    part = size.join(few(rest), "lead", "left").select(
        "lead", "label",
        F.when(F.col("n") > BLOCK, F.col("label")).otherwise(F.lit(-1)).alias("own"),
        F.when(F.col("n") > BLOCK, F.ceil(F.col("n") / BLOCK).cast("int")).otherwise(F.col("pools")).alias("parts"),
    )
    blocks = part.select("lead", "own", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("k")).distinct()
    left = blocks.withColumnsRenamed({"own": "o1", "k": "k1"})
    right = blocks.withColumnsRenamed({"own": "o2", "k": "k2"})
    ordered = (F.col("o1") < F.col("o2")) | ((F.col("o1") == F.col("o2")) & (F.col("o1") == -1) & (F.col("k1") <= F.col("k2")))
    groups = left.join(right, "lead").where(ordered).withColumn("g", F.xxhash64("lead", "o1", "k1", "o2", "k2"))
    sides = groups.select(
        "lead", "g",
        F.explode(F.array_distinct(F.array(F.struct(F.col("o1").alias("own"), F.col("k1").alias("k")), F.struct(F.col("o2").alias("own"), F.col("k2").alias("k"))))).alias("x"),
    ).select("lead", "g", "x.own", "x.k")
    dealt = rows.join(part, ["lead", "label"]).withColumn("k", F.pmod(F.xxhash64("c"), F.col("parts")).cast("int"))
    # A group has two blocks' rows at most, so its rows can be brought together.
    return dealt.join(sides, ["lead", "own", "k"]).select("g", "lead", "c", "label", carried).repartition("g").sortWithinPartitions("g")


def _by_group(batches: Iterator[pa.RecordBatch]) -> Iterator[list[tuple]]:
    """Rows of one group at a time, from batches in the order of the groups."""
    held: list[tuple] = []
    for batch in batches:
        for row in zip(*[col.to_pylist() for col in batch.columns], strict=True):
            if held and held[0][0] != row[0]:
                yield held
                held = []
            held.append(row)
    if held:
        yield held


def _with_partner(rows: DataFrame, few: Callable[[DataFrame], DataFrame], loose: int) -> DataFrame:
    """(lead, c) of classes with a class of another component in their group whose signature is near. rows: (lead, c, label, sig)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for group in _by_group(batches):
            label, sig = np.array([r[3] for r in group]), np.array([np.frombuffer(r[4], dtype=np.uint16) for r in group])
            near = np.zeros(len(group), dtype=bool)
            for i in range(len(group) - 1):
                ok = ((sig[i + 1 :] != sig[i]).sum(1) <= loose) & (label[i + 1 :] != label[i])
                near[i] |= ok.any()
                near[i + 1 :] |= ok
            at = np.flatnonzero(near)
            yield pa.RecordBatch.from_arrays([pa.array([group[i][1] for i in at], pa.int64()), pa.array([group[i][2] for i in at], pa.int64())], names=["lead", "c"])

    return _block_pairs(rows, "sig", few).mapInArrow(run, "lead long, c long").distinct()


def _joining_links(rows: DataFrame, few: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """(a, b): confirmed links that join two components of a group. rows: (lead, c, label, shingles)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        up, down = SHARE
        for group in _by_group(batches):
            sets = [np.frombuffer(r[4], dtype=np.uint64) for r in group]
            sizes = np.array([len(s) for s in sets])
            flat, off = np.concatenate(sets), np.concatenate([[0], np.cumsum(sizes)])
            labels, label = np.unique([r[3] for r in group], return_inverse=True)
            root = np.arange(len(labels))  # of each component, kept flat
            a, b = [], []
            for i in range(len(group) - 1):
                mine = root[label[i]]
                rest = np.arange(i + 1, len(group))
                # Sizes alone rule out many.
                rest = rest[(root[label[rest]] != mine) & (down * np.minimum(sizes[rest], sizes[i]) >= up * np.maximum(sizes[rest], sizes[i]))]
                if not len(rest):
                    continue
                x = flat if len(rest) > 0.7 * len(group) else np.concatenate([sets[j] for j in rest])
                where = off[:-1][rest] if x is flat else np.cumsum(sizes[rest]) - sizes[rest]
                own = sets[i]
                at = np.minimum(np.searchsorted(own, x), len(own) - 1)
                hits = np.concatenate([[0], np.cumsum(own[at] == x)])
                both = hits[where + sizes[rest]] - hits[where]
                for j in rest[down * both >= up * (sizes[rest] + sizes[i] - both)]:
                    if root[label[j]] != root[label[i]]:
                        root[root == root[label[j]]] = root[label[i]]
                        a.append(min(group[i][2], group[j][2]))
                        b.append(max(group[i][2], group[j][2]))
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])

    return _block_pairs(rows, "shingles", few).mapInArrow(run, "a long, b long").distinct()


def _components(docs: DataFrame, loose: int) -> tuple[DataFrame, DataFrame]:
    """(id, uid, digest, n_shingles, same) of each row, and (same, label) of each set. docs: (id, text)."""
    base = materialise(signed(docs))
    classes = base.where("same is not null").groupBy("same").agg(F.min("uid").alias("c"), F.max("sig").alias("sig"), F.min(F.struct("uid", "id")).alias("x"))
    classes = materialise(classes.select("c", "same", "sig", F.col("x.id").alias("m_id")))
    members = classes.select("c", "same", "m_id")
    # A class has 80 keys; so tasks are cut by classes, not by their bytes.
    buckets = _bucket_keys(classes.repartition(max(2 * docs.sparkSession.sparkContext.defaultParallelism, classes.count() // TASK_CLASSES + 1)))
    # Only keys that two classes share matter. Tables are written so that the joins have an exchange on both sides and large
    # keys can be split.
    shared = materialise(buckets.groupBy("bucket").agg(F.count("*").alias("n")).where("n > 1"))
    rows = materialise(buckets.join(shared, "bucket"))
    weight = materialise(rows.groupBy("c").agg(F.sum("n").alias("w")))
    leader = materialise(rows.join(weight, "c").groupBy("bucket").agg(F.max(F.struct("w", F.col("c").alias("lead"))).alias("x")).select("bucket", "x.lead"))
    groups = materialise(rows.join(leader, "bucket").select("lead", "c").distinct())
    release(shared, rows, weight, leader)
    near = _near(groups.where("c != lead").select(F.col("lead").alias("a"), F.col("c").alias("b")), classes, loose)
    closest = materialise(near.groupBy("b").agg(F.min(F.struct("apart", "a")).alias("x")).select(F.col("x.a").alias("a"), "b"))
    # A leader meets more classes than its followers (ties by number), so these links are a forest.
    links = _confirmed(closest, _sets(closest.select(F.explode(F.array("a", "b")).alias("c")), docs, members))
    label = materialise(roots(links.select(F.col("b").alias("node"), F.col("a").alias("parent"))))
    named = groups.join(label, groups["c"] == label["node"], "left").select("lead", "c", F.coalesce("label", "c").alias("label"))
    mixed = materialise(named.groupBy("lead").agg(F.min("label").alias("lo"), F.max("label").alias("hi")).where("lo != hi").select("lead"))
    few = F.broadcast if mixed.count() <= BROADCAST_LEADERS else lambda df: df
    open_rows = materialise(named.join(few(mixed), "lead"))
    partnered = materialise(_with_partner(open_rows.join(classes.select("c", "sig"), "c"), few, loose))
    if not partnered.isEmpty():
        full = _sets(partnered.select("c"), docs, members)
        more = _joining_links(open_rows.join(partnered, ["lead", "c"]).join(full, "c").select("lead", "c", "label", "shingles"), few)
        # What joins are components, by their labels; few are left by now.
        known = label.withColumnsRenamed({"node": "_n", "label": "_l"})
        ends = more.join(known, F.col("a") == F.col("_n"), "left").select(F.coalesce("_l", "a").alias("a"), "b")
        ends = ends.join(known, F.col("b") == F.col("_n"), "left").select("a", F.coalesce("_l", "b").alias("b"))
        joined = materialise(components(ends)).withColumnsRenamed({"node": "_j", "label": "_root"})
        every = label.unionByName(joined.select(F.col("_j").alias("node"), F.col("_j").alias("label"))).dropDuplicates(["node"])
        label = materialise(every.join(joined, F.col("label") == F.col("_j"), "left").select("node", F.coalesce("_root", "label").alias("label")))
    whole = classes.join(label, classes["c"] == label["node"], "left").select("same", F.coalesce("label", "c").alias("label"))
    return base.drop("sig"), whole


def _read(docs: DataFrame, text: str, key: str) -> DataFrame:
    return docs.select(F.col(f"`{key}`").alias("id"), F.col(f"`{text}`").cast("string").alias("text"))


def near_duplicates(docs: DataFrame, text: str = "text", key: str = "doc_id", loose: int = LOOSE) -> DataFrame:
    """(key, n_shingles, component_id, kept), one row for each of docs."""
    base, sets = _components(_read(docs, text, key), loose)
    reps = base.where("same is not null").groupBy("same").agg(F.min("id").alias("rep"))
    whole = sets.join(reps, "same")
    smallest = whole.groupBy("label").agg(F.min("rep").alias("component_id"))
    of = whole.join(smallest, "label").select(F.col("same").alias("_same"), "component_id")
    out = base.join(of, base["same"] == of["_same"], "left").withColumn("component_id", F.when(F.col("same").isNull(), F.col("id")).otherwise(F.col("component_id")))
    return out.select(F.col("id").alias(key), "n_shingles", "component_id", F.col("id").eqNullSafe(F.col("component_id")).alias("kept"))


def one_of_each(docs: DataFrame, text: str = "text", key: str = "doc_id", loose: int = LOOSE) -> DataFrame:
    """The rows of docs that stay: of each component, the one with the smallest id (null ids last; then by the text's md5), by
    row and not by id, so that other rows with its id go. Rows without a word all stay. Rows that repeat an id and its text
    stay once."""
    base, sets = _components(_read(docs, text, key), loose)
    groups = base.join(sets, "same", "left").withColumn("g", F.when(F.col("same").isNull(), -1 - F.col("uid")).otherwise(F.col("label")))
    first = groups.groupBy("g").agg(F.min(F.struct(F.col("id").isNull().alias("none"), "id", "digest")).alias("x"))
    stay = materialise(first.select("x.id", "x.digest").distinct()).alias("stay")
    same = F.col(f"docs.`{key}`").eqNullSafe(F.col("stay.id")) & F.unhex(F.md5(F.col(f"docs.`{text}`").cast("string"))).eqNullSafe(F.col("stay.digest"))
    repeated = base.groupBy("id", "digest").count().where("count > 1")
    if not repeated.isEmpty():
        docs = docs.dropDuplicates([key, text])
    return docs.alias("docs").join(stay, same, "left_semi")
