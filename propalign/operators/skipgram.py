"""Word2vec whose words and vectors stay in the cluster: skip-gram with hierarchical softmax, as in MLlib, whose driver holds
every word, its code and both matrices.

The loss of a pass over the texts is a sum over pairs (word, inner node of the Huffman tree) of how often the word stood near a
word below the node's left or right side, where a pair at distance d counts with the share of windows that reach it. So texts are
counted, pairs are counted, and the pass is taken in slices with a falling rate: in a slice, all nodes' vectors make the steps of
their pairs together, then all words' vectors do. A sum of steps is shortened by the curvature along it (as if it were many small
ones), so the loss never rises. The result doesn't depend on the number of blocks or tasks.

A word's number is its code in the tree with a 1 before it; shifted right, it gives the numbers of the nodes above it. The top of
the tree (its size is bounded by a parameter) goes to all tasks. Below, each subtree is a block: a partition with the vectors of its
words and nodes. Words of one block that stand near words of another have their vectors sent there after each step.
"""

from __future__ import annotations

import heapq
import pickle
from collections import Counter, defaultdict
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import RDD, StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from propalign.functions.formats import words
from propalign.operators.graph import checkpointed

#: As MLlib has them.
WINDOW, RATE, LONGEST = 5, 0.025, 1_000
#: Slices of the pass.
SLICES = 16
#: A block has words of about so many occurrences; the top of the tree has so many levels at most.
BLOCK_TOKENS, MOST_LEVELS = 150_000, 15
#: The most frequent words, which tasks look up (some 60 bytes each); others are joined.
LOOKED_UP = 2_000_000
#: Texts, or pairs of a word and a node, at once.
TEXTS_AT_ONCE, TERMS_AT_ONCE = 50_000, 4_096


def code_lengths(counts: list[tuple[int, int]]) -> dict[int, int]:
    """Length -> words with a code so long, by Huffman's algorithm on groups of like weight. counts: (weight, words that have it)."""
    below: list[list[tuple[int, int]]] = [[] for _ in counts]
    heap = [(w, i, m) for i, (w, m) in enumerate(counts)]
    heapq.heapify(heap)
    while heap:
        w, i, m = heapq.heappop(heap)
        if m == 1 and not heap:
            break
        if m > 1:
            new, left = (2 * w, len(below), m // 2), (w, i, m % 2)
            below.append([(i, 2)])
        else:
            v, j, n = heapq.heappop(heap)
            new, left = (w + v, len(below), 1), (v, j, n - 1)
            below.append([(i, 1), (j, 1)])
        heapq.heappush(heap, new)
        if left[2]:
            heapq.heappush(heap, left)
    depths: dict[int, Counter] = defaultdict(Counter)
    depths[len(below) - 1][0] = 1
    out: Counter = Counter()
    for i in range(len(below) - 1, -1, -1):
        for child, uses in below[i]:
            for d, n in depths[i].items():
                depths[child][d + 1] += uses * n
        if i < len(counts):
            out.update(depths[i])
    return dict(sorted(out.items()))


def _code_starts(lengths: dict[int, int]) -> list[tuple[int, int, int, int]]:
    """(length, first rank, rank after the last, number of the first word) of canonical codes."""
    out, code, rank, before = [], 0, 0, 0
    for n, many in lengths.items():
        code <<= n - before
        out.append((n, rank, rank + many, (1 << n) + code))
        code, rank, before = code + many, rank + many, n
    return out


def vocabulary(counted: DataFrame, min_count: int) -> tuple[DataFrame, list[tuple[int, int, int, int]], int]:
    """(word, rank, h) of words that occur often enough, the starts of codes, and the number of occurrences."""
    spark = counted.sparkSession
    found = counted.select(F.explode(words(F.col("text"))).alias("word"), "n").groupBy("word").agg(F.sum("n").alias("n")).where(F.col("n") >= min_count)
    listed = checkpointed(found.orderBy(F.desc("n"), "word").withColumn("_id", F.monotonically_increasing_id()))
    counts = [(r["n"], r["many"]) for r in listed.groupBy("n").agg(F.count("*").alias("many")).collect()]
    if not counts:
        return listed.select("word", F.col("n").alias("rank"), F.col("n").alias("h")), [], 0
    parts = listed.groupBy(F.shiftright("_id", 33).alias("_part")).agg(F.count("*").alias("many")).orderBy("_part").collect()
    offsets, upto = [], 0
    for r in parts:
        offsets.append((r["_part"], upto))
        upto += r["many"]
    starts = _code_starts(code_lengths(sorted(counts)))
    ranked = listed.join(F.broadcast(spark.createDataFrame(offsets, "_part long, _offset long")), F.shiftright("_id", 33) == F.col("_part"))
    ranked = ranked.select("word", (F.col("_id").bitwiseAND((1 << 33) - 1) + F.col("_offset")).alias("rank"))
    h = F.lit(None).cast("long")
    for _, first, end, number in reversed(starts):
        h = F.when(F.col("rank") < end, F.lit(number) + F.col("rank") - first).otherwise(h)
    return ranked.withColumn("h", h), starts, sum(n * many for n, many in counts)


def _gathered(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    held, rows = [], 0
    for b in batches:
        held.append(b)
        rows += b.num_rows
        if rows >= TEXTS_AT_ONCE:
            yield pa.Table.from_batches(held).combine_chunks()
            held, rows = [], 0
    if rows:
        yield pa.Table.from_batches(held).combine_chunks()


def _lists(table: pa.Table, name: str) -> pa.Array:
    c = table.column(name)
    return c.chunk(0) if c.num_chunks == 1 else pa.concat_arrays(c.chunks)


def encoded(counted: DataFrame, vocab: DataFrame, n_words: int, looked_up: int = LOOKED_UP) -> DataFrame:
    """(hs, n): the numbers of each text's words; words that are too rare are left out."""
    known = vocab.where(F.col("rank") < looked_up).select("word", "h").toArrow()
    shared = counted.sparkSession.sparkContext.broadcast((known.column("word").combine_chunks(), known.column("h").to_numpy()))

    def look(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, numbers = shared.value
        for t in _gathered(batches):
            w = _lists(t, "w")
            flat = w.flatten().cast(names.type)
            at = pc.fill_null(pc.index_in(flat, value_set=names), -1).to_numpy(zero_copy_only=False)
            lacks = at < 0
            offsets = w.offsets.to_numpy() - w.offsets[0].as_py()
            before = np.concatenate([[0], np.cumsum(lacks)])
            # The i-th word of a text that is not known here has -1-i.
            place = before[:-1] - np.repeat(before[offsets[:-1]], np.diff(offsets))
            hs = np.where(lacks, -1 - place, numbers[at]) if len(numbers) else -1 - place
            rest = pa.ListArray.from_arrays(pa.array(before[offsets], pa.int32()), flat.filter(pa.array(lacks)))
            yield pa.RecordBatch.from_arrays([t.column("text").combine_chunks(), t.column("n").combine_chunks(), pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(hs, pa.int64())), rest], ["text", "n", "hs", "rest"])

    rows = counted.select("text", "n", words(F.col("text")).alias("w")).mapInArrow(look, "text string, n long, hs array<long>, rest array<string>")
    if n_words > looked_up:
        tails = rows.select("text", F.posexplode("rest").alias("i", "word")).join(vocab.where(F.col("rank") >= looked_up), "word")
        tails = tails.groupBy("text").agg(F.map_from_entries(F.collect_list(F.struct("i", "h"))).alias("found"))
        rows = rows.join(tails, "text", "left").withColumn("hs", F.transform("hs", lambda x: F.when(x < 0, F.coalesce(F.try_element_at(F.col("found"), (-x - 1).cast("int")), x)).otherwise(x)))
    return rows.select(F.filter("hs", lambda x: x > 0).alias("hs"), "n")


def near(sentences: DataFrame) -> DataFrame:
    """(a, b, weight), a <= b: how often two words stand in one another's window, each distance with the share of windows that reach it."""

    def pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in _gathered(batches):
            hs = _lists(t, "hs")
            lens = np.diff(hs.offsets.to_numpy())
            ids, flat = np.unique(hs.flatten().to_numpy(zero_copy_only=False), return_inverse=True)
            text, n = np.repeat(np.arange(len(lens)), lens), t.column("n").to_numpy()
            part = (np.arange(len(flat)) - np.repeat(np.cumsum(lens) - lens, lens)) // LONGEST
            keys, weights = [], []
            for d in range(1, WINDOW + 1):
                ok = (text[:-d] == text[d:]) & (part[:-d] == part[d:])
                x, y = flat[:-d][ok], flat[d:][ok]
                keys.append(np.minimum(x, y) * len(ids) + np.maximum(x, y))
                weights.append(n[text[:-d][ok]] * ((WINDOW + 1 - d) / WINDOW))
            found, back = np.unique(np.concatenate(keys), return_inverse=True)
            if len(found):
                total = np.bincount(back, np.concatenate(weights))
                yield pa.RecordBatch.from_arrays([pa.array(ids[found // len(ids)]), pa.array(ids[found % len(ids)]), pa.array(total)], ["a", "b", "weight"])

    return sentences.where(F.size("hs") > 1).mapInArrow(pairs, "a long, b long, weight double").groupBy("a", "b").agg(F.sum("weight").alias("weight"))


def _depth(h: np.ndarray) -> np.ndarray:
    """Of numbers of words or nodes; the root's is 0, that of no node -1."""
    out, h = np.full(len(h), -1), h.copy()
    while (h > 0).any():
        out[h > 0] += 1
        h >>= 1
    return out


class Layout:
    """Which block a word or node is in. levels: of the tree's top; first: the number of the first block's subtree."""

    def __init__(self, starts: list[tuple[int, int, int, int]], n_tokens: int, block_tokens: int):
        self.levels = min(MOST_LEVELS, max(0, (n_tokens // block_tokens).bit_length()))
        deep = [(n, number) for n, _, _, number in starts if n > self.levels]
        self.first = deep[0][1] >> (deep[0][0] - self.levels) if deep else (2 << self.levels) - 1
        self.blocks = (2 << self.levels) - self.first
        self.top = 2 << self.levels  # words of the top have numbers below

    def of(self, h: np.ndarray) -> np.ndarray:
        """-1 for words of the top, and for its nodes if they are above the lowest level."""
        d = _depth(h)
        return np.where(d > self.levels, (h >> np.maximum(d - self.levels, 0)) - self.first, -1)

    def of_nodes(self, h: np.ndarray) -> np.ndarray:
        d = _depth(h)
        return np.where(d >= self.levels, (h >> np.maximum(d - self.levels, 0)) - self.first, -1)

    def column(self, h: Column) -> Column:
        d = F.length(F.bin(h)) - 1
        return F.when(d > self.levels, F.call_function("shiftright", h, d - self.levels) - self.first).otherwise(-1)


def _terms(rows: pd.DataFrame, layout: Layout) -> dict:
    """Pairs of a word and a node, how often, and how often on the left side. rows: (c, w, weight, top): c stood near w."""
    c, w, weight, top = (rows[x].to_numpy() for x in ("c", "w", "weight", "top"))
    own, ci = np.unique(c, return_inverse=True)
    depth = _depth(w)
    ups = range(1, int(depth.max(initial=0)) + 1)
    kept = lambda t: np.flatnonzero((depth >= t) & (top | (depth - t >= layout.levels)))
    ns = np.unique(np.concatenate([c[:0], *[np.unique(w[kept(t)] >> t) for t in ups]]))

    def summed(keys: list, many: list, left: list) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        key, back = np.unique(np.concatenate(keys), return_inverse=True)
        return key, *(np.bincount(back, np.concatenate(x), len(key)) for x in (many, left))

    # Each distance from the words is summed by itself first, since few nodes are high in the tree.
    parts = [(c[:0], weight[:0], weight[:0])]
    for t in ups:
        at = kept(t)
        parts.append(summed([ci[at] * len(ns) + np.searchsorted(ns, w[at] >> t)], [weight[at]], [weight[at] * (1 - ((w[at] >> (t - 1)) & 1))]))
    key, n, left = summed(*zip(*parts, strict=True))
    ci, ni = (key // max(len(ns), 1)).astype(np.int32), (key % max(len(ns), 1)).astype(np.int32)
    return {"words": own, "nodes": ns, "ci": ci, "ni": ni, "n": n.astype(np.float32), "left": left.astype(np.float32), "by_node": np.argsort(ni, kind="stable").astype(np.int32)}


def beginning(h: np.ndarray, size: int, seed: int) -> np.ndarray:
    """Small random vectors, by the words' numbers alone."""
    with np.errstate(over="ignore"):
        x = h.astype(np.uint64)[:, None] * np.uint64(size) + np.arange(size, dtype=np.uint64) + np.uint64(seed) * np.uint64(0x9E3779B97F4A7C15)
        for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
            x = (x ^ (x >> np.uint64(shift))) * np.uint64(factor)
        x ^= x >> np.uint64(31)
    return (((x >> np.uint64(11)) / 2.0**53 - 0.5) / size).astype(np.float32)


def moved(x: np.ndarray, slope: np.ndarray, curve: np.ndarray, rate: float) -> np.ndarray:
    """x after steps against the slope for a time; the curvature bounds how far."""
    far = np.where(curve > 0, -np.expm1(-rate * curve) / np.maximum(curve, 1e-300), rate)
    return (x - far[:, None] * slope).astype(np.float32)


def bent(z: np.ndarray) -> np.ndarray:
    """The curvature of a parabola that touches log(1 + exp(z)) at z and is nowhere below it."""
    near_0 = np.abs(z) < 1e-3
    return np.where(near_0, 0.25, np.tanh(z / 2) / np.where(near_0, 1, 2 * z))


def summed(of: np.ndarray, by: np.ndarray, x: np.ndarray, fixed: np.ndarray, to: np.ndarray, n: np.ndarray, left: np.ndarray, along: np.ndarray | None = None) -> np.ndarray:
    """The loss's slopes by the vectors x that move, or its curvatures along given directions. of, to: the places in x and in fixed
    of each term; by: terms in the order of x."""
    out = np.zeros(x.shape if along is None else len(x))
    for k in range(0, len(by), TERMS_AT_ONCE):
        t = by[k : k + TERMS_AT_ONCE]
        f, z = fixed[to[t]], np.einsum("ij,ij->i", x[of[t]], fixed[to[t]])
        first = np.concatenate([[0], np.flatnonzero(np.diff(of[t])) + 1])
        if along is None:
            part = f * (n[t] / (1 + np.exp(-np.clip(z, -80, 80))) - left[t])[:, None]
        else:
            part = n[t] * bent(z) * np.einsum("ij,ij->i", f, along[of[t]]) ** 2
        out[of[t][first]] += np.add.reduceat(part, first)
    return out


def unit(slope: np.ndarray) -> np.ndarray:
    return slope / np.maximum(np.sqrt((slope**2).sum(1, keepdims=True)), 1e-300)


def _step(layout: Layout, size: int, seed: int, rate: float, tops, words_move: bool, downhill=None) -> Callable:
    """One step of all words' or nodes' vectors, for the items of a block: its terms, its vectors, and those sent to it. downhill: the
    slopes of the top's vectors; without, the block's share of them is all that is made."""

    def run(block: int, items: Iterator) -> Iterator:
        terms, own, sent = None, {}, {"u": [], "v": []}
        for to, (kind, x) in items:
            if kind == "terms":
                terms = pickle.loads(x)
            elif kind in ("u", "v"):
                own[kind] = x
            elif kind in ("gu", "gv") and to == block:  # what a block sends lies beside its vectors as well
                sent[kind[1]].append(x)
        if terms is None:
            return
        ids, home = {"u": terms["words"], "v": terms["nodes"]}, {"u": layout.of(terms["words"]), "v": layout.of_nodes(terms["nodes"])}
        full = {}
        for k, top in zip("uv", tops.value, strict=True):
            full[k] = beginning(ids[k], size, seed) if k == "u" else np.zeros((len(ids[k]), size), np.float32)
            full[k][home[k] == -1] = top[ids[k][home[k] == -1]]
            if k in own:
                full[k][home[k] == block] = own[k]
            for theirs, vectors in sent[k]:
                full[k][np.searchsorted(ids[k], theirs)] = vectors
        moves, stays = ("u", "v") if words_move else ("v", "u")
        place = {"u": terms["ci"], "v": terms["ni"]}
        by = np.arange(len(terms["ci"])) if words_move else terms["by_node"]
        mine, top = home[moves] == block, home[moves] == -1
        by = by[(top if downhill is None else top | mine)[place[moves][by]]]
        given = (place[moves], by, full[moves], full[stays], place[stays], terms["n"], terms["left"])
        if downhill is None:
            yield block, ("top", (ids[moves][top], summed(*given)[top]))
            return
        slope = summed(place[moves], by[mine[place[moves][by]]], *given[2:])
        slope[top] = downhill.value[ids[moves][top]]
        curve = summed(*given, along=unit(slope).astype(np.float32))
        new = moved(full[moves], slope, curve, rate)
        yield block, (moves, new[mine])
        yield block, ("top", (ids[moves][top], curve[top]))
        # Other blocks have those of their vectors here that our moving vectors meet.
        a, b = place[moves], home[stays][place[stays]]
        out = (b >= 0) & (b != block) & mine[a]
        for to in np.unique(b[out]):
            at = np.unique(a[out & (b == to)])
            yield int(to), ("g" + moves, (ids[moves][at], new[at]))

    return lambda block, items: run(block, items)


def _added(a: tuple, b: tuple) -> tuple:
    ids, back = np.unique(np.concatenate([a[0], b[0]]), return_inverse=True)
    total = np.zeros((len(ids), *a[1].shape[1:]))
    total[back[: len(a[0])]] += a[1]
    total[back[len(a[0]) :]] += b[1]
    return ids, total


def fit(texts: DataFrame, size: int = 64, seed: int = 7, min_count: int = 5, slices: int = SLICES, block_tokens: int = BLOCK_TOKENS, looked_up: int = LOOKED_UP) -> DataFrame:
    """(word, vec) of all words that occur often enough. texts: (text)."""
    sc = texts.sparkSession.sparkContext
    counted = texts.groupBy("text").agg(F.count("*").alias("n")).persist(StorageLevel.DISK_ONLY)
    vocab, starts, n_tokens = vocabulary(counted, min_count)
    if not starts:
        counted.unpersist()
        return vocab.select("word", F.array().cast("array<double>").alias("vec"))
    layout = Layout(starts, n_tokens, block_tokens)
    pairs = near(encoded(counted, vocab, starts[-1][2], looked_up))
    both = pairs.select(F.explode(F.array(*[F.struct(F.col(x).alias("c"), F.col(y).alias("w"), "weight") for x, y in ("ab", "ba")])).alias("p")).select("p.*")
    both = both.withColumns({"of_c": layout.column(F.col("c")), "of_w": layout.column(F.col("w"))})
    main = F.when(F.col("of_c") >= 0, F.col("of_c")).when(F.col("of_w") >= 0, F.col("of_w")).otherwise(F.pmod(F.hash("c", "w"), F.lit(layout.blocks)).cast("long"))
    both = both.withColumn("main", main).withColumn("to", F.when((F.col("of_w") >= 0) & (F.col("of_w") != F.col("main")), F.array("main", "of_w")).otherwise(F.array("main")))
    dealt = both.select(F.explode("to").alias("block"), "c", "w", "weight", "main").select("block", "c", "w", "weight", (F.col("block") == F.col("main")).alias("top"))
    # Words that stand alone have a vector too.
    alone = vocab.select(layout.column(F.col("h")).cast("long").alias("block"), F.col("h").alias("c"), F.lit(0).cast("long").alias("w"), F.lit(0.0).alias("weight"), F.lit(True).alias("top")).where("block >= 0")
    made = dealt.unionByName(alone).groupBy("block").applyInPandas(
        lambda key, rows: pd.DataFrame({"block": [key[0]], "terms": [pickle.dumps(_terms(rows, layout), 5)]}), "block long, terms binary"
    )

    def parted(rows: RDD) -> RDD:
        return rows.partitionBy(layout.blocks, int)

    terms = parted(made.rdd.map(lambda r: (r["block"], ("terms", bytes(r["terms"]))))).persist(StorageLevel.DISK_ONLY)
    tops = [beginning(np.arange(layout.top), size, seed), np.zeros((layout.top, size), np.float32)]
    last: dict[str, RDD] = {}
    for k in range(2 * slices):
        words_move = k % 2 == 1
        moves, stays = ("u", "v") if words_move else ("v", "u")
        rate = RATE * (1 - (k // 2 + 0.5) / slices) / slices
        shared = sc.broadcast(tuple(tops))
        work = terms
        for kind in (moves, stays):
            if kind in last:
                work = work.union(last[kind])
        if stays in last:
            # A map forgets the partitioner, else what is sent to other blocks would stay where it is.
            work = work.union(parted(last[stays].filter(lambda x, kind="g" + stays: x[1][0] == kind).map(lambda x: x)))
        def top_of(rows: RDD) -> np.ndarray:
            ids, total = rows.filter(lambda x: x[1][0] == "top").map(lambda x: x[1][1]).treeReduce(_added)
            out = np.zeros((layout.top, *total.shape[1:]))
            out[ids] = total
            return out

        slope = top_of(work.mapPartitionsWithIndex(_step(layout, size, seed, rate, shared, words_move)))
        done = work.mapPartitionsWithIndex(_step(layout, size, seed, rate, shared, words_move, sc.broadcast(slope.astype(np.float32))), preservesPartitioning=True)
        curve = top_of(done.persist(StorageLevel.DISK_ONLY))
        if k == 0:
            counted.unpersist()
        tops[1 - words_move] = moved(tops[1 - words_move], slope, curve, rate)
        if moves in last:
            last[moves].unpersist()
        last[moves] = done
    return _lexicon(terms, last["u"], tops[0], layout, vocab, last, size)


def _lexicon(terms: RDD, learned: RDD, top: np.ndarray, layout: Layout, vocab: DataFrame, last: dict[str, RDD], size: int) -> DataFrame:
    spark = vocab.sparkSession
    shared = spark.sparkContext.broadcast(top)

    def own(block: int, items: Iterator) -> Iterator:
        got = {kind: x for _, (kind, x) in items}
        if "terms" in got:
            ids = pickle.loads(got["terms"])["words"]
            ids = ids[layout.of(ids) == block]
            yield ids.tobytes(), got["u"].astype(np.float32).tobytes()
        if block == 0:
            yield np.arange(len(shared.value)).tobytes(), shared.value.tobytes()

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for ids, vectors in zip(b.column("ids"), b.column("vectors"), strict=True):
                h, x = np.frombuffer(ids.as_buffer(), np.int64), np.frombuffer(vectors.as_buffer(), np.float32)
                for at in range(0, len(h), 10_000):
                    part = x[at * size : (at + 10_000) * size]
                    yield pa.RecordBatch.from_arrays([pa.array(h[at : at + 10_000]), pa.ListArray.from_arrays(pa.array(np.arange(0, len(part) + 1, size), pa.int32()), pa.array(part))], ["h", "vec"])

    both = terms.union(learned).mapPartitionsWithIndex(own)
    vectors = spark.createDataFrame(both, "ids binary, vectors binary").mapInArrow(rows, "h long, vec array<float>")
    out = checkpointed(vocab.select("word", "h").join(vectors, "h").select("word", "vec"))
    for r in (terms, *last.values()):
        r.unpersist()
    return out.select("word", F.col("vec").cast("array<double>").alias("vec"))
