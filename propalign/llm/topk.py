"""Exact top-k search by inner product with a pivot-distance index.

Vectors are keyed by their nearest pivot and their distance to it, cut into annuli; an annulus with many vectors is cut
into blocks. For a query q and a vector x at distance d from pivot p, the triangle inequality bounds the score:
``q.x <= q.p + |q| d`` and ``q.x <= (|q|^2 + |x|^2 - (|q-p| - d)^2) / 2``. Queries of one pivot go in groups. A group sorts the
annuli of all pivots by the highest bound that one of its queries has there, and expands them in this order, in rounds of
twice as many each. After a round each query has a score to beat; it passes over annuli whose bound is below, and a group
stops where none of its queries has an annulus left. Results are exact whatever the pivots; they are a bounded sample and
decide only how much is searched.

Components become integers ``floor(scale * x)``; scores are integer inner products.

Edge cases: vectors that are null, or hold null or non-finite components, take no part. Shorter vectors count as ending in
zeros; empty ones score 0. With fewer candidates than k, all are returned. Ties go to the smaller id. Only other *rows* are
candidates; a row with the query's id is the query itself. Rows that repeat an id count each: as candidates, and as queries,
whose results are ranked together. Null ids take no part. Components stay exact up to 2**53 in a score. No rows give no
rows. Only the key and the vector are read, so other columns may have any name.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from propalign.llm.tables import materialise

SCALE = 256
K = 5
#: Pivots, at most: the vectors with the smallest hashes of their ids.
PIVOTS = 24
#: Annuli of a pivot, vectors of a block, and queries of a block.
ANNULI, BLOCK, QUERIES = 4, 2048, 512
#: Annuli that a group expands in the first round; each round after it takes twice as many.
FIRST = 16


def integer_vectors(rows: DataFrame, key: str, vector: str, scale: int = SCALE) -> DataFrame:
    """(id, v): v array<double> with whole numbers; rows that take no part are left out."""
    x = F.col(vector).cast("array<double>")
    good = F.col(key).isNotNull() & x.isNotNull() & ~F.exists(x, lambda e: e.isNull() | F.isnan(e) | (F.abs(e) == float("inf")))
    return rows.where(good).select(F.col(key).cast("long").alias("id"), F.transform(x, lambda e: F.floor(e * F.lit(float(scale))).cast("double")).alias("v"))


def _matrix(col: pa.Array, width: int) -> np.ndarray:
    sizes, flat = pa.compute.list_value_length(col).to_numpy(zero_copy_only=False), col.flatten().to_numpy(zero_copy_only=False)
    if (sizes == width).all():
        return flat.reshape(len(col), width)
    out = np.zeros((len(col), width))
    out[np.repeat(np.arange(len(col)), sizes), np.arange(len(flat)) - np.repeat(np.cumsum(sizes) - sizes, sizes)] = flat
    return out


def _top(ids: np.ndarray, scores: np.ndarray, k: int) -> np.ndarray:
    """Places of the k highest scores, ties to smaller ids; ids ascend."""
    if len(scores) > 4 * k:
        bar = np.partition(scores, len(scores) - k)[len(scores) - k]
        near = np.flatnonzero(scores >= bar)
        return near[np.lexsort((ids[near], -scores[near]))[:k]]
    return np.lexsort((ids, -scores))[:k]


def pivot_index(vectors: DataFrame, pivots: np.ndarray, width: int) -> DataFrame:
    """(id, v, pivot, d, norm): each vector with its nearest pivot and distance."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = _matrix(b.column(1), width)
            norm = (x * x).sum(1)
            d2 = np.maximum(0, norm[:, None] + (pivots * pivots).sum(1)[None, :] - 2 * x @ pivots.T)
            near = d2.argmin(1)
            d = np.sqrt(d2[np.arange(len(x)), near])
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(near.astype(np.int32)), pa.array(d), pa.array(norm)], names=["id", "v", "pivot", "d", "norm"])

    return vectors.mapInArrow(run, "id long, v array<double>, pivot int, d double, norm double")


def _blocks(index: DataFrame, width: int) -> DataFrame:
    """One row a block: (block, pivot, d_low, d_high, norm_high, ids, matrix)."""
    span = index.groupBy("pivot").agg(F.min("d").alias("lo"), F.max("d").alias("hi"))  # a row for each pivot
    ring = F.when(F.col("hi") > F.col("lo"), F.least(F.lit(ANNULI - 1), F.floor((F.col("d") - F.col("lo")) / (F.col("hi") - F.col("lo")) * ANNULI))).otherwise(0).cast("int")
    placed = index.join(F.broadcast(span), "pivot").withColumn("ring", ring)
    sizes = placed.groupBy("pivot", "ring").agg(F.count("*").alias("n"))  # at most PIVOTS * ANNULI rows
    placed = placed.join(F.broadcast(sizes), ["pivot", "ring"]).withColumn("salt", F.pmod(F.xxhash64("id"), F.ceil(F.col("n") / BLOCK)).cast("int"))
    return placed.groupBy("pivot", "ring", "salt").agg(
        F.min("d").alias("d_low"), F.max("d").alias("d_high"), F.max("norm").alias("norm_high"), F.sort_array(F.collect_list(F.struct("id", "v"))).alias("members")
    ).withColumn("block", F.xxhash64("pivot", "ring", "salt"))


def _search(pairs: DataFrame, k: int, width: int) -> DataFrame:
    """(q, id, score): the k best of each query in each block. pairs: (queries array<struct<id, v, floor>>, members)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out_q, out_id, out_s = [], [], []
            for qs, ms in zip(b.column(0), b.column(1), strict=True):
                q, m = qs.values, ms.values
                qid, mid = q.field("id").to_numpy(), m.field("id").to_numpy()
                scores = _matrix(q.field("v"), width) @ _matrix(m.field("v"), width).T
                floor = q.field("floor").to_numpy()
                for i in range(len(qid)):
                    ok = np.flatnonzero((mid != qid[i]) & (scores[i] >= floor[i]))
                    best = ok[_top(mid[ok], scores[i, ok], k)]
                    out_q.append(np.full(len(best), qid[i]))
                    out_id.append(mid[best])
                    out_s.append(scores[i, best].astype(np.int64))
            cat = lambda xs: pa.array(np.concatenate(xs) if xs else np.zeros(0, dtype=np.int64))
            yield pa.RecordBatch.from_arrays([cat(out_q), cat(out_id), cat(out_s)], names=["q", "id", "score"])

    return pairs.select("queries", "members").mapInArrow(run, "q long, id long, score long")


def _best(found: DataFrame, k: int) -> DataFrame:
    """The k best of each query; a query row has at most k rows from each block, and searches no block twice."""
    order = Window.partitionBy("q").orderBy(F.col("score").desc(), "id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def top_k(
    rows: DataFrame, is_query, key: str = "vec_id", vector: str = "embedding", k: int = K, scale: int = SCALE, report: list | None = None,
) -> DataFrame:
    """(query_id, rank, key, score) for the rows that is_query (a column) picks, against all rows. report: a list that gets the
    number of scores computed in each round."""
    vectors = integer_vectors(rows, key, vector, scale)
    width = vectors.agg(F.coalesce(F.max(F.size("v")), F.lit(0))).first()[0]
    chosen = vectors.orderBy(F.xxhash64("id"), "id").limit(PIVOTS).collect()  # a fixed number
    pivots = np.zeros((max(1, len(chosen)), width))
    for i, r in enumerate(chosen):
        pivots[i, : len(r["v"])] = r["v"]
    index = materialise(pivot_index(vectors, pivots, width))
    blocks = materialise(_blocks(index, width))
    queries = index.where(is_query(F.col("id")))
    # Groups of queries; their number follows that of the queries.
    sizes = queries.groupBy("pivot").agg(F.ceil(F.count("*") / QUERIES).alias("parts"))  # a row for each pivot
    part = F.pmod(F.xxhash64("id"), F.col("parts"))
    asked = materialise(queries.join(F.broadcast(sizes), "pivot").select(F.xxhash64("pivot", part).alias("g"), "id", "v", "norm"))

    heads = blocks.groupBy("pivot", "ring").agg(F.min("d_low"), F.max("d_high"), F.max("norm_high")).collect()  # at most PIVOTS * ANNULI
    near, far, norms = (np.array([h[j] for h in heads]) for j in (2, 3, 4))
    of_pivot, of_ring = (np.array([h[j] for h in heads], dtype=np.int32) for j in (0, 1))

    def bounds(q: np.ndarray, norm: np.ndarray) -> np.ndarray:
        """The most that each query can score in each annulus, and a little more, for rounding."""
        at = q @ pivots.T
        apart = np.sqrt(np.maximum(0, norm[:, None] + (pivots * pivots).sum(1)[None, :] - 2 * at))[:, of_pivot]
        by_ball = at[:, of_pivot] + np.sqrt(norm)[:, None] * far[None, :]
        gap = np.maximum(0, np.maximum(near[None, :] - apart, apart - far[None, :]))
        best = np.minimum(by_ball, (norm[:, None] + norms[None, :] - gap**2) / 2)
        return best + 1e-9 * np.abs(best) + 1e-3

    def expand(first: int, last: int):
        """(pivot, ring, queries): the annuli at these places of each group's order, with its queries that can gain there."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for members in batch.column(0):
                    m = members.values
                    bound = bounds(_matrix(m.field("v"), width), m.field("norm").to_numpy())
                    can = bound >= m.field("floor").to_numpy()[:, None]
                    told = pa.StructArray.from_arrays([m.field("id"), m.field("v"), m.field("floor")], names=["id", "v", "floor"])
                    for j in np.argsort(-bound.max(0), kind="stable")[first:last]:
                        mine = np.flatnonzero(can[:, j])
                        if len(mine):
                            packed = pa.ListArray.from_arrays(pa.array([0, len(mine)], pa.int32()), told.take(pa.array(mine)))
                            yield pa.RecordBatch.from_arrays([pa.array(of_pivot[j : j + 1]), pa.array(of_ring[j : j + 1]), packed], names=["pivot", "ring", "queries"])

        return run

    floor = F.lit(float("-inf")).alias("floor")
    best, first, take = None, 0, FIRST
    while first < len(heads) or best is None:
        if best is not None:
            beaten = best.groupBy("q").agg(F.when(F.count("*") >= k, F.min("score").cast("double")).alias("worst"))
            members = asked.join(beaten, asked["id"] == beaten["q"], "left")
            floor = F.coalesce("worst", F.lit(float("-inf"))).alias("floor")
        else:
            members = asked
        # A query's vector is moved once, and then once for each annulus that it searches.
        groups = members.select("g", F.struct("id", "v", "norm", floor).alias("m")).groupBy("g").agg(F.collect_list("m").alias("members")).select("members")
        opened = groups.mapInArrow(expand(first, first + take), "pivot int, ring int, queries array<struct<id: bigint, v: array<double>, floor: double>>")
        pairs = opened.join(blocks.select("pivot", "ring", "members"), ["pivot", "ring"])
        if report is not None:
            report.append(pairs.agg(F.coalesce(F.sum(F.size("queries").cast("long") * F.size("members")), F.lit(0))).first()[0])
        found = _search(pairs, k, width)
        best = materialise(_best(found if best is None else best.select("q", "id", "score").unionByName(found), k))
        first, take = first + take, 2 * take
    return best.select(F.col("q").alias("query_id"), "rank", F.col("id").alias(key), "score")
