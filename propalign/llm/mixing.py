"""Mixing sources to target weights by systematic sampling.

Every source gets a target number of words; every document of it is expected ``target / size of the source`` times. The
expected copies are summed along the documents of a source, in the order of their sizes; with one random offset for the
source, a document is emitted once for each integer that the running sum crosses on it. Since neighbours have like sizes,
the words taken come near the target, to about the size of the largest document. Where a few documents hold much of a
source even that can be far, so ``TRIES`` random offsets are drawn for each source, and the one whose words come nearest to
the target is added.

The running sum needs a document's rank within its source. It comes from counts by (source, band of sizes, salt), summed
along the bands, and the rank within such a cell; so no task holds a source or a size that many documents share.

Edge cases: a null or empty text has size 0 and costs nothing; it is sampled at the rate of its source. A null source is
a source, the last in order. If no document has a word, nothing is taken. Rows that repeat are documents of their own; of
rows with equal ids and sizes, the texts' hashes decide the order, so reruns agree. Null ids are allowed; no documents give no
rows; texts of any length count whole. Columns pass through, whatever their names; those called like a result of
``systematic_mix`` are replaced there, and kept by ``emit_mix``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from propalign.llm.tables import kept_columns, materialise, unit_hash, word_count

#: The weights of the sources in their order, over and over.
WEIGHTS = (1, 2, 3)
#: No source, and no document, is taken more often.
MOST = 3
SALTS = 64
#: Random offsets of which the best is taken.
TRIES = 16
#: The columns that systematic_mix adds.
RESULTS = ("mix_size", "mix_source_size", "mix_target", "mix_copies")


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, most: int = MOST) -> DataFrame:
    """From (mix_source, mix_source_size) with one row a source: the target of each.

    A source can't get more than ``most`` times its size; what lies above is shared anew among the others by their
    weights, until none is above. That ends where target = min(level * weight, cap) for one level: sources in the order of
    cap / weight, the first is left uncapped from which on the level stays below. The windows here run over the sources,
    one row for each; a corpus has few.
    """
    order = Window.orderBy(F.col("mix_source").asc_nulls_last())
    every = Window.partitionBy(F.lit(1))
    by_cap = Window.orderBy("_ratio", F.col("mix_source").asc_nulls_last())
    before, rest = by_cap.rowsBetween(Window.unboundedPreceding, -1), by_cap.rowsBetween(0, Window.unboundedFollowing)
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.pmod(F.row_number().over(order) - 1, F.lit(len(weights))) + 1).cast("int"))
    return (
        sizes.withColumn("_weight", weight)
        .withColumn("_cap", F.col("mix_source_size") * F.lit(float(most)))
        .withColumn("_ratio", F.col("_cap") / F.col("_weight"))
        .withColumn("_total", F.sum("mix_source_size").over(every).cast("double"))
        .withColumn("_level", (F.col("_total") - F.coalesce(F.sum("_cap").over(before), F.lit(0.0))) / F.sum("_weight").over(rest))
        .withColumn("_open", F.min(F.when(F.col("_level") <= F.col("_ratio"), F.struct("_ratio", "_level"))).over(every))
        .withColumn("mix_target", F.least(F.col("_cap"), F.coalesce(F.col("_open._level"), F.lit(0.0)) * F.col("_weight")))
        .select("mix_source", "mix_source_size", "mix_target")
    )


def _copies(rank: Column, rate: Column, offset: Column) -> Column:
    return F.floor(rank * rate + offset) - F.floor((rank - 1) * rate + offset)


def _mixed(docs: DataFrame, keep: list[Column], source: str, text: str, key: str, seed: int, weights: tuple[int, ...], most: int) -> DataFrame:
    """(row: a struct of the columns keep, and RESULTS)."""
    own = lambda c: F.col(f"`{c}`")
    rows = docs.select(
        F.struct(*keep).alias("row"), own(source).alias("mix_source"), word_count(own(text)).alias("mix_size"), own(key).alias("key"), F.xxhash64(own(text)).alias("hash"),
        F.pmod(F.conv(F.substring(F.md5(F.coalesce(own(key).cast("string"), F.lit(""))), 1, 4), 16, 10).cast("int"), F.lit(SALTS)).alias("salt"),
    )
    # Bands of sizes: exact below 64, then 16 for each power of two.
    bits = F.length(F.bin("mix_size"))
    coarse = bits * 16 + F.call_function("shiftright", F.col("mix_size"), bits - 5)
    rows = rows.withColumn("band", F.when(F.col("mix_size") < 64, F.col("mix_size")).otherwise(coarse))
    light = materialise(rows.drop("row"))
    cells = light.groupBy("mix_source", "band", "salt").agg(F.count("*").alias("n"), F.sum("mix_size").alias("words"))
    targets = source_targets(cells.groupBy("mix_source").agg(F.sum("words").cast("long").alias("mix_source_size")), weights, most)
    name = F.coalesce("mix_source", F.lit("\x01null"))
    targets = targets.select(
        F.col("mix_source").alias("_s"), "mix_source_size", "mix_target",
        F.when(F.col("mix_source_size") > 0, F.col("mix_target") / F.col("mix_source_size")).otherwise(F.lit(0.0)).alias("rate"),
        F.array(*[unit_hash(F.lit(str(seed)), F.lit(str(j)), name) for j in range(TRIES)]).alias("offsets"),
    )
    # Ranks before a cell: those of the source's bands before, and those of the band's salts before. A source has some
    # hundred bands and a band SALTS salts, whatever the corpus.
    by_band = Window.partitionBy("_s").orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)
    by_salt = Window.partitionBy("mix_source", "band").orderBy("salt").rowsBetween(Window.unboundedPreceding, -1)
    bands = cells.groupBy(F.col("mix_source").alias("_s"), F.col("band").alias("_b")).agg(F.sum("n").alias("k"))
    bands = bands.withColumn("lower", F.coalesce(F.sum("k").over(by_band), F.lit(0)))
    cells = cells.withColumn("within", F.coalesce(F.sum("n").over(by_salt), F.lit(0)))
    cells = cells.join(bands, cells["mix_source"].eqNullSafe(bands["_s"]) & (cells["band"] == bands["_b"])).drop("_s")
    cells = cells.join(targets, cells["mix_source"].eqNullSafe(targets["_s"]))
    cells = materialise(cells.select(
        F.col("mix_source").alias("c_source"), F.col("band").alias("c_band"), F.col("salt").alias("c_salt"), (F.col("lower") + F.col("within")).alias("before"),
        "mix_source_size", "mix_target", "rate", "offsets",
    ))

    def ranked(of: DataFrame, cells: DataFrame) -> DataFrame:
        placed = of.join(cells, of["mix_source"].eqNullSafe(cells["c_source"]) & (of["band"] == cells["c_band"]) & (of["salt"] == cells["c_salt"]))
        within = Window.partitionBy("mix_source", "band", "salt").orderBy("mix_size", "key", "hash")
        return placed.withColumn("rank", F.col("before") + F.row_number().over(within))

    taken = ranked(light, cells).groupBy(F.col("mix_source").alias("_s")).agg(
        F.first("mix_target").alias("_t"), F.first("offsets").alias("_o"),
        *[F.sum(F.col("mix_size") * _copies(F.col("rank"), F.col("rate"), F.col("offsets")[j])).alias(f"_{j}") for j in range(TRIES)],
    )
    best = F.array_min(F.array(*[F.struct(F.abs(F.col(f"_{j}") - F.col("_t")).alias("far"), F.lit(j).alias("j")) for j in range(TRIES)]))["j"]
    chosen = materialise(taken.select("_s", F.get("_o", best).alias("offset")))
    cells = cells.join(chosen, cells["c_source"].eqNullSafe(chosen["_s"])).drop("_s", "offsets")
    out = ranked(rows, cells).withColumn("mix_copies", _copies(F.col("rank"), F.col("rate"), F.col("offset")).cast("int"))
    return out.select("row", *RESULTS)


def systematic_mix(
    docs: DataFrame, source: str = "source", text: str = "text", key: str = "doc_id", seed: int = 7,
    weights: tuple[int, ...] = WEIGHTS, most: int = MOST,
) -> DataFrame:
    """The rows of docs with ``mix_size``, ``mix_source_size``, ``mix_target`` and ``mix_copies`` (0 to most)."""
    return _mixed(docs, kept_columns(docs, docs.columns, RESULTS), source, text, key, seed, weights, most).select("row.*", *RESULTS)


def emit_mix(
    docs: DataFrame, source: str = "source", text: str = "text", key: str = "doc_id", seed: int = 7,
    weights: tuple[int, ...] = WEIGHTS, most: int = MOST,
) -> DataFrame:
    """The mix itself: each row of docs as often as it is taken, with the columns of docs."""
    mixed = _mixed(docs, kept_columns(docs, docs.columns, ()), source, text, key, seed, weights, most).where("mix_copies > 0")
    return mixed.select("row", F.explode(F.sequence(F.lit(1), F.col("mix_copies")))).select("row.*")
