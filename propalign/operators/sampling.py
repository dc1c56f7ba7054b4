"""True pairs, labelled pairs and training samples."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from propalign.model import PAIR_KEY


def truth(align: DataFrame) -> DataFrame:
    """PAIR rows whose two properties are aligned to the same reference property."""
    side = lambda s: align.select("cls", "ref_prop", *[F.col(c).alias(f"{c}_{s}") for c in ("source", "prop")])
    return side("a").join(side("b"), ["cls", "ref_prop"]).where("source_a < source_b").select(*PAIR_KEY).distinct()


def labelled(pairs: DataFrame, align: DataFrame) -> DataFrame:
    """pairs with label 1 where both properties are aligned to the same reference property, else 0.

    Only the alignment (a row for each property) is looked up, so true pairs are never expanded for this.
    """
    side = lambda s: align.select("cls", *[F.col(c).alias(f"{c}_{s}") for c in ("source", "prop")], F.col("ref_prop").alias(f"_ref_{s}"))
    out = pairs.join(side("a"), ["cls", "source_a", "prop_a"], "left").join(side("b"), ["cls", "source_b", "prop_b"], "left")
    return out.withColumn("label", F.coalesce((F.col("_ref_a") == F.col("_ref_b")).cast("int"), F.lit(0))).drop("_ref_a", "_ref_b")


def hash_rank(*parts: Column) -> Column:
    """A key for a random order that other SQL engines have too."""
    return F.md5(F.concat_ws("|", *[p.cast("string") for p in parts]))


def training_pairs(labelled_: DataFrame, ratio: int = 2, seed: int = 7, by: list[str] | None = None) -> DataFrame:
    """All matching pairs and ratio times as many others, those with the smallest hashes, within the groups by.

    Others are thinned by hash before they are ranked, where there are far more of them than are needed, so that the ranking
    sorts little; the ranks come from the same hash, so the result is the same.
    """
    by = by or ["cls"]
    pos = labelled_.where("label = 1")
    need = pos.groupBy(*by).agg((F.count("*") * ratio).alias("_need"))
    neg = labelled_.where("label = 0").withColumn("_hash", hash_rank(F.lit(seed), *[F.col(c) for c in [*by, *PAIR_KEY]]))
    have = labelled_.where("label = 0").groupBy(*by).agg(F.count("*").alias("_have"))
    share = F.least(F.lit(1.0), 2.0 * (F.col("_need") + 50) / F.col("_have"))
    unit = F.conv(F.substring("_hash", 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)
    # Groups are experiment runs or classes: few rows.
    thin = neg.join(F.broadcast(need.join(have, by)), by).where(unit < share)
    rank = F.row_number().over(Window.partitionBy(*by).orderBy("_hash"))
    taken = thin.withColumn("_rank", rank).where(F.col("_rank") <= F.col("_need"))
    columns = labelled_.columns
    return pos.select(*columns).unionByName(taken.select(*columns))
