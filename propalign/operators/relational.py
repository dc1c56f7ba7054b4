"""Relational helpers around the methods."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from propalign.model import PAIR_KEY


def select_class(instances: DataFrame, cls: str, sources: list[str] | None = None) -> DataFrame:
    """Instances of a class, of some sources; both filters reach the scan of a partitioned table."""
    out = instances.where(F.col("cls") == cls)
    return out.where(F.col("source").isin(sources)) if sources is not None else out


def cap_entities(instances: DataFrame, n: int) -> DataFrame:
    """At most n entities of each source, those with the smallest names."""
    from pyspark.sql import Window

    entities = instances.select("cls", "source", "entity").distinct()
    order = Window.partitionBy("cls", "source").orderBy("entity")
    kept = entities.withColumn("_r", F.row_number().over(order)).where(F.col("_r") <= n).drop("_r")
    return instances.join(kept, ["cls", "source", "entity"], "left_semi")


def sample_values(instances: DataFrame, per_property: int) -> DataFrame:
    """About per_property instances of each property, by hash: means of a sample differ by about one over the root of its
    size. Properties with fewer instances keep all."""
    from propalign.model import PROPERTY_KEY

    n = instances.groupBy(*PROPERTY_KEY).agg(F.count("*").alias("_n"))
    unit = F.pmod(F.xxhash64("entity", "value"), F.lit(1_000_000)) / 1_000_000
    return instances.join(n, PROPERTY_KEY).where(unit < F.lit(float(per_property)) / F.col("_n")).drop("_n")


def range_band_join(left: DataFrame, right: DataFrame, lx: str, rx: str, width: float) -> DataFrame:
    """Rows whose numbers differ by at most width: an equi-join on bands of that width, each right row in three bands."""
    a = left.withColumn("_band", F.floor(F.col(lx) / width))
    b = right.withColumn("_band", F.explode(F.array(*[F.floor(F.col(rx) / width) + d for d in (-1, 0, 1)])))
    return a.join(b, "_band").where(F.abs(F.col(lx) - F.col(rx)) <= width).drop("_band")


def word_blocking(properties: DataFrame) -> DataFrame:
    """PAIR rows that share a word of their names: a cheaper candidate set; what it loses must be reported (recall_loss)."""
    from propalign.functions.formats import words

    rows = properties.select("cls", "source", "prop", F.explode(F.array_distinct(words(F.col("prop")))).alias("w"))
    a = rows.withColumnsRenamed({"source": "source_a", "prop": "prop_a"})
    b = rows.withColumnsRenamed({"source": "source_b", "prop": "prop_b"})
    return a.join(b, ["cls", "w"]).where("source_a < source_b").select(*PAIR_KEY).distinct()


def recall_loss(candidates: DataFrame, truth: DataFrame) -> DataFrame:
    """(cls, n_true, n_lost): true pairs that a blocking leaves out."""
    lost = truth.join(candidates.select(*PAIR_KEY).distinct(), PAIR_KEY, "left_anti").groupBy("cls").agg(F.count("*").alias("n_lost"))
    return truth.groupBy("cls").agg(F.count("*").alias("n_true")).join(lost, "cls", "left").fillna(0, ["n_lost"])
