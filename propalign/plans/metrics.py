"""Precision, recall and F1, and summaries of many runs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from propalign.model import PAIR_KEY


def ratio(a: Column, b: Column) -> Column:
    return F.when(b > 0, a / b).otherwise(F.lit(0.0))


def with_scores(counts: DataFrame) -> DataFrame:
    """counts (tp, fp, fn) with precision, recall and f1; 0/0 is 0."""
    tp, fp, fn = F.col("tp"), F.col("fp"), F.col("fn")
    return counts.withColumns({"precision": ratio(tp, tp + fp), "recall": ratio(tp, tp + fn), "f1": ratio(2 * tp, 2 * tp + fp + fn)})


def prf(sim: DataFrame, truth: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Measures of SIM rows against true PAIR rows, for each group by (columns of both). A true pair that wasn't scored is
    missed."""
    by = by if by is not None else ["cls"]
    keys = list(dict.fromkeys([*by, *PAIR_KEY]))
    found = sim.where("is_match").select(*keys, F.lit(1).alias("_m"))
    real = truth.select(*keys, F.lit(1).alias("_t"))
    both = found.join(real, keys, "full_outer")
    count = lambda c: F.coalesce(F.sum(c.cast("long")), F.lit(0))
    m, t = F.col("_m").isNotNull(), F.col("_t").isNotNull()
    return with_scores(both.groupBy(*by).agg(count(m & t).alias("tp"), count(m & ~t).alias("fp"), count(~m & t).alias("fn")))


def summarise(runs: DataFrame, by: list[str]) -> DataFrame:
    """Means and spread over runs, with the F1 of the mean precision and recall beside the mean F1."""
    out = []
    for c in ("precision", "recall", "f1"):
        out += [F.avg(c).alias(f"mean_{c}"), F.min(c).alias(f"min_{c}"), F.max(c).alias(f"max_{c}"), F.stddev_pop(c).alias(f"sd_{c}")]
        out += [F.percentile(c, F.lit(q)).alias(f"q{int(q * 100)}_{c}") for q in (0.25, 0.5, 0.75)]
    rows = runs.groupBy(*by).agg(F.count("*").alias("runs"), *out)
    p, r = F.col("mean_precision"), F.col("mean_recall")
    return rows.withColumn("f1_of_means", ratio(2 * p * r, p + r))


def gap(summary: DataFrame, method: str, by: list[str], name: str = "method", measure: str = "mean_f1") -> DataFrame:
    """By how many points of F1 method leads each other one."""
    best = summary.where(F.col(name) == method).select(*by, F.col(measure).alias("_m"))
    return summary.where(F.col(name) != method).join(best, by).select(*by, name, (100 * (F.col("_m") - F.col(measure))).alias("gap_points"))


def best(summary: DataFrame, by: list[str], measure: str = "mean_f1") -> DataFrame:
    """Rows with the best measure in their group; ties share the rank."""
    order = Window.partitionBy(*by).orderBy(F.col(measure).desc())
    return summary.withColumn("place", F.rank().over(order)).where("place = 1").drop("place")


def cube(runs: DataFrame, dims: list[str]) -> DataFrame:
    """Mean measures for every combination of dimensions and all their totals (nulls). Sums are decimals, so they don't depend on
    the order of rows."""
    mean = lambda c: (F.sum(F.col(c).cast("decimal(18,12)")).cast("double") / F.count("*")).alias(f"mean_{c}")
    return runs.cube(*dims).agg(F.count("*").alias("n"), *[mean(c) for c in ("precision", "recall", "f1")])


def pr_curve(sim: DataFrame, truth: DataFrame) -> DataFrame:
    """(cls, score, tp, fp, precision, recall) at each different score from the highest down."""
    scored = sim.select(*PAIR_KEY, "score").join(truth.select(*PAIR_KEY).withColumn("_t", F.lit(1)), PAIR_KEY, "left")
    steps = scored.groupBy("cls", "score").agg(F.count("_t").alias("t"), F.count("*").alias("n"))
    total = truth.groupBy("cls").agg(F.count("*").alias("all"))
    down = Window.partitionBy("cls").orderBy(F.col("score").desc()).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    rows = steps.withColumns({"tp": F.sum("t").over(down), "seen": F.sum("n").over(down)}).join(total, "cls")
    return rows.select("cls", "score", "tp", (F.col("seen") - F.col("tp")).alias("fp"), ratio(F.col("tp"), F.col("seen")).alias("precision"), ratio(F.col("tp"), F.col("all")).alias("recall"))
