"""Connected components of an edge table, by rounds of joins."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from propalign.llm.tables import materialise


#: Edges of a task, about; tables with few edges don't need a task for every shuffle partition.
TASK_EDGES = 1_000_000


def _tasks(spark: SparkSession, rows: int) -> int:
    return max(2 * spark.sparkContext.defaultParallelism, rows // TASK_EDGES + 1)


def roots(parents: DataFrame) -> DataFrame:
    """(node, label) of a forest (node, parent) in which each node has at most one parent and no cycle: label is the root,
    and roots are listed too. Each round replaces a parent by its parent, which halves every path."""
    up = materialise(parents.select("node", F.col("parent").alias("label"), F.lit(True).alias("moved")))
    k = _tasks(up.sparkSession, up.count())
    while True:
        over = up.select(F.col("node").alias("_n"), F.col("label").alias("_l"))
        new = up.join(over, up["label"] == over["_n"], "left").select("node", F.coalesce("_l", "label").alias("label"), F.col("_l").isNotNull().alias("moved"))
        up = materialise(new.coalesce(k))
        if up.where("moved").isEmpty():
            break
    return up.select("node", "label").unionByName(up.select(F.col("label").alias("node"), "label").distinct())


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, label): label is the smallest node that can be reached; nodes without an edge aren't listed.

    Each round links every neighbour of a node that is larger than it to the node's smallest neighbour, and then every
    neighbour that is not larger to the smallest one; paths shrink by a factor, so few rounds are needed. The neighbour
    minimum is a partial aggregate and the join back is on it, so a node with many edges makes no large group in a task
    (adaptive execution can split its side of the join). Loops end when a round changes nothing; null ends are left out.
    """
    e = materialise(
        edges.where(F.col(a).isNotNull() & F.col(b).isNotNull() & (F.col(a) != F.col(b)))
        .select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).distinct()
    )
    n = e.count()
    k = _tasks(e.sparkSession, n)
    while True:
        # Large star: of u's neighbours, those above u go to the smallest of them and u.
        both = e.select("u", "v").unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m")).coalesce(k)
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).coalesce(k)
        large = materialise(large.distinct().coalesce(k))
        # Small star: of u's neighbours below, all and u go to the smallest.
        least = large.groupBy("u").agg(F.min("v").alias("m")).coalesce(k)
        joined = large.join(least, "u")
        small = joined.select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(least.select("u", F.col("m").alias("v"))).where("u != v")
        small = materialise(small.coalesce(k).distinct().coalesce(k))
        m = small.count()
        if m == n and small.join(e, ["u", "v"], "left_anti").isEmpty():
            break
        e, n = small, m
    return e.groupBy("u").agg(F.min("v").alias("label")).withColumnRenamed("u", "node").unionByName(
        e.select(F.col("v").alias("node"), F.col("v").alias("label")).distinct()
    )
