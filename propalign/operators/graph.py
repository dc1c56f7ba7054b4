"""The similarity graph and what can be done with it."""

from __future__ import annotations

import os
import tempfile

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from propalign.model import PAIR_KEY, PROPERTY_KEY


def checkpointed(df: DataFrame) -> DataFrame:
    """df with its lineage cut by a checkpoint in the cluster's folder, or in one of our own where none is set."""
    sc = df.sparkSession.sparkContext
    if not (df.sparkSession.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()):
        sc.setCheckpointDir(os.path.join(tempfile.gettempdir(), "propalign-checkpoints"))
    return df.checkpoint()


def similarity_graph(sim: DataFrame, min_score: float = 0.0) -> DataFrame:
    return sim.where(F.col("score") >= min_score)


def _nodes(sim: DataFrame) -> DataFrame:
    node = lambda s: F.struct("cls", F.col(f"source_{s}").alias("source"), F.col(f"prop_{s}").alias("prop"))
    return sim.select(node("a").alias("u"), node("b").alias("v"))


def connected_components(sim: DataFrame, threshold: float | None = None) -> DataFrame:
    """CLUSTER rows: properties that matches connect, by transitive closure; the cluster is named after its smallest member.

    Each round every node takes the smallest label among itself and its neighbours, then the label of that label; the second
    step halves paths, so rounds grow with the logarithm of the diameter.
    """
    edges = _nodes(sim.where("is_match") if threshold is None else sim.where(F.col("score") >= threshold))
    both = checkpointed(edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v"))).distinct())
    label = checkpointed(both.select("u").distinct().withColumn("l", F.col("u")))
    while True:
        near = both.join(label.withColumnsRenamed({"u": "v", "l": "lv"}), "v").groupBy("u").agg(F.min("lv").alias("m"))
        step = label.join(near, "u").select("u", F.least("l", "m").alias("l"))
        jump = step.select(F.col("u").alias("k"), F.col("l").alias("kl"))
        new = checkpointed(step.join(jump, step["l"] == jump["k"]).select("u", F.least("l", "kl").alias("l")))
        changed = not new.join(label.withColumnRenamed("l", "old"), "u").where("l != old").isEmpty()
        label = new
        if not changed:
            break
    return label.select("u.cls", "u.source", "u.prop", F.concat_ws("/", "l.cls", "l.source", "l.prop").alias("cluster_id"))


def _unique_merge(group: pd.DataFrame) -> pd.DataFrame:
    """Pairs by falling score; two clusters become one if they share no source."""
    root, sources = {}, {}

    def find(x):
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    rows = group.sort_values(["score", "source_a", "prop_a", "source_b", "prop_b"], ascending=[False, True, True, True, True])
    for r in rows.itertuples(index=False):
        for x in ((r.source_a, r.prop_a), (r.source_b, r.prop_b)):
            if x not in root:
                root[x], sources[x] = x, {x[0]}
        a, b = find((r.source_a, r.prop_a)), find((r.source_b, r.prop_b))
        if a != b and not sources[a] & sources[b]:
            low, high = min(a, b), max(a, b)
            root[high] = low
            sources[low] |= sources.pop(high)
    cls = group["cls"].iloc[0]
    return pd.DataFrame([(cls, s, p, "/".join((cls, *find((s, p))))) for s, p in root], columns=["cls", "source", "prop", "cluster_id"])


def source_unique_clusters(sim: DataFrame, threshold: float | None = None) -> DataFrame:
    """CLUSTER rows with at most one property of a source in a cluster, greedily by score within each component.

    A component is the properties of one concept and its confusions, some for each source; it goes to one task.
    """
    edges = sim.where("is_match") if threshold is None else sim.where(F.col("score") >= threshold)
    parts = connected_components(edges, float("-inf")).select("cls", F.col("source").alias("source_a"), F.col("prop").alias("prop_a"), "cluster_id")
    rows = edges.select(*PAIR_KEY, "score").join(parts, ["cls", "source_a", "prop_a"])
    return rows.groupBy("cluster_id").applyInPandas(_unique_merge, "cls string, source string, prop string, cluster_id string")


def both_ways(sim: DataFrame) -> DataFrame:
    """(cls, source, prop, other_source, other_prop, score) for both ends of each pair."""
    a = sim.select("cls", F.col("source_a").alias("source"), F.col("prop_a").alias("prop"), F.col("source_b").alias("other_source"), F.col("prop_b").alias("other_prop"), "score")
    b = sim.select("cls", F.col("source_b").alias("source"), F.col("prop_b").alias("prop"), F.col("source_a").alias("other_source"), F.col("prop_a").alias("other_prop"), "score")
    return a.unionByName(b)


def partners(sim: DataFrame) -> DataFrame:
    """For each property and other source, its matches there: no, one or several."""
    return both_ways(sim.where("is_match")).groupBy(*PROPERTY_KEY, "other_source").agg(
        F.sort_array(F.collect_list("other_prop")).alias("partners"), F.count("*").alias("n_partners")
    )


def topk(sim: DataFrame, k: int = 3) -> DataFrame:
    """The k strongest partners of each property."""
    order = Window.partitionBy(*PROPERTY_KEY).orderBy(F.col("score").desc(), "other_source", "other_prop")
    return both_ways(sim).withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def keep_equal(sim: DataFrame) -> DataFrame:
    """Matches that are each other's best partner between their sources: a heuristic for equality as against part-of."""
    score = [F.col("score").desc(), F.col("prop_a"), F.col("prop_b")]
    wa = Window.partitionBy("cls", "source_a", "prop_a", "source_b").orderBy(*score)
    wb = Window.partitionBy("cls", "source_b", "prop_b", "source_a").orderBy(*score)
    ranked = sim.where("is_match").withColumns({"_ra": F.row_number().over(wa), "_rb": F.row_number().over(wb)})
    return ranked.where("_ra = 1 and _rb = 1").drop("_ra", "_rb")


def fuse_values(instances: DataFrame, clusters: DataFrame) -> DataFrame:
    """(cls, cluster_id, entity, value, n): an entity's most frequent value for each cluster; ties to the smaller value."""
    rows = instances.join(clusters, PROPERTY_KEY).groupBy("cls", "cluster_id", "entity", "value").agg(F.count("*").alias("n"))
    best = rows.groupBy("cls", "cluster_id", "entity").agg(F.min(F.struct(-F.col("n"), F.col("value"))).alias("x"))
    return best.select("cls", "cluster_id", "entity", F.col("x.value").alias("value"), (-F.col("x.col1")).alias("n"))


def reference_names(spark: SparkSession, clusters: DataFrame) -> DataFrame:
    """The most frequent property name of each cluster."""
    n = clusters.groupBy("cluster_id", "prop").agg(F.count("*").alias("n"))
    return n.groupBy("cluster_id").agg(F.max_by("prop", F.struct("n", "prop")).alias("name"))
