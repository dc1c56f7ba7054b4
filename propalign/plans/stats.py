"""Statistics of the datasets."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from propalign.functions.strings import DISTANCES
from propalign.model import PAIR_KEY, PROPERTY_KEY
from propalign.operators.pairs import pair_matrix


def property_catalog(instances: DataFrame) -> DataFrame:
    """The schema as the data has it: (property, n_instances, n_entities, n_values)."""
    return instances.groupBy(*PROPERTY_KEY).agg(F.count("*").alias("n_instances"), F.count_distinct("entity").alias("n_entities"), F.count_distinct("value").alias("n_values"))


def support(instances: DataFrame, approx: bool = False) -> DataFrame:
    distinct = F.approx_count_distinct if approx else F.count_distinct
    return instances.groupBy(*PROPERTY_KEY).agg(distinct("value").alias("n_values"), distinct("entity").alias("n_entities"))


def min_support(instances: DataFrame, n: int) -> DataFrame:
    """Instances of properties with at least n of them."""
    often = instances.groupBy(*PROPERTY_KEY).agg(F.count("*").alias("_n")).where(F.col("_n") >= n).drop("_n")
    return instances.join(often, PROPERTY_KEY, "left_semi")


def source_stats(instances: DataFrame) -> DataFrame:
    """(cls, source, n_properties, n_entities, n_instances)."""
    return instances.groupBy("cls", "source").agg(F.count_distinct("prop").alias("n_properties"), F.count_distinct("entity").alias("n_entities"), F.count("*").alias("n_instances"))


def dataset_stats(instances: DataFrame, truth: DataFrame) -> DataFrame:
    """(cls, n_sources, n_properties, n_entities, n_matching_pairs)."""
    matching = truth.groupBy("cls").agg(F.count("*").alias("n_matching_pairs"))
    rows = instances.groupBy("cls").agg(
        F.count_distinct("source").alias("n_sources"), F.count_distinct("source", "prop").alias("n_properties"), F.count_distinct("source", "entity").alias("n_entities")
    )
    return rows.join(matching, "cls", "left").withColumn("n_matching_pairs", F.coalesce("n_matching_pairs", F.lit(0)))


#: The pairs of the sample table, (source_a, prop_a, source_b, prop_b).
SAMPLE = [
    ("g00", "retail price", "g03", "price tag"), ("g00", "size", "g01", "dimension"),
    ("g00", "retail price", "g01", "dimension"), ("g00", "brand", "g01", "dispatch day"),
]


def sample_features(profile: DataFrame, labelled: DataFrame) -> DataFrame:
    """A few features of two matching and two other pairs. The pairs are a fixed list, so few rows come to the driver."""
    import numpy as np

    spark = profile.sparkSession
    want = spark.createDataFrame([("goods", *p) for p in SAMPLE], PAIR_KEY)
    from propalign.operators.profile import vector_of

    vec = profile.select(*PROPERTY_KEY, vector_of(profile).alias("v"))
    a = vec.withColumnsRenamed({"source": "source_a", "prop": "prop_a", "v": "va"})
    b = vec.withColumnsRenamed({"source": "source_b", "prop": "prop_b", "v": "vb"})
    rows = want.join(a, ["cls", "source_a", "prop_a"]).join(b, ["cls", "source_b", "prop_b"]).join(labelled.select(*PAIR_KEY, "label"), PAIR_KEY).orderBy(*PAIR_KEY).collect()
    out = []
    for r in rows:
        x = pair_matrix(np.array([r["va"]], dtype=float), np.array([r["vb"]], dtype=float), [r["prop_a"]], [r["prop_b"]])[0]
        d = (len(x) - 37) // 2
        out.append((*[r[c] for c in PAIR_KEY], r["label"], float(x[-8 + DISTANCES.index("levenshtein")]), float(x[1]), float(x[28]), float(x[29 + 3]), float(x[29 + d + 1])))
    return spark.createDataFrame(out, ", ".join(f"{c} string" for c in PAIR_KEY) + ", label int, levenshtein double, letter_share double, number double, value_vector_4 double, name_vector_2 double")


def cost(steps: dict[str, Callable[[], DataFrame]]) -> list[dict]:
    """Rows and wall-clock seconds of each step, run to the end by a sink that keeps nothing."""
    out = []
    for name, make in steps.items():
        began = time.time()
        df = make()
        n = df.count()
        out.append({"step": name, "rows": n, "seconds": round(time.time() - began, 3)})
    return out
