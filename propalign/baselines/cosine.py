"""Plain unsupervised use of word vectors: cosine of mean vectors and one threshold."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from propalign.functions.lexicon import dot
from propalign.model import PAIR_KEY, PROPERTY_KEY
from propalign.operators.pairs import candidates


def match(profile: DataFrame, threshold: float = 0.6, origin: str = "names", least: float | None = None) -> DataFrame:
    """SIM rows of the pairs with at least a score of least (None: threshold; -1: all pairs). Vectors are brought to length 1 once for
    each property, so a pair takes one product."""
    vec = {"names": F.col("name_emb"), "instances": F.col("val_emb"), "both": F.concat("name_emb", "val_emb")}[origin]
    norm = F.sqrt(dot(F.col("v"), F.col("v")))
    rows = profile.select(*PROPERTY_KEY, vec.alias("v")).select(*PROPERTY_KEY, norm.alias("_n"), "v")
    unit = F.when(F.col("_n") > 0, F.transform("v", lambda x: x / F.col("_n"))).otherwise(F.col("v"))
    pairs = candidates(rows.select(*PROPERTY_KEY, unit.alias("v")), ["v"])
    sim = pairs.select(*PAIR_KEY, F.round(dot(F.col("v_a"), F.col("v_b")), 9).alias("score"))
    return sim.where(F.col("score") >= (threshold if least is None else least)).withColumn("is_match", F.col("score") >= threshold)
