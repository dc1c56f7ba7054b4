"""Formal-concept matcher over names: properties are objects, the words of their names attributes.

Two properties match if their concept is the same (equal words), or if what they share is the largest shared concept of both
between their two sources and covers half of the smaller set of words.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from propalign.functions.formats import words
from propalign.model import PAIR_KEY, PROPERTY_KEY
from propalign.operators.graph import checkpointed
from propalign.operators.pairs import candidates


def _sharing(props: DataFrame) -> DataFrame:
    """(PAIR, n, u, least) of pairs with a word in common, by an equi-join of the different sets of words on their words."""
    props = checkpointed(props.where(F.size("w") > 0).withColumn("k", F.concat_ws(" ", "w")))
    rows = props.select("cls", "k", F.size("w").alias("size"), "w").dropDuplicates(["cls", "k"]).select("cls", "k", "size", F.explode("w").alias("word"))
    a, b = (rows.withColumnsRenamed({"k": f"k_{s}", "size": f"size_{s}"}) for s in "ab")
    both = a.join(b, ["cls", "word"]).groupBy("cls", "k_a", "k_b", "size_a", "size_b").agg(F.count("*").cast("int").alias("n"))
    side = lambda s: props.select("cls", F.col("k").alias(f"k_{s}"), F.col("source").alias(f"source_{s}"), F.col("prop").alias(f"prop_{s}"))
    pairs = both.join(side("a"), ["cls", "k_a"]).join(side("b"), ["cls", "k_b"]).where("source_a < source_b")
    return pairs.select(*PAIR_KEY, "n", (F.col("size_a") + F.col("size_b") - F.col("n")).alias("u"), F.least("size_a", "size_b").alias("least"))


def match(profile: DataFrame, every_pair: bool = False) -> DataFrame:
    """SIM rows of the pairs that share a word; every_pair: of the others too, whose score is 0 (they grow with the square of the
    properties)."""
    props = profile.select(*PROPERTY_KEY, F.array_sort(F.array_distinct(words(F.col("prop")))).alias("w"))
    if every_pair:
        pairs = candidates(props, ["w"])
        pairs = pairs.withColumns({"n": F.size(F.array_intersect("w_a", "w_b")), "u": F.size(F.array_union("w_a", "w_b")), "least": F.least(F.size("w_a"), F.size("w_b"))})
    else:
        pairs = _sharing(props)
    most_a = F.max("n").over(Window.partitionBy("cls", "source_a", "prop_a", "source_b"))
    most_b = F.max("n").over(Window.partitionBy("cls", "source_b", "prop_b", "source_a"))
    equal = (F.col("n") > 0) & (F.col("n") == F.col("u"))
    largest = (F.col("n") > 0) & (F.col("n") == most_a) & (F.col("n") == most_b) & (2 * F.col("n") >= F.col("least"))
    score = F.when(F.col("u") > 0, F.col("n") / F.col("u")).otherwise(F.lit(0.0))
    return pairs.select(*PAIR_KEY, score.alias("score"), (equal | largest).alias("is_match"))
