"""Matcher graph with word vectors: syntactic links that meaning may cancel, and links that meaning adds."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from propalign.functions.formats import words
from propalign.functions.lexicon import cosine
from propalign.functions.strings import normal
from propalign.model import PAIR_KEY, PROPERTY_KEY
from propalign.operators.pairs import candidates

SYN, NEG, POS = 0.2, 0.2, 0.4
GRID = (0.2, 0.4, 0.6, 0.8)


def scores(profile: DataFrame, lexicon: DataFrame) -> DataFrame:
    """PAIR rows with syn (string similarity) and coherence (mean cosine of all word pairs; null without vectors).

    Both are computed for pairs of different names and joined back.
    """
    names = profile.select("cls", "source", "prop", normal(F.col("prop")).alias("n"))
    pairs = candidates(names, ["n"])
    need = pairs.select("n_a", "n_b").distinct()
    vectors = names.select("n").distinct().select("n", F.explode(words(F.col("n"))).alias("word")).join(lexicon, "word").groupBy("n").agg(F.collect_list("vec").alias("vs"))
    va, vb = vectors.withColumnsRenamed({"n": "n_a", "vs": "va"}), vectors.withColumnsRenamed({"n": "n_b", "vs": "vb"})
    each = F.flatten(F.transform("va", lambda x: F.transform("vb", lambda y: cosine(x, y))))
    mean = F.aggregate(each, F.lit(0.0), lambda s, x: s + x) / F.size(each)
    longest = F.greatest(F.length("n_a"), F.length("n_b"), F.lit(1))
    both = need.join(va, "n_a", "left").join(vb, "n_b", "left").select(
        "n_a", "n_b", (1 - F.levenshtein("n_a", "n_b") / longest).alias("syn"),
        F.when(F.col("va").isNotNull() & F.col("vb").isNotNull(), F.round(mean, 9)).alias("coherence"),
    )
    return pairs.join(both, ["n_a", "n_b"]).select(*PAIR_KEY, F.round("syn", 9).alias("syn"), "coherence")


def decide(syn, coherence, s, n, p):
    """Whether a pair is linked at thresholds s (syntactic), n (negative) and p (positive)."""
    cancelled = F.coalesce(coherence < n, F.lit(False))
    return ((syn >= s) & ~cancelled) | F.coalesce(coherence >= p, F.lit(False))


def match(profile: DataFrame, lexicon: DataFrame, syn: float = SYN, neg: float = NEG, pos: float = POS) -> DataFrame:
    rows = scores(profile, lexicon)
    score = F.greatest(F.col("syn"), F.coalesce("coherence", F.lit(0.0)))
    return rows.select(*PAIR_KEY, score.alias("score"), decide(F.col("syn"), F.col("coherence"), F.lit(syn), F.lit(neg), F.lit(pos)).alias("is_match"))


def grid(spark: SparkSession, values: tuple[float, ...] = GRID) -> DataFrame:
    """All threshold combinations: a small constant table."""
    return spark.createDataFrame([(s, n, p) for s in values for n in values for p in values], "syn_t double, neg_t double, pos_t double")


def sweep(scored: DataFrame, spark: SparkSession, values: tuple[float, ...] = GRID) -> DataFrame:
    """(dataset, thresholds, tp, fp, fn) of all combinations. scored: (dataset, syn, coherence, label); read once.

    Thresholds only see which of the grid's values a score reaches, so pairs are first counted by that.
    """
    level = lambda c: sum(((F.coalesce(c, F.lit(-1.0)) >= v).cast("int") for v in values[1:]), (F.coalesce(c, F.lit(-1.0)) >= values[0]).cast("int"))
    counts = scored.groupBy("dataset", "label", level(F.col("syn")).alias("ls"), level(F.col("coherence")).alias("lc"), F.col("coherence").isNull().alias("none")).agg(F.count("*").alias("n"))
    rows = counts.crossJoin(F.broadcast(grid(spark, values)))  # a few dozen counts by 64 combinations
    rank = lambda t: F.array_position(F.array(*map(F.lit, values)), t)
    linked = ((F.col("ls") >= rank(F.col("syn_t"))) & ~(~F.col("none") & (F.col("lc") < rank(F.col("neg_t"))))) | (~F.col("none") & (F.col("lc") >= rank(F.col("pos_t"))))
    count = lambda c: F.coalesce(F.sum(F.when(c, F.col("n"))), F.lit(0))
    one = F.col("label") == 1
    return rows.withColumn("_m", linked).groupBy("dataset", "syn_t", "neg_t", "pos_t").agg(
        count(F.col("_m") & one).alias("tp"), count(F.col("_m") & ~one).alias("fp"), count(~F.col("_m") & one).alias("fn")
    )
