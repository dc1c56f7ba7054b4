"""Unsupervised lexical matcher over names: equal names, rare shared words, string similarity; best partners only.

Pairs below a score are not made: of the different names of a class, only those are compared that share one of their rarest
words (enough of them that the others can't reach the score) or an unchanged part at nearly the same place (a name cut into one
part more than the edits allowed keeps at least one). Both are equi-joins, and lose no pair that reaches the score.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from propalign.functions.formats import words
from propalign.functions.strings import normal
from propalign.model import PAIR_KEY, PROPERTY_KEY
from propalign.operators.graph import checkpointed
from propalign.operators.pairs import candidates

THRESHOLD = 0.6
#: A string similarity counts for so much.
DISCOUNT = 0.8


#: Leaves room for the rounding of sums.
SLACK = 1e-6


def _mass(w: Column) -> Column:
    return F.aggregate(w, F.lit(0.0), lambda s, x: s + x["r"])


def _score() -> Column:
    """Of norm_a, w_a and norm_b, w_b."""
    both, every = _mass(F.array_intersect("w_a", "w_b")), _mass(F.array_union("w_a", "w_b"))
    longest = F.greatest(F.length("norm_a"), F.length("norm_b"), F.lit(1))
    by_text = DISCOUNT * (1 - F.levenshtein("norm_a", "norm_b") / longest)
    return F.round(F.when(F.col("norm_a") == F.col("norm_b"), 1.0).otherwise(F.greatest(F.when(every > 0, both / every).otherwise(0.0), by_text)), 9)


def by_rare_words(names: DataFrame, least: float) -> DataFrame:
    """(cls, norm_a, norm_b) of names whose words can be alike enough: they share one of those that come first, by rarity, until
    the rest is lighter than least of the whole."""
    w = F.array_sort(F.transform("w", lambda x: F.struct((-x["r"]).alias("o"), x["word"].alias("word"), x["r"].alias("r"))))
    first = F.filter("o", lambda x, i: _mass(F.slice("o", i + 1, F.size("o"))) >= least * _mass(F.col("o")) - SLACK)
    rows = names.where(F.size("w") > 0).withColumn("o", w).select("cls", "norm", F.explode(F.transform(first, lambda x: x["word"])).alias("word"))
    b = rows.withColumnRenamed("norm", "norm_b")
    return rows.withColumnRenamed("norm", "norm_a").join(b, ["cls", "word"]).where("norm_a < norm_b").select("cls", "norm_a", "norm_b")


def by_parts(names: DataFrame, least: float) -> DataFrame:
    """(cls, norm_a, norm_b) of names with few enough edits between them: the shorter one, cut into one part more than edits
    allowed, has a part that stands in the longer one, moved no further than edits to its left and right explain."""
    share = 1 - least / DISCOUNT
    if share <= 0:
        return names.select("cls", F.col("norm").alias("norm_a"), F.col("norm").alias("norm_b")).where("false")
    edits = lambda n: F.floor(share * n + 1e-9).cast("int")
    own = F.length("norm")
    # Columns: short, long (lengths), k (edits allowed), i (the part, from 1), start and size of the part in the shorter name.
    start = F.floor((F.col("i") - 1) * F.col("short") / (F.col("k") + 1)).cast("int") + 1
    size = F.floor(F.col("i") * F.col("short") / (F.col("k") + 1)).cast("int") + 1 - start
    parts = lambda df: df.withColumn("k", edits(F.col("long"))).where("k > 0").withColumn("i", F.explode(F.sequence(F.lit(1), F.col("k") + 1))).withColumns({"start": start, "size": size})
    longest = F.ceil(own / (least / DISCOUNT) + 1).cast("int")
    lengths = F.filter(F.sequence(own, longest), lambda n: n - edits(n) <= own)
    index = parts(names.select("cls", F.col("norm").alias("norm_a"), own.alias("short"), F.explode(lengths).alias("long")))
    index = index.select("cls", "norm_a", "short", "long", "i", F.substring("norm_a", F.col("start"), F.col("size")).alias("part"))
    probe = parts(names.select("cls", F.col("norm").alias("norm_b"), own.alias("long"), F.explode(F.sequence(own - edits(own), own)).alias("short")))
    more, left, right = F.col("long") - F.col("short"), F.col("i") - 1, F.col("k") + 1 - F.col("i")
    low = F.greatest(F.lit(1), F.col("start") - left, F.col("start") + more - right)
    high = F.least(F.col("long") - F.col("size") + 1, F.col("start") + left, F.col("start") + more + right)
    probe = probe.withColumns({"low": low, "high": high}).where("low <= high").withColumn("at", F.explode(F.sequence("low", "high")))
    probe = probe.select("cls", "norm_b", "short", "long", "i", F.substring("norm_b", F.col("at"), F.col("size")).alias("part")).distinct()
    found = index.join(probe, ["cls", "short", "long", "i", "part"]).where("norm_a != norm_b")
    return found.select("cls", F.least("norm_a", "norm_b").alias("norm_a"), F.greatest("norm_a", "norm_b").alias("norm_b"))


def _alike(props: DataFrame, least: float) -> DataFrame:
    """(PAIR, score) of the pairs with at least such a score. Properties and names are written once, since all joins read them."""
    props = checkpointed(props)
    names = checkpointed(props.select("cls", "norm", "w").dropDuplicates(["cls", "norm"]))
    a, b = (names.withColumnsRenamed({"norm": f"norm_{s}", "w": f"w_{s}"}) for s in "ab")
    some = checkpointed(by_rare_words(names, least).unionByName(by_parts(names, least)).distinct())
    scored = some.join(a, ["cls", "norm_a"]).join(b, ["cls", "norm_b"]).select("cls", "norm_a", "norm_b", _score().alias("score")).where(F.col("score") >= least)
    turned = scored.select("cls", F.col("norm_b").alias("norm_a"), F.col("norm_a").alias("norm_b"), "score")
    same = names.select("cls", F.col("norm").alias("norm_a"), F.col("norm").alias("norm_b"), F.lit(1.0).alias("score"))
    side = lambda s: props.select("cls", F.col("norm").alias(f"norm_{s}"), F.col("source").alias(f"source_{s}"), F.col("prop").alias(f"prop_{s}"))
    pairs = scored.unionByName(turned).unionByName(same.where(F.col("score") >= least))
    return pairs.join(side("a"), ["cls", "norm_a"]).join(side("b"), ["cls", "norm_b"]).where("source_a < source_b").select(*PAIR_KEY, "score")


def match(profile: DataFrame, threshold: float = THRESHOLD, cardinality: str = "1:1", synonyms: DataFrame | None = None, least: float | None = None) -> DataFrame:
    """SIM rows. synonyms: (word, concept): words are replaced by their concept before they are compared.

    least: pairs of a lower score are left out, and mostly never looked at; None: those below threshold. 0 has all pairs, which
    grow with the square of the properties.
    """
    props = profile.select(*PROPERTY_KEY, normal(F.col("prop")).alias("norm"), F.array_distinct(words(F.col("prop"))).alias("w"))
    if synonyms is not None:
        rows = props.select(*PROPERTY_KEY, "norm", F.explode_outer("w").alias("word")).join(synonyms, "word", "left")
        props = rows.groupBy(*PROPERTY_KEY, "norm").agg(F.array_sort(F.collect_set(F.coalesce("concept", "word"))).alias("w"))
    # How many properties of the class have each word; rare words say more.
    freq = props.select("cls", F.explode("w").alias("word")).groupBy("cls", "word").agg(F.count("*").alias("f"))
    total = props.groupBy("cls").agg(F.count("*").alias("t"))
    rarity = F.when(F.col("t") > 1, 1 - F.log(F.col("f").cast("double")) / F.log(F.col("t").cast("double"))).otherwise(F.lit(1.0))
    weight = freq.join(total, "cls").select("cls", "word", rarity.alias("r"))
    weighted = props.select(*PROPERTY_KEY, "norm", F.explode_outer("w").alias("word")).join(weight, ["cls", "word"], "left")
    props = weighted.groupBy(*PROPERTY_KEY, "norm").agg(F.array_sort(F.collect_list(F.when(F.col("word").isNotNull(), F.struct("word", "r")))).alias("w"))
    least = threshold if least is None else least
    if min(least, threshold) > 0:
        # Both windows below need every pair that can be a match.
        sim = _alike(props, min(least, threshold))
    else:
        sim = candidates(props, ["norm", "w"]).select(*PAIR_KEY, _score().alias("score"))
    sim = sim.withColumn("is_match", F.col("score") >= threshold)
    if cardinality == "n:m":
        return sim.where(F.col("score") >= least)
    wa = Window.partitionBy("cls", "source_a", "prop_a", "source_b").orderBy(F.col("score").desc(), "prop_b")
    wb = Window.partitionBy("cls", "source_b", "prop_b", "source_a").orderBy(F.col("score").desc(), "prop_a")
    best = sim.withColumns({"_a": F.row_number().over(wa), "_b": F.row_number().over(wb)})
    return best.withColumn("is_match", F.col("is_match") & (F.col("_a") == 1) & (F.col("_b") == 1)).drop("_a", "_b").where(F.col("score") >= least)
