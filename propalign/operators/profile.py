"""Profiles: one feature vector for each property, averaged over its instances.

The mean word vector of a property's values is a mean of means and therefore linear in the word vectors: each word's weight
is the sum, over the values, of its share among the value's words. So instances are first reduced to (property, word)
weights, with map-side sums, and only these meet the lexicon; instances never carry vectors. Words without a vector count as
zeros, and a value without words counts as one unknown word; the weights of a property thus add up to its number of values.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from propalign.functions.formats import META_NAMES, numeric, with_meta, words
from propalign.model import PROPERTY_KEY

#: A lexicon of at most so many words is broadcast (64 doubles each: 100 MB at most); others are shuffled by word.
BROADCAST_WORDS = 200_000

AGGREGATES = {"mean": F.avg, "min": F.min, "max": F.max, "stddev": F.stddev_pop, "median": F.median}


def value_word_weights(instances: DataFrame) -> DataFrame:
    """(property, word, weight, n_values); the word is null for values without words."""
    toks = instances.select(*PROPERTY_KEY, words(F.col("value")).alias("w"))
    rows = toks.select(*PROPERTY_KEY, F.explode_outer("w").alias("word"), F.when(F.size("w") > 0, 1.0 / F.size("w")).otherwise(1.0).alias("share"))
    return rows.groupBy(*PROPERTY_KEY, "word").agg(F.sum("share").alias("weight"))


def _weighted_mean(weights: DataFrame, lexicon: DataFrame, keys: list[str], d: int, name: str) -> DataFrame:
    """Mean vector by keys. weights: (keys, word, weight)."""
    found = weights.join(lexicon, "word", "left")
    # One sum for each component: plain aggregates that combine before the shuffle and spill like any other.
    sums = [F.sum(F.coalesce(F.get("vec", F.lit(i)), F.lit(0.0)) * F.col("weight")).alias(f"s{i}") for i in range(d)]
    grouped = found.groupBy(*keys).agg(F.sum("weight").alias("_w"), *sums)
    return grouped.select(*keys, F.array(*[F.col(f"s{i}") / F.col("_w") for i in range(d)]).alias(name))


def _ready(lexicon: DataFrame) -> tuple[DataFrame, int]:
    """The lexicon, broadcast if it is small, and the length of its vectors."""
    n, d = lexicon.agg(F.count("*"), F.max(F.size("vec"))).first()
    return (F.broadcast(lexicon) if n <= BROADCAST_WORDS else lexicon), d or 0


def value_embedding(instances: DataFrame, lexicon: DataFrame) -> DataFrame:
    lex, d = _ready(lexicon)
    return _weighted_mean(value_word_weights(instances), lex, PROPERTY_KEY, d, "val_emb")


def name_embedding(properties: DataFrame, lexicon: DataFrame) -> DataFrame:
    """Mean vector of the words of each property's name."""
    lex, d = _ready(lexicon)
    names = properties.select("prop").distinct().select("prop", F.explode_outer(words(F.col("prop"))).alias("word"), F.lit(1.0).alias("weight"))
    means = _weighted_mean(names, lex, ["prop"], d, "name_emb")
    return properties.select(*PROPERTY_KEY).distinct().join(means, "prop").select(*PROPERTY_KEY, "name_emb")


def meta_profile(instances: DataFrame, agg: str = "mean", missing: float | None = -1.0, exact_entities: bool = False) -> DataFrame:
    """(property, n_instances, n_entities, meta, num): aggregated format features and numbers; one shuffle. n_entities, which no
    feature uses, is a sketch's estimate unless it is asked for exactly."""
    f = AGGREGATES[agg]
    rows = with_meta(instances).withColumn("_num", numeric(F.col("value"), missing))
    return rows.groupBy(*PROPERTY_KEY).agg(
        F.count("*").alias("n_instances"), (F.count_distinct if exact_entities else F.approx_count_distinct)("entity").alias("n_entities"),
        F.array(*[f(F.col(c)) for c in META_NAMES]).alias("meta"), F.coalesce(f(F.col("_num")), F.lit(-1.0)).alias("num"),
    )


def profile(instances: DataFrame, lexicon: DataFrame, agg: str = "mean", distinct_values: bool = False, missing: float | None = -1.0) -> DataFrame:
    """PROFILE: (property, n_instances, n_entities, meta, num, val_emb, name_emb).

    agg: mean, median, min, max or stddev of the format features; word vectors are always averaged. distinct_values: each
    different value of a property counts once.
    """
    if distinct_values:
        instances = instances.dropDuplicates([*PROPERTY_KEY, "value"])
    meta = meta_profile(instances, agg, missing)
    values = value_embedding(instances, lexicon)
    names = name_embedding(meta, lexicon)
    return meta.join(values, PROPERTY_KEY).join(names, PROPERTY_KEY)


def vector_of(profile_: DataFrame) -> Column:
    """The 29 + 2d numbers of a property as one array."""
    as_double = lambda c: F.col(c).cast("array<double>")
    return F.concat(as_double("meta"), F.array(F.col("num").cast("double")), as_double("val_emb"), as_double("name_emb"))
