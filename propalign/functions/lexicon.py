"""Word vectors: a curated list of words and concepts blended with given vectors, a control without meaning, and trained ones."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

EPSILON = 0.25

#: Words of each concept. A word's place gives its number; some words of names are left out on purpose,
#: and some stand in names of two properties, so that vectors neither cover nor decide everything.
CONCEPTS = {
    "price": ["price", "cost", "retail", "tag", "worth"],
    "size": ["size", "dimension", "extent", "measure"],
    "brand": ["brand", "maker", "manufacturer", "make"],
    "name": ["name", "title", "label", "called", "heading"],
    "type": ["type", "category", "sort", "style"],
    "quantity": ["quantity", "amount", "count", "units", "pieces"],
    "discount": ["discount", "rebate", "reduction"],
    "tax": ["tax", "duty", "levy"],
    "ship": ["ship", "shipped", "dispatch", "sent", "delivery"],
    "date": ["date", "day", "on", "time", "when", "stamp"],
    "flag": ["flag", "mark", "code"],
    "status": ["status", "state", "condition", "stage"],
    "total": ["total", "sum", "value", "extended"],
    "nation": ["nation", "country", "land"],
    "region": ["region", "area", "continent"],
    "balance": ["balance", "credit", "funds", "bal"],
    "segment": ["segment", "market", "sector"],
    "customer": ["customer", "client", "buyer", "party"],
    "order": ["order", "purchase", "purchased", "placed"],
    "priority": ["priority", "urgency", "importance"],
    "year": ["year", "month"],
    "user": ["user", "visitor", "account", "member"],
    "kind": ["kind", "event", "action", "activity"],
    "key": ["key", "index", "position"],
    "body": ["body", "text", "content", "message"],
    "language": ["language", "lang", "tongue"],
    "length": ["length", "chars", "characters"],
    "quality": ["quality", "grade", "rating"],
    "toxic": ["toxic", "toxicity", "harm"],
    "address": ["address", "url", "link", "location"],
    "role": ["role", "speaker", "author"],
    "max": ["max", "most", "highest", "largest", "last", "final"],
    "return": ["return", "returned", "back"],
    "line": ["line", "row"],
}


def word_concepts() -> list[tuple[str, int, int]]:
    """(word, number of its concept, number of the word); the two kinds of numbers don't meet."""
    out, word = [], len(CONCEPTS)
    for c, words in enumerate(CONCEPTS.values()):
        for w in words:
            out.append((w, c, word))
            word += 1
    return out


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def cosine(a: Column, b: Column) -> Column:
    norm = F.sqrt(dot(a, a) * dot(b, b))
    return F.when(norm > 0, dot(a, b) / norm).otherwise(F.lit(0.0))


def _unit(v: Column) -> Column:
    norm = F.sqrt(F.aggregate(v, F.lit(0.0), lambda s, x: s + x * x))
    return F.transform(v, lambda x: x / norm)


def blended(spark: SparkSession, vectors: DataFrame, epsilon: float = EPSILON) -> DataFrame:
    """LEXICON: words of a concept lie close together. vectors: (vec_id, embedding)."""
    rows = spark.createDataFrame(word_concepts(), "word string, concept_id int, word_id int")
    v = vectors.select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    c, w = v.withColumnsRenamed({"vec_id": "concept_id", "v": "vc"}), v.withColumnsRenamed({"vec_id": "word_id", "v": "vw"})
    both = F.broadcast(rows).join(c, "concept_id").join(w, "word_id")
    mixed = F.zip_with("vc", "vw", lambda x, y: x * (1 - epsilon) + y * epsilon)
    return both.select("word", _unit(mixed).alias("vec"))


def hashed(spark: SparkSession, vectors: DataFrame) -> DataFrame:
    """LEXICON without meaning: every word has a vector of its own."""
    rows = spark.createDataFrame([(w, i) for w, _, i in word_concepts()], "word string, vec_id long")
    return F.broadcast(rows).join(vectors.select("vec_id", F.col("embedding").cast("array<double>").alias("vec")), "vec_id").select("word", "vec")


def trained(texts: DataFrame, text: str = "text", size: int = 64, seed: int = 7, min_count: int = 5) -> DataFrame:
    """LEXICON from the corpus itself, by word2vec."""
    from propalign.operators.skipgram import fit

    return fit(texts.select(F.col(text).alias("text")), size, seed, min_count)


def prune(lexicon: DataFrame, used: DataFrame) -> DataFrame:
    """The words that occur. used: (word)."""
    return lexicon.join(used.select("word").distinct(), "word", "left_semi")
