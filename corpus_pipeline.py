"""The corpus pipeline: from raw documents to packed training sequences.

Each stage takes all documents that its predecessor kept and returns a DataFrame, which is written as Parquet and read
again for the next. All but the last return the columns of documents.

Every stage takes null, empty and very long texts, null and repeated ids, repeated rows, tables without rows, and further columns
of any name, which it passes on; what becomes of these is told at each stage.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from propalign.llm.minhash import one_of_each
from propalign.llm.mixing import emit_mix
from propalign.llm.nnpu import score, train
from propalign.llm.packing import best_fit_packing
from propalign.llm.pii import redact
from propalign.llm.tables import materialise, table


def _unused(docs: DataFrame, name: str) -> str:
    """name, longer by as many letters as it takes to be no column of docs."""
    taken = {c.lower() for c in docs.columns}
    while name in taken:
        name += "_"
    return name


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the positive-unlabelled classifier doesn't reject. Each row is judged by its own text; null and empty texts
    by their zero counts. Where labels are too few to learn from, nothing is rejected."""
    model = train(docs, table(spark, sf_dir, "labels"))
    if model["weights"] is None:
        return docs
    name = _unused(docs, "pipeline_score")
    return score(docs, model, name=name).where(F.col(name) >= 0.5).drop(name)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each component of near copies; rows without a word, or with a null text, are in none and stay. Decided by
    row, so repeated and null ids make no difference; rows that repeat an id and its text stay once."""
    return one_of_each(docs)


def redact_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All rows, with personal data replaced by its kind, and n_chars counted anew. Null texts stay null, with their n_chars;
    repeated rows are redacted each."""
    out = redact(docs)
    kind = docs.schema["n_chars"].dataType
    return out.withColumn("n_chars", F.when(F.col("text").isNull(), F.col("n_chars")).otherwise(F.length("text").cast(kind)))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each row as often as the mix takes it, none at most three times its source's size. Texts without a word are taken at their
    source's rate; a null source is a source; repeated rows are rows of their own."""
    return emit_mix(docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all rows with their places in sequences. A null or empty text is one piece, its end token; rows that the mix
    repeats have pieces each."""
    return best_fit_packing(docs)


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality_classifier", keep_good),
    ("near_dedup", drop_near_duplicates),
    ("personal_data", redact_personal_data),
    ("mixing", mix_sources),
    ("packing", pack_sequences),
]

#: A trained classifier and shared shingle sets are beyond SQL; the stages are tested against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES:
        docs = materialise(stage(spark, docs, sf_dir))
    return docs
