"""The registered queries of the corpus operators. Each derives its columns from what its operator returns."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from propalign.llm.tables import table


def op1_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from propalign.llm.packing import best_fit_packing

    return best_fit_packing(table(spark, sf_dir, "documents"))


def op2_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    from propalign.llm.quality_rules import quality_rules

    out = quality_rules(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op3_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from propalign.llm.suffix_dedup import suffix_dedup

    out = suffix_dedup(table(spark, sf_dir, "documents"))
    return out.select(
        "doc_id", "n_bytes", (F.col("n_bytes") - F.octet_length("kept")).alias("n_removed"),
        F.size("spans").cast("long").alias("n_spans"), F.sha2("kept", 256).alias("kept_sha256"),
        F.size("passages").cast("long").alias("n_passages"),
    )


def op4_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    from propalign.llm.url_filter import rule_table, url_filter

    return url_filter(table(spark, sf_dir, "pages").select("page_id", "url"), rule_table(spark)).select(
        "page_id", F.col("url_host").alias("host"), F.col("url_path").alias("path"),
        F.col("url_rule").alias("rule"), F.col("url_verdict").alias("verdict"),
    )


def op5_exact_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    from propalign.llm.topk import top_k

    return top_k(table(spark, sf_dir, "embeddings"), lambda vec_id: vec_id % 50 == 0)


def op6_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    from propalign.llm.pii import KINDS, personal_data

    out = personal_data(table(spark, sf_dir, "documents"))
    order = {k: i for i, k in enumerate(KINDS)}
    told = lambda c: F.array_join(F.transform(c, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["stop"].cast("string"))), ",")
    count = lambda k: F.size(F.filter("base", lambda s: s["kind"] == k)).cast("long").alias(f"n_{k}")
    assert list(order) == ["email", "ip", "card", "phone", "secret"]  # the spans come in this order of kinds
    return out.select("doc_id", *[count(k) for k in KINDS[:4]], F.sha2(told("base"), 256).alias("base_sha256"), told("spans").alias("spans"), F.size("spans").cast("long").alias("n_spans"))


def op7_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    from propalign.llm.license_scan import license_scan

    out = license_scan(table(spark, sf_dir, "documents"))
    told = F.transform("matches", lambda m: F.concat_ws(":", m["license"], m["start"].cast("string"), m["stop"].cast("string")))
    return out.select(
        "doc_id", F.size("matches").cast("long").alias("n_matches"),
        F.array_join(F.sort_array(F.array_distinct(F.col("matches.license"))), ",").alias("licenses"),
        F.round(F.array_max("matches.coverage"), 6).alias("coverage"), F.array_join(told, ",").alias("spans"),
    )


def op8_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    from propalign.llm.nnpu import held_out, quality_classifier

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    out = quality_classifier(docs, table(spark, sf_dir, "labels"))
    return out.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def op9_minhash_neardup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from propalign.llm.minhash import near_duplicates

    return near_duplicates(table(spark, sf_dir, "documents"))


def op10_systematic_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    from propalign.llm.mixing import systematic_mix

    return systematic_mix(table(spark, sf_dir, "documents")).select(
        "doc_id", F.col("mix_size").alias("size"), F.col("mix_source_size").alias("source_size"),
        F.col("mix_target").alias("target"), (F.col("mix_size") * F.col("mix_copies")).alias("taken"),
    )


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (
        op1_best_fit_packing, op2_quality_rules, op3_suffix_dedup, op4_url_filter, op5_exact_topk,
        op6_personal_data, op7_license_scan, op8_quality_classifier, op9_minhash_neardup, op10_systematic_mix,
    )
}
