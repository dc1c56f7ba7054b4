"""URL filters: host-suffix and path-prefix expressions, joined on short hashes and confirmed by full digests.

Each URL becomes the list of expressions that a rule could have (every suffix of its host's labels with every prefix of
its path whose length some rule has). An expression is looked up by the first 32 bits of its SHA-256; a hit counts only
if the whole digests are equal. The longest rule that hits decides, a block before an allow of the same text.

Edge cases: a null URL or one without ``://`` has an empty host and path and gets the default verdict, and so has an
empty rule table for all URLs. Equal rules with both verdicts block. Rules with a null host, path or verdict are left
out. Columns pass
through; those called ``url_*`` or ``_url_*`` are replaced.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from propalign.llm.tables import materialise

#: The rules that the query applies.
RULES = [
    ("org", "/", "allow"),
    ("example.org", "/es/", "block"),
    ("example.org", "/en/1", "block"),
    ("com", "/fr/", "allow"),
    ("com", "/de/", "block"),
]

#: Rule tables of at most so many rows are broadcast (a row has about 200 bytes); larger ones are shuffled.
BROADCAST_RULES = 100_000


def host_of(url: Column) -> Column:
    """What stands between the first ``://`` and the next of ``/?#``, A-Z lower-cased; other letters stay."""
    host = F.coalesce(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1), F.lit(""))
    return F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*(/[^?#]*)", 1), F.lit(""))


def _digest(host: Column, path: Column) -> Column:
    return F.sha2(F.concat(host, F.lit("\n"), path), 256)


def rule_table(spark: SparkSession, rules: list[tuple[str, str, str]] = RULES) -> DataFrame:
    return spark.createDataFrame(rules, "host string, path string, verdict string")


def url_filter(pages: DataFrame, rules: DataFrame, url: str = "url", default: str = "allow") -> DataFrame:
    """The rows of pages with ``url_host``, ``url_path``, ``url_rule`` (host and path of the rule that decides, or null)
    and ``url_verdict``."""
    rules = rules.where("host is not null and path is not null and verdict is not null").select(
        F.lower("host").alias("r_host"), F.col("path").alias("r_path"), F.col("verdict").alias("r_verdict")
    )
    shape = rules.agg(
        F.sort_array(F.collect_set(F.length("r_path"))).alias("lengths"),
        F.coalesce(F.max(F.size(F.split("r_host", r"\."))), F.lit(0)).alias("labels"),
        F.count("*").alias("n"),
    ).first()
    # Rule paths have few different lengths (a URL has some thousand characters), so this list is bounded.
    lengths, labels = (shape["lengths"] or [0]), shape["labels"]
    keyed = rules.select(
        F.substring(_digest(F.col("r_host"), F.col("r_path")), 1, 8).alias("r_short"),
        _digest(F.col("r_host"), F.col("r_path")).alias("r_full"),
        F.struct(
            (F.length("r_host") + F.length("r_path")).alias("size"),
            F.length("r_host").alias("host_size"),
            (F.col("r_verdict") == "block").alias("blocks"),
            F.concat("r_host", "r_path").alias("rule"),
            F.col("r_verdict").alias("verdict"),
        ).alias("r_rank"),
    )
    parts = F.split("url_host", r"\.")
    suffixes = F.transform(
        F.sequence(F.lit(1), F.least(F.size(parts), F.lit(max(labels, 1)))),
        lambda k: F.array_join(F.slice(parts, F.size(parts) - k + 1, k), "."),
    )
    prefixes = F.transform(
        F.filter(F.array(*[F.lit(n) for n in lengths]), lambda n: n <= F.length("url_path")),
        lambda n: F.substring(F.col("url_path"), F.lit(1), n),
    )
    pages = pages.drop(*[c for c in pages.columns if c.startswith(("url_", "_url_")) and c != url])
    rows = pages.withColumns({"url_host": host_of(F.col(url)), "url_path": path_of(F.col(url))})
    # Each address is judged once, however many pages have it.
    addresses = rows.select("url_host", "url_path").distinct().withColumns({"_url_suffixes": suffixes, "_url_prefixes": prefixes})
    expressions = addresses.select(
        F.col("url_host").alias("_url_host"),
        F.col("url_path").alias("_url_path"),
        F.explode(
            F.flatten(
                F.transform("_url_suffixes", lambda h: F.transform("_url_prefixes", lambda p: _digest(h, p)))
            )
        ).alias("_url_full"),
    ).withColumn("_url_short", F.substring("_url_full", 1, 8))
    small = shape["n"] <= BROADCAST_RULES
    hits = expressions.join(
        F.broadcast(keyed) if small else keyed,
        (F.col("_url_short") == F.col("r_short")) & (F.col("_url_full") == F.col("r_full")),
    )
    # Written, so that the join below has an exchange on both sides and a frequent address can be split.
    best = materialise(hits.groupBy("_url_host", "_url_path").agg(F.max("r_rank").alias("_url_best")))
    return (
        rows.join(best, (F.col("url_host") == F.col("_url_host")) & (F.col("url_path") == F.col("_url_path")), "left")
        .withColumns(
            {
                "url_rule": F.col("_url_best.rule"),
                "url_verdict": F.coalesce(F.col("_url_best.verdict"), F.lit(default)),
            }
        )
        .drop("_url_host", "_url_path", "_url_best")
    )
