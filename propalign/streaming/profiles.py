"""Incremental profiles from a stream of instances, and matching for each micro-batch.

Means are sums over counts, so a stream keeps mergeable sums for each property. profile_stream aggregates by property and a
time window with a watermark; merge_profiles folds batches into a table of sums; match_stream rescores after each.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from propalign.functions.formats import META_NAMES, numeric, with_meta
from propalign.model import PROPERTY_KEY


def instance_stream(events: DataFrame, sources: int = 8) -> DataFrame:
    """(INSTANCE, ts) from a stream of event rows."""
    value = F.col("value").cast("decimal(18,2)").cast("string")
    props = F.array(
        F.struct(F.lit("user").alias("prop"), F.col("user_id").cast("string").alias("value")),
        F.struct(F.lit("event type").alias("prop"), F.col("event_type").alias("value")),
        F.struct(F.lit("amount").alias("prop"), value.alias("value")),
        F.struct(F.lit("key").alias("prop"), F.get_json_object("props", "$.k").alias("value")),
    )
    source = F.concat(F.lit("e"), F.lpad((F.col("user_id") % sources).cast("string"), 2, "0"))
    rows = events.select(F.lit("event").alias("cls"), source.alias("source"), F.col("event_id").cast("string").alias("entity"), F.inline(props), F.col("ts").cast("timestamp").alias("ts"))
    return rows.where("value is not null")


def sums(instances: DataFrame, keys: list) -> DataFrame:
    """Mergeable sums of the format features and numbers by keys."""
    rows = with_meta(instances).withColumn("_num", numeric(F.col("value")))
    return rows.groupBy(*keys).agg(F.count("*").alias("n"), F.sum("_num").alias("s_num"), *[F.sum(c).alias(f"s_{c}") for c in META_NAMES])


def profile_stream(instances: DataFrame, watermark: str = "1 hour", width: str = "1 day", slide: str | None = None) -> DataFrame:
    """Sums by property and event-time window; rows later than the watermark are dropped. instances needs ts."""
    return sums(instances.withWatermark("ts", watermark), [*PROPERTY_KEY, F.window("ts", width, slide).alias("win")])


def sessions(instances: DataFrame, watermark: str = "1 hour", gap: str = "30 minutes") -> DataFrame:
    """Sums by property and session: runs of instances without a longer gap."""
    return sums(instances.withWatermark("ts", watermark), [*PROPERTY_KEY, F.session_window("ts", gap).alias("win")])


def deduplicated(instances: DataFrame, watermark: str = "1 hour") -> DataFrame:
    """An instance that is sent again within the watermark counts once."""
    return instances.withWatermark("ts", watermark).dropDuplicatesWithinWatermark([*PROPERTY_KEY, "entity"])


def means(summed: DataFrame) -> DataFrame:
    """(property, n_instances, meta, num) from sums of any number of windows or batches."""
    total = summed.groupBy(*PROPERTY_KEY).agg(F.sum("n").alias("n"), F.sum("s_num").alias("s_num"), *[F.sum(f"s_{c}").alias(f"s_{c}") for c in META_NAMES])
    return total.select(*PROPERTY_KEY, F.col("n").alias("n_instances"), F.array(*[F.col(f"s_{c}") / F.col("n") for c in META_NAMES]).alias("meta"), (F.col("s_num") / F.col("n")).alias("num"))


def match_stream(instances: DataFrame, rescore: Callable[[DataFrame, int], None], checkpoint: str, trigger: dict | None = None) -> StreamingQuery:
    """Calls rescore(sums of a micro-batch, batch number) for each micro-batch; a batch that is repeated after a failure has
    the same number, so writing by number keeps sums right."""
    return (
        instances.writeStream.foreachBatch(lambda df, i: rescore(sums(df.drop("ts"), PROPERTY_KEY), i))
        .option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()
    )
