"""Readers into the instance form (class, source, entity, property, value), and writers."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def read(spark: SparkSession, spec: dict) -> DataFrame:
    """spec: format (parquet, csv, json, orc, text, jdbc), path or paths, options."""
    reader = spark.read.format(spec.get("format", "parquet")).options(**spec.get("options", {}))
    if "schema" in spec:
        reader = reader.schema(spec["schema"])
    paths = spec.get("paths", spec.get("path"))
    return reader.load(paths) if paths is not None else reader.load()


def text_value(c: Column, kind: T.DataType) -> Column:
    """A literal as text: fractions with two places, times to the second."""
    if isinstance(kind, (T.DoubleType, T.FloatType)):
        return c.cast("decimal(18,2)").cast("string")
    if isinstance(kind, (T.TimestampType, T.TimestampNTZType)):
        return F.date_format(c, "yyyy-MM-dd HH:mm:ss")
    return c.cast("string")


def unpivot(df: DataFrame, cls: str, source: Column, entity: Column, columns: list[str] | None = None) -> DataFrame:
    """INSTANCE rows of a wide table; nulls give none. Spark reads only the columns named."""
    columns = columns or df.columns
    wide = df.select(source.cast("string").alias("_source"), entity.cast("string").alias("_entity"), *[text_value(F.col(c), df.schema[c].dataType).alias(c) for c in columns])
    long = wide.unpivot(["_source", "_entity"], columns, "prop", "value").where("value is not null")
    return long.select(F.lit(cls).alias("cls"), F.col("_source").alias("source"), F.col("_entity").alias("entity"), "prop", "value")


def flatten(df: DataFrame, cls: str, source: Column, entity: Column) -> DataFrame:
    """INSTANCE rows of a nested table: arrays give one instance for each element, structs dotted names, maps a property for
    each key."""
    base = df.withColumns({"_source": source.cast("string"), "_entity": entity.cast("string")})

    def parts(c: Column, kind: T.DataType, name: Column, rows: DataFrame) -> list[DataFrame]:
        if isinstance(kind, T.StructType):
            return [x for f in kind for x in parts(c[f.name], f.dataType, F.concat_ws(".", name, F.lit(f.name)), rows)]
        if isinstance(kind, T.ArrayType):
            out = rows.select("_source", "_entity", name.alias("_name"), F.explode(c).alias("_x"))
            return parts(F.col("_x"), kind.elementType, F.col("_name"), out)
        if isinstance(kind, T.MapType):
            out = rows.select("_source", "_entity", name.alias("_outer"), F.explode(c).alias("_k", "_x")).withColumn("_name", F.concat_ws(".", "_outer", "_k"))
            return parts(F.col("_x"), kind.valueType, F.col("_name"), out)
        return [rows.select(F.lit(cls).alias("cls"), F.col("_source").alias("source"), F.col("_entity").alias("entity"), name.alias("prop"), text_value(c, kind).alias("value"))]

    found = [x for f in df.schema for x in parts(F.col(f"`{f.name}`"), f.dataType, F.lit(f.name), base)]
    return reduce(DataFrame.unionByName, found).where("value is not null")


def pages(df: DataFrame, cls: str = "text") -> DataFrame:
    """INSTANCE rows of raw web pages (page_id, url, html); the source is the host."""
    pick = lambda p: F.nullif(F.regexp_extract("html", p, 1), F.lit(""))
    wide = df.select(
        F.col("page_id").cast("string").alias("entity"), F.regexp_extract("url", r"://([^/?#]+)", 1).alias("source"),
        pick(r"(?is)<title[^>]*>([^<]*)</title>").alias("title"), pick(r"(?is)<h1[^>]*>([^<]*)</h1>").alias("heading"),
        pick(r"(?i)<html[^>]* lang=[\"']?([a-z-]+)").alias("language"), F.col("url").alias("address"),
    )
    return unpivot(wide, cls, F.col("source"), F.col("entity"), ["title", "heading", "language", "address"])


def write(df: DataFrame, path: str, fmt: str = "parquet", partition: list[str] | None = None, mode: str = "errorifexists") -> None:
    writer = df.write.format(fmt).mode(mode)
    (writer.partitionBy(*partition) if partition else writer).save(path)
