"""The matcher for SQL users: functions, a table function and views."""

from __future__ import annotations

import json
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from propalign.functions.strings import DISTANCES, all_eight, jaro_winkler, normal_py
from propalign.model import INSTANCE


class NameDistances:
    """SELECT * FROM name_distances(a, b): a row for each of the eight distances of two names."""

    def eval(self, a: str, b: str) -> Iterator[tuple[str, float]]:
        yield from zip(DISTANCES, all_eight(normal_py(a or ""), normal_py(b or "")), strict=True)


class PropertyInstances:
    """SELECT * FROM property_instances(cls, source, entity, json): a row for each field of a JSON object that isn't null; fields
    of nested objects are called by their path. With LATERAL, it turns a table's rows into instances."""

    def eval(self, cls: str, source: str, entity: str, row: str) -> Iterator[tuple[str, str, str, str, str]]:
        todo = [("", json.loads(row or "{}"))]
        while todo:
            path, x = todo.pop(0)
            if isinstance(x, dict):
                todo += [(f"{path}.{k}" if path else k, v) for k, v in x.items()]
            elif isinstance(x, list):
                todo += [(path, v) for v in x]
            elif x is not None and path:
                yield cls, source, entity, path, str(x).lower() if isinstance(x, bool) else str(x)


def register(spark: SparkSession, views: dict[str, DataFrame] | None = None) -> None:
    """Registers name_similarity(a, b), name_distances(a, b), property_instances(cls, source, entity, json) and a view for each
    DataFrame given."""

    @F.pandas_udf("double")
    def name_similarity(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([jaro_winkler(normal_py(x or ""), normal_py(y or "")) for x, y in zip(a, b, strict=True)])

    spark.udf.register("name_similarity", name_similarity)
    spark.udtf.register("name_distances", F.udtf(NameDistances, returnType="distance string, value double"))
    spark.udtf.register("property_instances", F.udtf(PropertyInstances, returnType=INSTANCE))
    for name, df in (views or {}).items():
        df.createOrReplaceTempView(name)
