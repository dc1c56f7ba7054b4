"""Small helpers that the corpus operators share."""

from __future__ import annotations

import atexit
import tempfile
import uuid
from collections.abc import Iterable, Iterator
from contextlib import contextmanager
from weakref import WeakKeyDictionary

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructField, StructType

#: Characters that part words, as Java and Python patterns spell them.
SPACE = r"[\x20\x09-\x0D]+"
WORD = r"[^\x20\x09-\x0D]+"

#: Rows that Spark hands a worker at a time. Both sides hold such a batch outside the heap, and texts make rows large.
BATCH_ROWS = 1_000
_ROWS = "spark.sql.execution.arrow.maxRecordsPerBatch"

_ours: dict[str, SparkSession] = {}
_path_of: WeakKeyDictionary[DataFrame, str] = WeakKeyDictionary()


def shared_folder(spark: SparkSession) -> str:
    """The folder that all executors share: spark.checkpoint.dir, or a folder of our own where it is unset (tests)."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        root = _ours.setdefault("", tempfile.mkdtemp(prefix="propalign-"))  # type: ignore[arg-type]
    return str(root).rstrip("/")


@contextmanager
def small_batches(spark: SparkSession) -> Iterator[None]:
    """While it lasts, workers get at most BATCH_ROWS rows at a time; then the session has its own setting again."""
    before = spark.conf.get(_ROWS)
    if not 0 < int(before) <= BATCH_ROWS:
        spark.conf.set(_ROWS, str(BATCH_ROWS))
    try:
        yield
    finally:
        spark.conf.set(_ROWS, before)


def materialise(df: DataFrame) -> DataFrame:
    """Write df once as Parquet into the shared folder and read it back.

    This cuts the lineage: a lost executor costs no more than the tasks that it ran, and later passes read the columns
    that they need.
    """
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/propalign-{spark.sparkContext.applicationId}/{uuid.uuid4().hex}"
    with small_batches(spark):
        df.write.parquet(path)
    _ours[path] = spark
    out = spark.read.schema(df.schema).parquet(path)
    _path_of[out] = path
    return out


def release(*tables: DataFrame) -> None:
    """Delete tables that materialise wrote and nothing reads any more."""
    for df in tables:
        path = _path_of.pop(df)
        _delete(path, _ours.pop(path))


def _delete(path: str, spark: SparkSession) -> None:
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def kept_columns(docs: DataFrame, keep: Iterable[str], results: Iterable[str]) -> list[Column]:
    """The columns of docs called keep, but for those whose names an operator's results have (in any case)."""
    taken = {r.lower() for r in results}
    return [docs[f"`{c}`"] for c in keep if c.lower() not in taken]


def schema_with(fields: Iterable[StructField], ddl: str) -> StructType:
    """A schema of given fields, whatever their names, and of those that ddl names."""
    return StructType([*fields, *StructType.fromDDL(ddl).fields])


@atexit.register
def _clean() -> None:
    for path, spark in _ours.items():
        try:
            if path:
                _delete(path, spark)
        except Exception:  # noqa: BLE001  the session may have ended before
            return


def word_count(text: Column) -> Column:
    """Words of a text; a null text has none."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def unit_hash(*parts: Column) -> Column:
    """A number in [0, 1) from the first 32 bits of an md5, the same in other SQL engines."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", *parts)), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
