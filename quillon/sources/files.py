"""Basket text files, and the folder that all executors share."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_local: list[str] = []
_tables: list[str] = []


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir, or a temporary folder if a local master has none."""
    shared = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if shared:
        return shared
    master = spark.sparkContext.master
    if not (master == "local" or master.startswith("local[")):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if not _local:
        _local.append(tempfile.mkdtemp(prefix="quillon-files-"))
        atexit.register(shutil.rmtree, _local[0], ignore_errors=True)
    return _local[0]


def stored(df: DataFrame, what: str) -> DataFrame:
    """`df` written as Parquet to the shared folder and read again, which cuts its lineage there."""
    path = f"{shared_folder(df.sparkSession)}/quillon-{what}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _tables.append(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def discard_all(spark: SparkSession) -> None:
    """Deletes all tables that this process stored; for when no result that reads them is used any more."""
    while _tables:
        place = spark._jvm.org.apache.hadoop.fs.Path(_tables.pop())
        place.getFileSystem(spark._jsc.hadoopConfiguration()).delete(place, True)


def write_baskets(rows: DataFrame, path: str) -> None:
    """(tid, items) as lines of tab-separated items; an empty transaction is an empty line."""
    rows.select(F.concat_ws("\t", "items").alias("value")).write.text(path)


def read_baskets(spark: SparkSession, path: str) -> DataFrame:
    """(tid, items) of lines of tab-separated items; lines have no key."""
    parts = F.filter(F.split("value", "\t"), lambda x: x != "")
    return spark.read.text(path).select(F.lit(None).cast("long").alias("tid"), F.array_sort(F.array_distinct(parts)).alias("items"))
