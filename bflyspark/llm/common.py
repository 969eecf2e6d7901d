"""Helpers that the operators of this subpackage share."""

from __future__ import annotations

import ctypes
import gc
import sys
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

ASCII_UPPER, ASCII_LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    bounded_batches(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir, which driver and executors share. Without that setting a local folder serves a local master alone."""
    sc = spark.sparkContext
    path = spark.conf.get("spark.checkpoint.dir", None)
    current = sc._jsc.sc().getCheckpointDir()
    if current.isEmpty():
        if not path and (not sc.master.startswith("local") or sc.master.startswith("local-cluster")):
            raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
        sc.setCheckpointDir(path or tempfile.mkdtemp(prefix="bfly-checkpoint-"))
        current = sc._jsc.sc().getCheckpointDir()
    return path or current.get()


def cut(df: DataFrame) -> DataFrame:
    """Cut the lineage of a small table through the shared checkpoint folder."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def stored(df: DataFrame, label: str, row_group: int = 32 << 20) -> DataFrame:
    """Write a table to the shared folder as Parquet and read it back: it outlives lost executors.

    Small row groups bound what a writer holds and what a reader of long values takes in at once.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").option("parquet.block.size", row_group).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def ascii_lower(col: Column) -> Column:
    """Lower-case A-Z alone; other letters stay as they are."""
    return F.translate(col, ASCII_UPPER, ASCII_LOWER)


def per_worker(name: str, version, build):
    """One value per name in each Python worker process: later tasks reuse it until another version is asked for."""
    cache = sys.__dict__.setdefault("_bfly_worker_cache", {})
    held = cache.get(name)
    if held is None or held[0] != version:
        cache.pop(name, None)
        held = cache[name] = (version, build())
    return held[1]


def forget(*names: str) -> None:
    """Drop values that an earlier stage has left in this worker, and hand the memory back."""
    cache = sys.__dict__.get("_bfly_worker_cache", {})
    if [cache.pop(n) for n in names if n in cache]:
        gc.collect()
        trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
        if trim:
            trim(0)


def bounded_batches(spark: SparkSession, rows: int = 2000, size: int = 8 << 20) -> None:
    """Arrow batches of fewer rows and bytes, as long texts would make the usual ones large."""
    for key, limit in (("spark.sql.execution.arrow.maxRecordsPerBatch", rows), ("spark.sql.execution.arrow.maxBytesPerBatch", size)):
        now = spark.conf.get(key).removesuffix("B").removesuffix("b")
        if not now.isdigit() or not 0 < int(now) <= limit:
            spark.conf.set(key, limit)
