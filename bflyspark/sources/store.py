"""Edges from files, and indexes kept as sorted Parquet with a manifest."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.indexes import Index
from ..operators.wedges import GROUP
from .graph import TemporalBipartite, from_table

EDGE_SCHEMA = "u long, v long, t long"


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", low: int | None = None, high: int | None = None, **options) -> TemporalBipartite:
    """Edges of a parquet, orc, csv or json source; a window becomes a filter of the scan."""
    reader = spark.read.options(**options)
    df = reader.schema(EDGE_SCHEMA).csv(path) if fmt == "csv" else reader.schema(EDGE_SCHEMA).json(path) if fmt == "json" else reader.format(fmt).load(path)
    if low is not None:
        df = df.where(F.col("t") >= low)
    if high is not None:
        df = df.where(F.col("t") <= high)
    return from_table(df)


def read_blank_separated(spark: SparkSession, path: str, comment: str = "%") -> TemporalBipartite:
    """Edge lists as public collections spell them: u v [weight] t, lines with a mark are comments."""
    parts = F.split(F.trim("value"), r"\s+")
    lines = spark.read.text(path).where(~F.col("value").startswith(comment) & (F.trim("value") != "")).select(parts.alias("p"))
    return from_table(lines.select(F.col("p")[0].cast("long").alias("u"), F.col("p")[1].cast("long").alias("v"), F.element_at("p", -1).cast("long").alias("t")))


def save(index: Index, path: str, cells: int = 64) -> None:
    """Points by ranges of l, sorted, so that a window reads the files from its start on; groups by their keys."""
    spark = (index.points if index.points is not None else index.groups).sparkSession
    if index.points is not None:
        width = max(1, cells)
        bounds = index.points.agg(F.min("l").alias("a"), F.max("l").alias("b")).first()
        step = max(1, ((bounds.b or 0) - (bounds.a or 0)) // width + 1)
        cell = F.floor((F.col("l") - F.lit(bounds.a or 0)) / step).cast("int")
        index.points.withColumn("part_l", cell).repartition("part_l").sortWithinPartitions("part_l", "l", "r").write.mode("overwrite").partitionBy("part_l").parquet(f"{path}/points")
        index = Index(index.points, index.groups, {**index.meta, "low": bounds.a or 0, "step": step})
    if index.groups is not None:
        index.groups.repartition(*GROUP).sortWithinPartitions(*GROUP, "r").write.mode("overwrite").parquet(f"{path}/groups")
    manifest = json.dumps({**index.meta, "points": index.points is not None, "groups": index.groups is not None})
    spark.createDataFrame([(manifest,)], "manifest string").coalesce(1).write.mode("overwrite").text(f"{path}/manifest")


def load(spark: SparkSession, path: str) -> Index:
    meta = json.loads(spark.read.text(f"{path}/manifest").first()[0])
    points = spark.read.parquet(f"{path}/points") if meta["points"] else None
    groups = spark.read.parquet(f"{path}/groups") if meta["groups"] else None
    return Index(points, groups, meta)


def points_from(index: Index, start: int) -> DataFrame:
    """Points that windows from `start` on can count; the folder of each range of l prunes files."""
    cell = (start - index.meta["low"]) // index.meta["step"]
    return index.points.where((F.col("part_l") >= cell) & (F.col("l") >= start))


def bucketed(df: DataFrame, name: str, buckets: int, *keys: str) -> None:
    """A table dealt and sorted by keys, so that joins and sums on them need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, *keys).sortBy(*keys).saveAsTable(name)
