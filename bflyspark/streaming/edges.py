"""Structured Streaming over event edges."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.scratch import scratch
from . import maintenance


def event_edges(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """u, v, ts of a growing folder of event files; the schema is read once. A path that is one file works too: as a pattern."""
    schema = spark.read.parquet(path).schema
    pattern = f"{path[:-1]}[{path[-1]}]"
    events = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(pattern)
    return events.select(F.col("user_id").alias("u"), F.get_json_object("props", "$.k").cast("long").alias("v"), F.col("ts").cast("timestamp").alias("ts"), "event_type")


def deduplicated(edges: DataFrame, delay: str = "1 day") -> DataFrame:
    """Each (u, v, ts) once within the watermark."""
    return edges.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["u", "v", "ts"])


def tumbling(edges: DataFrame, length: str = "1 day", delay: str = "1 day") -> DataFrame:
    """Edges per window; windows close as the watermark passes."""
    return edges.withWatermark("ts", delay).groupBy(F.window("ts", length)).agg(F.count("*").alias("edges"))


def sliding(edges: DataFrame, length: str = "7 days", step: str = "1 day", delay: str = "1 day") -> DataFrame:
    return edges.withWatermark("ts", delay).groupBy(F.window("ts", length, step)).agg(F.count("*").alias("edges"))


def sessions(edges: DataFrame, gap: str = "1 hour", delay: str = "1 day") -> DataFrame:
    return edges.withWatermark("ts", delay).groupBy(F.session_window("ts", gap), "u").agg(F.count("*").alias("edges"))


def hours(edges: DataFrame) -> DataFrame:
    """u, v, t with t in whole hours of the event clock; events without a property make no edge."""
    t = F.timestamp_diff("HOUR", F.lit("2024-01-01 00:00:00").cast("timestamp"), F.col("ts"))
    return edges.where("u is not null and v is not null").select("u", "v", t.cast("long").alias("t"))


class Maintained:
    """An index kept up by a stream, batch by batch. A batch that is delivered again is passed over by its id."""

    def __init__(self, spark: SparkSession, sink: Callable[[maintenance.State, DataFrame, int], None] | None = None):
        self.state, self.last, self.sink = maintenance.empty(spark), -1, sink

    def take(self, batch: DataFrame, batch_id: int) -> None:
        if batch_id <= self.last:
            return
        self.state, added = maintenance.append(self.state, hours(batch), f"batch-{batch_id}")
        self.last = batch_id
        if self.sink:
            self.sink(self.state, added, batch_id)

    def follow(self, edges: DataFrame) -> None:
        """Take in what is there and stop."""
        writer = edges.writeStream.foreachBatch(self.take).option("checkpointLocation", scratch(edges.sparkSession, "stream"))
        writer.trigger(availableNow=True).start().awaitTermination()


def in_order_and_late(edges: DataFrame, latest: DataFrame, delay: str = "1 day") -> tuple[DataFrame, DataFrame]:
    """Edges of a batch that the watermark lets through, and those that come later than the delay behind `latest` (one row, ts)."""
    marked = edges.crossJoin(F.broadcast(latest.select((F.col("ts") - F.expr(f"INTERVAL {delay}")).alias("watermark"))))
    on_time = F.col("watermark").isNull() | (F.col("ts") >= F.col("watermark"))
    return marked.where(on_time).drop("watermark"), marked.where(~on_time).drop("watermark")


def partner_increments(edges: DataFrame) -> DataFrame:
    """v, u, partners: for each new edge, how many earlier distinct neighbours its right vertex had.

    The sum of these increments is the number of wedges through right vertices. State: each pair once, and a
    count per vertex, so that taking in an edge touches one number however many neighbours there are.
    """
    first = edges.where("v is not null").withWatermark("ts", "40 days").dropDuplicates(["u", "v"])

    def update(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        known = state.get[0] if state.exists else 0
        for batch in batches:
            users = batch.sort_values(["ts", "u"])["u"]
            yield pd.DataFrame({"v": key[0], "u": users.to_numpy(), "partners": range(known, known + len(users))})
            known += len(users)
        state.update((known,))

    return first.groupBy("v").applyInPandasWithState(update, "v long, u long, partners long", "known long", "append", "NoTimeout")


def labelled(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """Stream with a static table of vertex labels (u, label)."""
    return edges.join(labels, "u")


def paired(a: DataFrame, b: DataFrame, within: str = "1 hour", delay: str = "1 day") -> DataFrame:
    """Two streams joined where the same user acts in both within an interval."""
    x = a.select(F.col("u").alias("u1"), F.col("v").alias("v1"), F.col("ts").alias("ts1")).withWatermark("ts1", delay)
    y = b.select(F.col("u").alias("u2"), F.col("v").alias("v2"), F.col("ts").alias("ts2")).withWatermark("ts2", delay)
    return x.join(y, F.expr(f"u1 = u2 AND ts2 > ts1 AND ts2 <= ts1 + INTERVAL {within}"))


def run_to_table(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Take in what is there and stop; the result as Parquet in the shared folder. Complete results replace the table at each batch."""
    spark = stream.sparkSession
    path = scratch(spark, name)
    if mode == "complete":
        writer = stream.writeStream.outputMode(mode).foreachBatch(lambda rows, _: rows.write.mode("overwrite").parquet(path))
    else:
        writer = stream.writeStream.outputMode(mode).format("parquet").option("path", path)
    writer.option("checkpointLocation", scratch(spark, "stream")).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(path)
