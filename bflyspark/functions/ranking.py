"""Running sums and numbers in an order of ids, without sorting everything in one task."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

BLOCKS = 1 << 20  # blocks that one task adds up at most, per value of `by`


def running(df: DataFrame, id_: str, weight: Column | None = None, by: tuple[str, ...] = ()) -> DataFrame:
    """Adds `before`: the weight of all rows of smaller id. (by, id) is unique.

    Ids are cut into blocks of a power of two; sums per block are added up, and rows inside a block.
    """
    low, high = df.agg(F.min(id_), F.max(id_)).first()
    if low is None:
        return df.withColumn("before", F.lit(0).cast("long"))
    bits = max(12, int(high - low).bit_length() - (BLOCKS.bit_length() - 1))
    own = df.withColumn("_weight", F.lit(1).cast("long") if weight is None else weight).withColumn("_block", F.shiftright(F.col(id_) - F.lit(low), bits))
    sums = own.groupBy(*by, "_block").agg(F.sum("_weight").alias("_all"))
    offset = F.sum("_all").over(Window.partitionBy(*by).orderBy("_block")) - F.col("_all")
    inside = F.sum("_weight").over(Window.partitionBy(*by, "_block").orderBy(id_)) - F.col("_weight")
    placed = own.withColumn("_inside", inside).join(sums.select(*by, "_block", offset.alias("_offset")), [*by, "_block"])
    return placed.withColumn("before", F.col("_offset") + F.col("_inside")).select(*df.columns, "before")
