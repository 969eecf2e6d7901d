"""Sharding by Karmarkar-Karp differencing.

Equal texts form a group that stays in one shard. Groups are summed with map-side combine, dealt by
hash into cells, and each cell is differenced on its own: the two partial partitions of largest spread
are joined, largest part of the one with smallest part of the other, until one is left. The partial
partitions of the cells are then differenced in the same way. That last step sees one small row per
cell, whatever the number of groups, and cells are numbered so that none outgrows a worker.

Law: `bytes` (sizes near equal). Slots are gapless per shard in order of doc_id: places inside ranges
of doc_id are ranked apart and the ranges' counts are added in front, so no shard is sorted in one task.

Defined results: null text has no bytes, size 1, crc of no bytes, and groups with the empty text.
Repeated rows are equal texts and share a shard, each with a slot of its own. Null ids come first. An
empty table gives an empty result. A group above an eighth of all bytes leaves its shard larger than
the others: it can't be divided.
"""

from __future__ import annotations

import heapq
from itertools import count

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import cut, read_table

SHARDS = 8
GROUPS_PER_CELL = 20_000
MAX_CELLS = 1 << 16


def difference(partials: list[tuple[list[int], list[list]]], shards: int) -> tuple[list[int], list[list]]:
    """Karmarkar-Karp: combine partial partitions (sums, members of each part) until one is left.

    Members are kept as linked pairs, so joining two parts takes constant time.
    """
    order = count()
    heap = []
    for sums, parts in partials:
        ranked = sorted(zip(sums, range(shards), parts, strict=True), key=lambda x: (-x[0], x[1]))
        sums, parts = [x[0] for x in ranked], [x[2] for x in ranked]
        heap.append((sums[-1] - sums[0], next(order), sums, parts))
    heapq.heapify(heap)
    while len(heap) > 1:
        _, _, a, x = heapq.heappop(heap)
        _, _, b, y = heapq.heappop(heap)
        both = [(a[i] + b[-1 - i], i, (x[i], y[-1 - i]) if x[i] and y[-1 - i] else x[i] or y[-1 - i]) for i in range(shards)]
        both.sort(key=lambda p: (-p[0], p[1]))
        sums = [p[0] for p in both]
        heapq.heappush(heap, (sums[-1] - sums[0], next(order), sums, [p[2] for p in both]))
    if not heap:
        return [0] * shards, [()] * shards
    return heap[0][2], heap[0][3]


def flatten(part) -> list:
    """Members of a part; a member is ('g', value)."""
    out, stack = [], [part]
    while stack:
        x = stack.pop()
        if not x:
            continue
        if x[0] == "g":
            out.append(x[1])
        else:
            stack += x
    return out


def single(size: int, member, shards: int) -> tuple[list[int], list]:
    return [size] + [0] * (shards - 1), [("g", member)] + [()] * (shards - 1)


def assign_groups(groups: DataFrame, shards: int = SHARDS) -> DataFrame:
    """group_key, shard for rows of group_key and bytes."""
    cells = max(1, min(MAX_CELLS, -(-groups.count() // GROUPS_PER_CELL)))

    def local(key, table):
        sizes = table.column("bytes").to_pylist()
        rows = sorted(zip(sizes, table.column("group_key").to_pylist(), strict=True), reverse=True)
        sums, parts = difference([single(n, k, shards) for n, k in rows], shards)
        out = [(key[0].as_py(), i, sums[i], k) for i in range(shards) for k in flatten(parts[i])]
        return pa.table({n: pa.array([r[j] for r in out], t) for j, (n, t) in enumerate((("cell", pa.int32()), ("part", pa.int32()), ("part_bytes", pa.int64()), ("group_key", pa.int64())))})

    keyed = groups.withColumn("cell", F.pmod(F.xxhash64("group_key"), F.lit(cells)).cast("int"))
    dealt = cut(keyed.groupBy("cell").applyInArrow(local, "cell int, part int, part_bytes long, group_key long"))
    totals: dict[int, list[int]] = {}
    for row in dealt.select("cell", "part", "part_bytes").distinct().collect():  # bounded: MAX_CELLS times shards rows
        totals.setdefault(row.cell, [0] * shards)[row.part] = row.part_bytes
    partials = [(sums, [("g", (cell, i)) for i in range(shards)]) for cell, sums in sorted(totals.items())]
    _, parts = difference(partials, shards)
    places = [(cell, part, shard) for shard in range(shards) for cell, part in flatten(parts[shard])]
    spark = groups.sparkSession
    final = spark.createDataFrame(places, "cell int, part int, shard int")
    return dealt.join(F.broadcast(final), ["cell", "part"]).select("group_key", "shard")


def with_slots(rows: DataFrame, ranges: int = 64) -> DataFrame:
    """Adds slot: 0, 1, 2, ... within each shard, by doc_id. Ranges of doc_id are ranked on their own."""
    bounds = rows.select(F.percentile_approx("doc_id", [i / ranges for i in range(1, ranges)], 10_000)).first()[0] or []
    bounds = sorted(set(bounds))
    span = F.size(F.filter(F.array(*map(F.lit, bounds)), lambda b: b <= F.coalesce(F.col("doc_id"), F.lit(-(1 << 63))))) if bounds else F.lit(0)
    placed = rows.withColumn("span", span)
    before = placed.groupBy("shard", "span").count().withColumn("before", F.sum("count").over(Window.partitionBy("shard").orderBy("span")) - F.col("count")).drop("count")
    inside = F.row_number().over(Window.partitionBy("shard", "span").orderBy(F.col("doc_id").asc_nulls_first(), "text_crc32", "group_key"))
    return placed.withColumn("inside", inside).join(F.broadcast(before), ["shard", "span"]).withColumn("slot", (F.col("before") + F.col("inside") - 1).cast("long"))


def shard_by_bytes(docs: DataFrame, shards: int = SHARDS) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard."""
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = docs.select("doc_id", (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), F.xxhash64(text).alias("group_key"))
    rows = cut(rows)  # small: the texts are left behind here
    groups = rows.groupBy("group_key").agg(F.sum("size").alias("bytes"))
    out = with_slots(rows.join(assign_groups(groups, shards), "group_key"))
    return out.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def op4_shard_balance(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shard_by_bytes(read_table(spark, sf_dir, "documents"))
