"""Graphs on the given tables, and literal graphs of known counts."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .graph import TemporalBipartite, from_table

DAY_ZERO, HOUR_ZERO = "1995-01-01", "2024-01-01 00:00:00"
MODULUS = 10007

# Literal graphs (u, v, t).
TOY = [(1, 4, 2), (1, 5, 3), (3, 4, 4), (3, 5, 4), (2, 4, 5), (2, 5, 6)]
TWO_WEDGES = [(1, 3, 1), (1, 4, 3), (2, 3, 4), (2, 4, 2)]
DUPLICATES = [(1, 4, 1), (1, 4, 9), (1, 5, 2), (2, 4, 3), (2, 5, 8)]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def days(column: str) -> Column:
    return F.datediff(F.col(column), F.lit(DAY_ZERO)).cast("long")


def _orders_lines(spark, sf_dir, u, v):
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", *{c for c in (u, v) if c.startswith("l_") and c != "l_orderkey"})
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_orderdate", *{c for c in (u, v) if c.startswith("o_")})
    both = lines.join(orders, lines["l_orderkey"] == orders["o_orderkey"])
    return from_table(both.select(F.col(u).alias("u"), F.col(v).alias("v"), days("o_orderdate").alias("t")))


def power_rank(residue: Column, k: int) -> Column:
    """Whole-number power of a residue, scaled back below the modulus after each factor."""
    out = residue
    for _ in range(k - 1):
        out = F.floor(out * residue / MODULUS)  # below 2^53, and a quotient is whole or far from the next whole number
    return out


def _skew(spark, sf_dir, k: int, sides: str):
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_shipdate")
    order, line, part = (F.col(c).cast("long") for c in ("l_orderkey", "l_linenumber", "l_partkey"))
    rv = F.pmod(7919 * order + 104729 * line, F.lit(MODULUS))
    ru = F.pmod(48271 * order + 69621 * line + 16807 * part, F.lit(MODULUS))
    return from_table(lines.select((power_rank(ru, k) if sides == "both" else ru).alias("u"), power_rank(rv, k).alias("v"), days("l_shipdate").alias("t")))


def load(spark: SparkSession, sf_dir: str, name: str, **options) -> TemporalBipartite:
    """g1 ... g9 of the graph catalog."""
    if name == "g1":
        return _orders_lines(spark, sf_dir, "o_custkey", "l_suppkey")
    if name == "g2":
        return _orders_lines(spark, sf_dir, "o_custkey", "l_partkey")
    if name == "g3":
        return from_table(table(spark, sf_dir, "lineitem").select("l_partkey", "l_suppkey", days("l_shipdate").alias("t")), "l_partkey", "l_suppkey")
    if name == "g4":
        return _orders_lines(spark, sf_dir, "l_suppkey", "l_orderkey")
    if name == "g5":
        return _orders_lines(spark, sf_dir, "l_partkey", "l_orderkey")
    if name in ("g6", "g9"):
        events = table(spark, sf_dir, "events")
        start, stamp = F.lit(HOUR_ZERO).cast("timestamp_ntz"), F.col("ts").cast("timestamp_ntz")
        hours, micros = F.timestamp_diff("HOUR", start, stamp), F.timestamp_diff("MICROSECOND", start, stamp)
        kind = F.get_json_object("props", "$.k").cast("long") if name == "g6" else F.length("event_type") * 1000 + F.ascii("event_type")
        return from_table(events.select(F.col("user_id").alias("u"), kind.cast("long").alias("v"), (micros if options.get("micros") else hours).alias("t")))
    if name == "g7":
        docs = table(spark, sf_dir, "documents")
        words = docs.select("doc_id", F.explode(F.array_distinct(F.filter(F.split(F.lower("text"), r"\s+"), lambda w: w != ""))).alias("word"))
        return from_table(words.select(F.col("doc_id").alias("u"), F.xxhash64("word").alias("v"), F.col("doc_id").alias("t")))
    if name == "g8":
        return _skew(spark, sf_dir, options.get("k", 2), options.get("sides", "both"))
    raise ValueError(f"no graph named {name}")


#: DuckDB text of each graph's edges, over the same tables.
_JOINED = "SELECT {u} AS u, {v} AS v, date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS t FROM lineitem JOIN orders ON l_orderkey = o_orderkey"
_RV = f"((7919 * l_orderkey + 104729 * l_linenumber) % {MODULUS})"
_RU = f"((48271 * l_orderkey + 69621 * l_linenumber + 16807 * l_partkey) % {MODULUS})"


def _power_sql(r: str, k: int) -> str:
    out = r
    for _ in range(k - 1):
        out = f"(({out} * {r}) // {MODULUS})"
    return out


def edges_sql(name: str, **options) -> str:
    if name in ("g1", "g2", "g4", "g5"):
        u, v = {"g1": ("o_custkey", "l_suppkey"), "g2": ("o_custkey", "l_partkey"), "g4": ("l_suppkey", "l_orderkey"), "g5": ("l_partkey", "l_orderkey")}[name]
        return _JOINED.format(u=u, v=v)
    if name == "g3":
        return "SELECT l_partkey AS u, l_suppkey AS v, date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE)) AS t FROM lineitem"
    if name == "g6":
        return "SELECT user_id AS u, CAST(json_extract_string(props, '$.k') AS BIGINT) AS v, date_diff('hour', TIMESTAMP '2024-01-01', CAST(ts AS TIMESTAMP)) AS t FROM events"
    if name == "g9":
        return "SELECT user_id AS u, length(event_type) * 1000 + ascii(event_type) AS v, date_diff('hour', TIMESTAMP '2024-01-01', CAST(ts AS TIMESTAMP)) AS t FROM events"
    if name == "g7":
        return "SELECT DISTINCT doc_id AS u, w AS v, doc_id AS t FROM (SELECT doc_id, unnest(string_split_regex(lower(text), '\\s+')) AS w FROM documents) WHERE w <> ''"
    if name == "g8":
        k = options.get("k", 2)
        u = _power_sql(_RU, k) if options.get("sides", "both") == "both" else _RU
        return f"SELECT {u} AS u, {_power_sql(_RV, k)} AS v, date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE)) AS t FROM lineitem"
    raise ValueError(f"no graph named {name}")


def literal(spark: SparkSession, rows: list[tuple[int, int, int]]) -> TemporalBipartite:
    return from_table(spark.createDataFrame(rows, "u long, v long, t long"))
