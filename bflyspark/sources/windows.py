"""Query windows: closed, in batches."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMA = "window_id long, t_start long, t_end long"

# Windows that tests and reports use.
FIXED_DAYS = [(0, 2404), (0, 729), (365, 1094), (1000, 1300), (1500, 2400), (2000, 2100)]
FIXED_HOURS = [(0, 719), (0, 167), (100, 400), (24, 47), (500, 719)]


def fixed(spark: SparkSession, spans: list[tuple[int, int]]) -> DataFrame:
    return spark.createDataFrame([(i, a, b) for i, (a, b) in enumerate(spans)], SCHEMA)


def random_windows(spark: SparkSession, n: int, low: int, high: int, seed: int = 1) -> DataFrame:
    """n windows with two ends drawn from [low, high] by modular arithmetic and put in order."""
    width = high - low + 1
    i = F.col("id")
    draw = lambda a, b, c: low + F.pmod(F.pmod(i * a + seed * b + c, F.lit(1_000_003)) * F.pmod(i + c, F.lit(999_983)), F.lit(width))
    a, b = draw(7919, 104729, 12345), draw(15485863, 32452843, 67891)
    return spark.range(n).select(i.alias("window_id"), F.least(a, b).alias("t_start"), F.greatest(a, b).alias("t_end"))


def random_sql(n: int, low: int, high: int, seed: int = 1) -> str:
    width = high - low + 1
    draw = lambda a, b, c: f"({low} + (((i * {a} + {seed * b + c}) % 1000003) * ((i + {c}) % 999983)) % {width})"
    a, b = draw(7919, 104729, 12345), draw(15485863, 32452843, 67891)
    return f"SELECT i AS window_id, least({a}, {b}) AS t_start, greatest({a}, {b}) AS t_end FROM (SELECT unnest(range({n})) AS i)"


def fixed_sql(spans: list[tuple[int, int]]) -> str:
    rows = ", ".join(f"({i}, {a}, {b})" for i, (a, b) in enumerate(spans))
    return f"SELECT CAST(column0 AS BIGINT) AS window_id, CAST(column1 AS BIGINT) AS t_start, CAST(column2 AS BIGINT) AS t_end FROM (VALUES {rows}) AS w(column0, column1, column2)"


def sliding(spark: SparkSession, low: int, high: int, length: int, step: int) -> DataFrame:
    """Windows of one length whose starts are a step apart."""
    starts = spark.range(1).select(F.explode(F.sequence(F.lit(low).cast("long"), F.lit(high).cast("long"), F.lit(step).cast("long"))).alias("t_start"))
    return starts.select(((F.col("t_start") - low) / step).cast("long").alias("window_id"), "t_start", (F.col("t_start") + length - 1).alias("t_end"))


def calendar_years(spark: SparkSession, first: int, last: int, years: int, zero: str = "1995-01-01") -> DataFrame:
    """Windows of whole calendar years, one-year step, as days since zero."""
    year = spark.range(first, last + 1)
    day = lambda y: F.datediff(F.make_date(y, F.lit(1), F.lit(1)), F.lit(zero)).cast("long")
    y = F.col("id").cast("int")
    return year.select((F.col("id") - first).alias("window_id"), day(y).alias("t_start"), (day(y + years) - 1).alias("t_end"))


def calendar_sql(first: int, last: int, years: int, zero: str = "1995-01-01") -> str:
    day = lambda y: f"date_diff('day', DATE '{zero}', make_date({y}, 1, 1))"
    return f"SELECT y - {first} AS window_id, {day('y')} AS t_start, {day(f'y + {years}')} - 1 AS t_end FROM (SELECT unnest(range({first}, {last + 1})) AS y)"
