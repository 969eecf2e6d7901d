"""Queries of methods, variants, baselines, measures and workloads, each with DuckDB text where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import PRIME, hash_sql, kept_sql
from ..functions.intervals import active_interval
from ..operators import apps, baselines, dominance, duration, hardness, indexes, measures
from ..operators.wedges import concentration, group_points, group_sizes, one_sided_wedges, priority_wedges, with_stairs
from ..sources import catalog, graph, windows
from . import experiments, sqlapi

Query = Callable[[SparkSession, str], DataFrame]
DAYS, HOURS = windows.FIXED_DAYS, windows.FIXED_HOURS


def spans_of(name: str) -> list[tuple[int, int]]:
    return HOURS if name in ("g6", "g9") else [(0, 199), (0, 99), (50, 400), (0, 1 << 40)] if name == "g7" else DAYS


# DuckDB text


def counts_sql(edges: str, wins: str, end: str = "v") -> str:
    """Independent of priority, intervals and points: distinct pairs per window, wedges by id, sums of C(c, 2)."""
    mid = "u" if end == "v" else "v"
    return f"""
WITH e AS ({edges}), w AS ({wins}),
p AS (SELECT DISTINCT w.window_id, e.u, e.v FROM e JOIN w ON e.t BETWEEN w.t_start AND w.t_end),
c AS (SELECT a.window_id, count(*) AS c FROM p a JOIN p b ON a.window_id = b.window_id AND a.{mid} = b.{mid} AND a.{end} < b.{end} GROUP BY a.window_id, a.{end}, b.{end})
SELECT CAST(w.window_id AS BIGINT) AS window_id, CAST(w.t_start AS BIGINT) AS t_start, CAST(w.t_end AS BIGINT) AS t_end, CAST(coalesce(sum(c * (c - 1) // 2), 0) AS BIGINT) AS butterflies
FROM w LEFT JOIN c ON w.window_id = c.window_id GROUP BY w.window_id, w.t_start, w.t_end"""


def arcs_sql(edges: str, times: bool = False) -> str:
    """CTEs up to wedges g(side, x, z, y) by priority; with times also l and r for pairs of one time."""
    t = ", t" if times else ""
    lr = ", least(h.t, k.t) AS l, greatest(h.t, k.t) AS r" if times else ""
    return f"""
e AS ({edges}), p AS (SELECT DISTINCT u, v{t} FROM e), q AS (SELECT DISTINCT u, v FROM e),
du AS (SELECT u, count(*) AS d FROM q GROUP BY u), dv AS (SELECT v, count(*) AS d FROM q GROUP BY v),
arcs AS MATERIALIZED (SELECT 0 AS side, p.u AS a, p.v AS b, du.d AS da, dv.d AS db{t} FROM p JOIN du ON p.u = du.u JOIN dv ON p.v = dv.v
 UNION ALL SELECT 1, p.v, p.u, dv.d, du.d{t} FROM p JOIN du ON p.u = du.u JOIN dv ON p.v = dv.v),
heads AS MATERIALIZED (SELECT * FROM arcs WHERE da > db OR (da = db AND (side > 1 - side OR (side = 1 - side AND a < b)))),
g AS MATERIALIZED (SELECT h.side, h.a AS x, k.a AS z, h.b AS y{lr} FROM heads h JOIN arcs k ON h.side = k.side AND h.b = k.b WHERE h.da > k.da OR (h.da = k.da AND h.a < k.a))"""


def three_paths_sql(edges: str, wins: str) -> str:
    return f"""
WITH e AS ({edges}), w AS ({wins}),
p AS (SELECT DISTINCT w.window_id, e.u, e.v FROM e JOIN w ON e.t BETWEEN w.t_start AND w.t_end),
du AS (SELECT window_id, u, count(*) AS d FROM p GROUP BY 1, 2), dv AS (SELECT window_id, v, count(*) AS d FROM p GROUP BY 1, 2),
s AS (SELECT p.window_id, sum((du.d - 1) * (dv.d - 1)) AS n FROM p JOIN du ON p.window_id = du.window_id AND p.u = du.u JOIN dv ON p.window_id = dv.window_id AND p.v = dv.v GROUP BY 1)
SELECT CAST(w.window_id AS BIGINT) AS window_id, CAST(w.t_start AS BIGINT) AS t_start, CAST(w.t_end AS BIGINT) AS t_end, CAST(coalesce(n, 0) AS BIGINT) AS three_paths FROM w LEFT JOIN s ON w.window_id = s.window_id"""


def timed_sql(edges: str) -> str:
    return f"""
e AS (SELECT DISTINCT * FROM ({edges})),
i AS (SELECT a.v AS x, b.v AS z, a.u AS y, least(a.t, b.t) AS l, greatest(a.t, b.t) AS r FROM e a JOIN e b ON a.u = b.u AND a.v < b.v AND a.t <> b.t),
f AS (SELECT a.x, a.z, a.y AS y1, b.y AS y2, least(a.l, b.l) AS l, greatest(a.r, b.r) AS r FROM i a JOIN i b ON a.x = b.x AND a.z = b.z AND a.y < b.y AND a.l <> b.l AND a.l <> b.r AND a.r <> b.l AND a.r <> b.r)"""


def deltas_sql(edges: str, deltas: list[int]) -> str:
    rows = ", ".join(f"({d})" for d in deltas)
    return f"WITH {timed_sql(edges)}, d AS (SELECT CAST(column0 AS BIGINT) AS delta FROM (VALUES {rows}) AS t(column0)) SELECT d.delta, CAST(count(f.l) AS BIGINT) AS butterflies FROM d LEFT JOIN f ON f.r - f.l <= d.delta GROUP BY d.delta"


# Builders


def with_windows(name: str, method: Callable, wins: list | None = None, end: str = "v", **options) -> tuple[Query, str]:
    spans = wins or spans_of(name)

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return method(catalog.load(spark, sf_dir, name, **options), windows.fixed(spark, spans))

    return run, counts_sql(catalog.edges_sql(name, **options), windows.fixed_sql(spans), "u" if name == "g7" else end)


def enumerated(layout: str = "scan"):
    return lambda g, w: indexes.query_enumerated(indexes.build_enumerated(g), w, layout)


def grouped(layout: str = "scan"):
    return lambda g, w: indexes.query_grouped(indexes.build_grouped(g), w, layout)


def hybrid(**options):
    return lambda g, w: indexes.query_hybrid(indexes.build_hybrid(g, **options), w)


def plain(make: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> tuple[Query, str | None]:
    return make, sql


def delta_table(spark: SparkSession, deltas: list[int]) -> DataFrame:
    return spark.createDataFrame([(d,) for d in deltas], "delta long")


DELTAS = [30, 90, 200, 365, 600, 730, 2404]
MANY_DELTAS = [(i * 7919) % 2405 for i in range(1, 51)]
YEARS = (1995, 2000, 2)


def random_batch(name: str, method, n: int = 20, high: int = 2404) -> tuple[Query, str]:
    return (lambda s, d: method(catalog.load(s, d, name), windows.random_windows(s, n, 0, high))), counts_sql(catalog.edges_sql(name), windows.random_sql(n, 0, high), "u" if name == "g7" else "v")


def draws_sql(edges: str, wins: str, draws: int, seed: int, weights: str = "degree", side: str = "u") -> str:
    """CTEs up to val(window_id, draw, value)."""
    pick = lambda which: f"1 + ({hash_sql([f'draw * 2 + {which}', 'window_id', 'draw'], seed)} * 1009 + {hash_sql(['draw + 7919', 'window_id'], seed + 13 + which)}) % m"
    pool = "SELECT p.window_id, p.e, deg, row_number() OVER (PARTITION BY p.window_id ORDER BY p.e, p.o) AS k FROM p JOIN deg ON p.window_id = deg.window_id AND p.e = deg.e" if weights == "degree" else "SELECT window_id, e, deg, row_number() OVER (PARTITION BY window_id ORDER BY e) AS k FROM deg"
    scale = "CAST(m AS DOUBLE) * m / (2 * da * db)" if weights == "degree" else "CAST(m AS DOUBLE) * m / 2"
    end, other = ("u", "v") if side == "u" else ("v", "u")
    return f"""
WITH e AS ({edges}), w AS ({wins}),
p AS (SELECT DISTINCT w.window_id, e.{end} AS e, e.{other} AS o FROM e JOIN w ON e.t BETWEEN w.t_start AND w.t_end),
deg AS (SELECT window_id, e, count(*) AS deg FROM p GROUP BY 1, 2),
pool AS ({pool}),
m AS (SELECT window_id, count(*) AS m FROM pool GROUP BY 1),
asked AS (SELECT window_id, m, draw, {pick(0)} AS ka, {pick(1)} AS kb FROM m, (SELECT unnest(range(1, {draws + 1})) AS draw)),
drawn AS (SELECT asked.*, a.e AS a, a.deg AS da, b.e AS b, b.deg AS db FROM asked JOIN pool a ON asked.window_id = a.window_id AND ka = a.k JOIN pool b ON asked.window_id = b.window_id AND kb = b.k),
com AS (SELECT d.window_id, d.draw, count(*) AS c FROM drawn d JOIN p x ON d.window_id = x.window_id AND d.a = x.e JOIN p y ON d.window_id = y.window_id AND d.b = y.e AND x.o = y.o WHERE d.a <> d.b GROUP BY 1, 2),
val AS (SELECT d.window_id, d.draw, CASE WHEN a = b THEN 0.0 ELSE {scale} * (coalesce(c, 0) * (coalesce(c, 0) - 1) // 2) END AS value FROM drawn d LEFT JOIN com ON d.window_id = com.window_id AND d.draw = com.draw)"""


def pair_sampling_sql(edges: str, wins: str, draws: int, seed: int, **options) -> str:
    return f"""{draws_sql(edges, wins, draws, seed, **options)}
SELECT CAST(w.window_id AS BIGINT) AS window_id, CAST(w.t_start AS BIGINT) AS t_start, CAST(w.t_end AS BIGINT) AS t_end, coalesce(round(avg(value), 6), 0.0) AS estimate FROM w LEFT JOIN val ON w.window_id = val.window_id GROUP BY w.window_id, w.t_start, w.t_end"""


def sampled_one(spark, sf_dir):
    index = indexes.build_sampled(catalog.load(spark, sf_dir, "g4"), alpha=1.0, share1=0.25, seed=5)
    return indexes.query_sampled(index, windows.fixed(spark, DAYS)).select("window_id", "kept_points", F.col("estimate"))


def sampled_two(spark, sf_dir):
    index = indexes.build_sampled(catalog.load(spark, sf_dir, "g1"), alpha=0.0, share1=1.0, share2=0.5, seed=5)
    return indexes.query_sampled(index, windows.fixed(spark, DAYS)).select("window_id", "kept_pairs", F.col("estimate"))


def sampled_one_sql(name: str, share: float, seed: int) -> str:
    """Pairs of a group's wedges by number, one drawn place per stretch of 1 / share numbers; counts per window."""
    q = f"CAST({share} AS DOUBLE)"
    return f"""
WITH {arcs_sql(catalog.edges_sql(name), True)}, w AS ({windows.fixed_sql(DAYS)}),
ranked AS (SELECT *, row_number() OVER (PARTITION BY side, x, z ORDER BY y) - 1 AS rank FROM g),
sizes AS (SELECT side, x, z, count(*) AS size FROM g GROUP BY 1, 2, 3 HAVING count(*) >= 2),
stretches AS (SELECT side, x, z, size, unnest(range(CAST(floor((size * (size - 1) // 2 - 1) * {q}) AS BIGINT) + 1)) AS stretch FROM sizes),
numbers AS (SELECT side, x, z, size, CAST(floor((stretch + ({hash_sql(["x", "z", "stretch", "side"], seed)} + CAST(0.5 AS DOUBLE)) / {PRIME}) / {q}) AS BIGINT) AS number FROM stretches),
placed AS (SELECT side, x, z, number, CAST(floor((1 + sqrt(1 + 8 * CAST(number AS DOUBLE))) / 2) AS BIGINT) AS j FROM numbers WHERE number < size * (size - 1) // 2),
k AS (SELECT least(a.l, b.l) AS l, greatest(a.r, b.r) AS r FROM placed n JOIN ranked b ON n.side = b.side AND n.x = b.x AND n.z = b.z AND b.rank = n.j
 JOIN ranked a ON n.side = a.side AND n.x = a.x AND n.z = a.z AND a.rank = n.number - n.j * (n.j - 1) // 2)
SELECT w.window_id, CAST(count(k.l) AS BIGINT) AS kept_points, round(count(k.l) / {q}, 6) AS estimate FROM w LEFT JOIN k ON k.l >= w.t_start AND k.r <= w.t_end GROUP BY w.window_id"""


SAMPLED_ONE_SQL = sampled_one_sql("g4", 0.25, 5)

SAMPLED_TWO_SQL = f"""
WITH {arcs_sql(catalog.edges_sql("g1"))}, w AS ({windows.fixed_sql(DAYS)}),
kept AS (SELECT * FROM g WHERE {kept_sql(["x", "z", "y"], 0.5, 6)}),
pw AS (SELECT DISTINCT w.window_id, e.u, e.v FROM e JOIN w ON e.t BETWEEN w.t_start AND w.t_end),
ends AS (SELECT window_id, 0 AS side, u AS a, v AS b FROM pw UNION ALL SELECT window_id, 1, v, u FROM pw),
c AS (SELECT p.window_id, kept.side, x, z, count(*) AS c FROM kept JOIN ends p ON p.side = kept.side AND p.a = x AND p.b = y JOIN ends q ON q.window_id = p.window_id AND q.side = kept.side AND q.a = z AND q.b = y GROUP BY 1, 2, 3, 4),
s AS (SELECT window_id, sum(c * (c - 1) // 2) AS n FROM c GROUP BY 1)
SELECT w.window_id, CAST(coalesce(n, 0) AS BIGINT) AS kept_pairs, round(coalesce(n, 0) / 0.25, 6) AS estimate FROM w LEFT JOIN s ON w.window_id = s.window_id"""


def disjoint_sets(spark, sf_dir):
    """A set per region, numbered from 1: the remainders of its nations' keys by 7."""
    nation = catalog.table(spark, sf_dir, "nation")
    return nation.select((F.col("n_regionkey") + 1).cast("long").alias("set_id"), F.pmod(F.col("n_nationkey"), F.lit(7)).cast("long").alias("element")).distinct()


def disjointness(spark, sf_dir):
    g = hardness.reduce_sets(disjoint_sets(spark, sf_dir))
    out = None
    for a, b in ((1, 2), (1, 4), (2, 5)):
        counts = indexes.query_enumerated(indexes.build_enumerated(g), hardness.intersection_windows(spark, a, b))
        one = hardness.intersection_size(counts).select(F.lit(a).cast("long").alias("a"), F.lit(b).cast("long").alias("b"), "common")
        out = one if out is None else out.unionByName(one)
    return out


DISJOINT_SQL = "WITH s AS (SELECT DISTINCT n_regionkey + 1 AS i, n_nationkey % 7 AS e FROM nation), q AS (SELECT CAST(column0 AS BIGINT) AS a, CAST(column1 AS BIGINT) AS b FROM (VALUES (1, 2), (1, 4), (2, 5)) AS t(column0, column1)) SELECT q.a, q.b, CAST(count(y.e) AS BIGINT) AS common FROM q LEFT JOIN s x ON x.i = q.a LEFT JOIN s y ON y.i = q.b AND y.e = x.e GROUP BY 1, 2"


def supplier_sets(spark, sf_dir):
    """A set per nation, its suppliers; a supplier has one nation, so no two sets meet."""
    supplier = catalog.table(spark, sf_dir, "supplier")
    g = hardness.reduce_sets(supplier.select((F.col("s_nationkey") + 1).cast("long").alias("set_id"), F.col("s_suppkey").cast("long").alias("element")))
    index, out = indexes.build_enumerated(g), None
    for a, b in ((1, 2), (3, 9), (5, 25)):
        counts = indexes.query_enumerated(index, hardness.intersection_windows(spark, a, b))
        one = hardness.intersection_size(counts).select(F.lit(a).cast("long").alias("a"), F.lit(b).cast("long").alias("b"), "common")
        out = one if out is None else out.unionByName(one)
    return out


SUPPLIER_SETS_SQL = "WITH q AS (SELECT CAST(column0 AS BIGINT) AS a, CAST(column1 AS BIGINT) AS b FROM (VALUES (1, 2), (3, 9), (5, 25)) AS t(column0, column1)) SELECT q.a, q.b, CAST(count(y.s_suppkey) AS BIGINT) AS common FROM q LEFT JOIN supplier x ON x.s_nationkey + 1 = q.a LEFT JOIN supplier y ON y.s_nationkey + 1 = q.b AND y.s_suppkey = x.s_suppkey GROUP BY 1, 2"


def some_edges(where: str, name: str, spans: list) -> tuple[Query, str]:
    """Enumerated counts of the edges of a graph that a condition leaves; times counts the times of an edge's pair."""
    times = "SELECT u, v, t, count(*) OVER (PARTITION BY u, v) AS times FROM (SELECT DISTINCT u, v, t FROM {})"

    def run(spark, sf_dir):
        e = catalog.load(spark, sf_dir, name).edges
        if "times" in where:
            e = e.distinct().join(e.distinct().groupBy("u", "v").agg(F.count("*").alias("times")), ["u", "v"])
        return indexes.query_enumerated(indexes.build_enumerated(graph.TemporalBipartite(e.where(where).select("u", "v", "t"))), windows.fixed(spark, spans))

    return run, counts_sql(f"SELECT u, v, t FROM ({times.format(f'({catalog.edges_sql(name)})')}) WHERE {where}", windows.fixed_sql(spans))


def bcc_trend(spark, sf_dir):
    g, w = catalog.load(spark, sf_dir, "g4"), windows.calendar_years(spark, *YEARS)
    return measures.bcc(indexes.build_hybrid(g, alpha=0.5), g, w)


BCC_SQL = f"""
SELECT a.window_id, a.butterflies, b.three_paths, CASE WHEN b.three_paths > 0 THEN round(4 * a.butterflies / b.three_paths, 9) END AS bcc
FROM ({counts_sql(catalog.edges_sql("g4"), windows.calendar_sql(*YEARS), "u")}) a JOIN ({three_paths_sql(catalog.edges_sql("g4"), windows.calendar_sql(*YEARS))}) b ON a.window_id = b.window_id"""


def year_windows(measure):
    return lambda s, d: measure(catalog.load(s, d, "g4"), windows.calendar_years(s, *YEARS))


PROJECTED_YEARS = f"WITH e AS ({catalog.edges_sql('g4')}), w AS ({windows.calendar_sql(*YEARS)}), p AS (SELECT DISTINCT w.window_id, e.u, e.v FROM e JOIN w ON e.t BETWEEN w.t_start AND w.t_end)"


def ego_busiest(spark, sf_dir):
    return apps.busiest_window(spark, catalog.load(spark, sf_dir, "g2"), 7, 0, 2404 - 729, 730, 30)


EGO_WINDOWS = "SELECT i // 30 AS window_id, i AS t_start, i + 729 AS t_end FROM (SELECT unnest(range(0, 1676, 30)) AS i)"
EGO_SQL = f"""
SELECT t_start, butterflies FROM ({counts_sql(f"SELECT u, v, t FROM ({catalog.edges_sql('g2')}) WHERE v IN (SELECT v FROM ({catalog.edges_sql('g2')}) WHERE u = 7)", EGO_WINDOWS)}) ORDER BY butterflies DESC, t_start LIMIT 1"""


def community(spark, sf_dir):
    supplier, nation = catalog.table(spark, sf_dir, "supplier"), catalog.table(spark, sf_dir, "nation")
    labels = supplier.join(F.broadcast(nation), supplier["s_nationkey"] == nation["n_nationkey"]).select(F.col("s_suppkey").alias("v"), F.col("n_regionkey").cast("long").alias("label"))
    return apps.community_trend(catalog.load(spark, sf_dir, "g1"), labels, windows.calendar_years(spark, *YEARS), vertex=7)


COMMUNITY_SQL = f"""
WITH e0 AS ({catalog.edges_sql("g1")}), e AS (SELECT * FROM e0 WHERE v IN (SELECT v FROM e0 WHERE u = 7)), w AS ({windows.calendar_sql(*YEARS)}),
lab AS (SELECT s_suppkey AS v, CAST(n_regionkey AS BIGINT) AS label FROM supplier JOIN nation ON s_nationkey = n_nationkey),
p AS (SELECT DISTINCT label, w.window_id, e.u, e.v FROM e JOIN lab ON e.v = lab.v JOIN w ON e.t BETWEEN w.t_start AND w.t_end),
c AS (SELECT a.label, a.window_id, count(*) AS c FROM p a JOIN p b ON a.label = b.label AND a.window_id = b.window_id AND a.u = b.u AND a.v < b.v GROUP BY a.label, a.window_id, a.v, b.v),
s AS (SELECT label, window_id, sum(c * (c - 1) // 2) AS n FROM c GROUP BY 1, 2)
SELECT l.label, CAST(w.window_id AS BIGINT) AS window_id, CAST(coalesce(n, 0) AS BIGINT) AS butterflies FROM (SELECT DISTINCT label FROM lab) l CROSS JOIN w LEFT JOIN s ON s.label = l.label AND s.window_id = w.window_id"""


def co_purchase(spark, sf_dir):
    return apps.co_purchase(catalog.load(spark, sf_dir, "g5").swapped(), windows.fixed(spark, DAYS[:3]), 10)


CO_SQL = f"""
WITH e AS ({catalog.edges_sql("g5")}), w AS ({windows.fixed_sql(DAYS[:3])}),
p AS (SELECT DISTINCT w.window_id, e.v AS u, e.u AS v FROM e JOIN w ON e.t BETWEEN w.t_start AND w.t_end),
c AS (SELECT a.window_id, a.v AS v1, b.v AS v2, count(*) AS buyers FROM p a JOIN p b ON a.window_id = b.window_id AND a.u = b.u AND a.v < b.v GROUP BY 1, 2, 3)
SELECT * FROM (SELECT *, CAST(row_number() OVER (PARTITION BY window_id ORDER BY buyers DESC, v1, v2) AS INTEGER) AS rank FROM c) WHERE rank <= 10"""


def kernel(spark, sf_dir):
    w = windows.fixed(spark, DAYS)
    a, b = (apps.kernel_vector(baselines.recount_by_lists(catalog.load(spark, sf_dir, n), w)) for n in ("g2", "g4"))
    return apps.kernel_similarity(a, b)


KERNEL_SQL = f"""
WITH a AS ({counts_sql(catalog.edges_sql("g2"), windows.fixed_sql(DAYS))}), b AS ({counts_sql(catalog.edges_sql("g4"), windows.fixed_sql(DAYS), "u")})
SELECT round(sum(CAST(a.butterflies AS DOUBLE) * b.butterflies) / sqrt(sum(CAST(a.butterflies AS DOUBLE) * a.butterflies) * sum(CAST(b.butterflies AS DOUBLE) * b.butterflies)), 6) AS cosine FROM a JOIN b ON a.window_id = b.window_id"""


def instance_sql(edges: str, wins: str) -> str:
    return f"""
WITH e AS (SELECT DISTINCT * FROM ({edges})), w AS ({wins}),
k AS (SELECT w.window_id, e.u, e.v, count(*) AS k FROM e JOIN w ON e.t BETWEEN w.t_start AND w.t_end GROUP BY 1, 2, 3),
c AS (SELECT a.window_id, a.v AS x, b.v AS z, a.k * b.k AS c FROM k a JOIN k b ON a.window_id = b.window_id AND a.u = b.u AND a.v < b.v),
g AS (SELECT window_id, x, z, sum(c) AS n, sum(c * (c - 1) // 2) AS same FROM c GROUP BY 1, 2, 3),
s AS (SELECT window_id, sum(n * (n - 1) // 2 - same) AS b FROM g GROUP BY 1)
SELECT w.window_id, w.t_start, w.t_end, CAST(coalesce(b, 0) AS BIGINT) AS butterflies FROM w LEFT JOIN s ON w.window_id = s.window_id"""


def sampled_error(spark, sf_dir):
    """Settings of both shares, with size and mean relative error."""
    g, w = catalog.load(spark, sf_dir, "g1"), windows.fixed(spark, DAYS[:5])
    exact = baselines.recount(g, w)
    out = None
    for a, b in ((1.0, 1.0), (0.08, 1.0), (0.018, 1.0), (0.01, 0.5), (0.001, 0.05)):
        index = indexes.build_sampled(g, alpha=0.5, share1=a, share2=b, seed=3)
        error = measures.relative_error(indexes.query_sampled(index, w), exact).agg(F.round(F.avg("error"), 9).alias("mean_error"), F.max("error").alias("max_error"))
        size = measures.index_size(index).agg(F.sum("bytes").alias("bytes"))
        row = error.crossJoin(size).select(F.lit(a).alias("share1"), F.lit(b).alias("share2"), "bytes", "mean_error", "max_error")
        out = row if out is None else out.unionByName(row)
    return out


def memory_levels(spark, sf_dir):
    """Limits of 10 % to 100 % of the enumerated size: alpha chosen, estimated bytes."""
    g = catalog.load(spark, sf_dir, "g2")
    sizes = indexes.wedge_sizes(g)
    full = sum(r.butterflies for r in indexes.size_histogram(sizes).collect()) * indexes.POINT_BYTES
    rows = []
    for tenth in range(1, 11):
        c = indexes.cutoff_by_memory(sizes, full * tenth // 10)
        rows.append((tenth, full * tenth // 10, c.size, round(c.alpha, 6), c.est_bytes))
    return spark.createDataFrame(rows, "tenth int, limit_bytes long, size long, alpha double, est_bytes long")


def memory_levels_sql(name: str) -> str:
    """The walk over sizes as running sums: it stops before the first size whose estimate passes the limit and grows."""
    return f"""
WITH {arcs_sql(catalog.edges_sql(name))}, s AS (SELECT count(*) AS size FROM g GROUP BY side, x, z HAVING count(*) >= 2),
h AS (SELECT size, count(*) AS groups FROM s GROUP BY 1),
a AS (SELECT CAST(sum(size * (size - 1) // 2 * groups) AS BIGINT) AS total, CAST(sum(size * groups) AS BIGINT) AS wedges FROM h),
c AS (SELECT size, CAST(sum(size * (size - 1) // 2 * groups) OVER (ORDER BY size) AS BIGINT) AS done, CAST(sum(size * groups) OVER (ORDER BY size) AS BIGINT) AS moved FROM h),
f AS (SELECT size, done, done * {indexes.POINT_BYTES} + (wedges - moved) * {indexes.GROUPED_POINT_BYTES} AS est FROM c, a),
steps AS (SELECT size, done, est, lag(est, 1, (SELECT wedges * {indexes.GROUPED_POINT_BYTES} FROM a)) OVER (ORDER BY size) AS before FROM f),
t AS (SELECT tenth, total * {indexes.POINT_BYTES} * tenth // 10 AS lim FROM a, (SELECT unnest(range(1, 11)) AS tenth)),
b AS (SELECT tenth, lim, (SELECT coalesce(min(size), 1099511627776) FROM steps WHERE est > lim AND est > before) AS stop FROM t)
SELECT CAST(tenth AS INTEGER) AS tenth, CAST(lim AS BIGINT) AS limit_bytes, CAST(coalesce(max(steps.size), 0) AS BIGINT) AS size, round(coalesce(max(steps.done), 0) / any_value(a.total), 6) AS alpha, CAST(coalesce(arg_max(steps.est, steps.size), any_value(a.wedges) * {indexes.GROUPED_POINT_BYTES}) AS BIGINT) AS est_bytes
FROM b CROSS JOIN a LEFT JOIN steps ON steps.size < b.stop GROUP BY tenth, lim"""


def index_sizes_sql(name: str, alpha: float) -> str:
    """Points of both parts for pairs of one time: small groups up to the share of butterflies, large ones beyond it."""
    return f"""
WITH {arcs_sql(catalog.edges_sql(name), True)}, s AS (SELECT side, x, z, count(*) AS size FROM g GROUP BY 1, 2, 3 HAVING count(*) >= 2),
h AS (SELECT size, sum(size * (size - 1) // 2) AS b FROM s GROUP BY 1),
c AS (SELECT size, sum(b) OVER (ORDER BY size) AS done, (SELECT sum(b) FROM h) AS total FROM h),
cut AS (SELECT coalesce(max(size), 0) AS most FROM c WHERE done <= {alpha} * total),
k AS (SELECT g.*, size FROM g JOIN s ON g.side = s.side AND g.x = s.x AND g.z = s.z),
one AS (SELECT DISTINCT least(a.l, b.l), greatest(a.r, b.r) FROM k a JOIN k b ON a.side = b.side AND a.x = b.x AND a.z = b.z AND a.y < b.y WHERE a.size <= (SELECT most FROM cut)),
two AS (SELECT DISTINCT side, x, z, l, r FROM k WHERE size > (SELECT most FROM cut))
SELECT 'enumerated' AS part, count(*) AS points, count(*) * {indexes.POINT_BYTES} AS bytes FROM one UNION ALL SELECT 'grouped', count(*), count(*) * {indexes.GROUPED_POINT_BYTES} FROM two"""


def concentration_share_sql(name: str) -> str:
    return f"""
WITH {arcs_sql(catalog.edges_sql(name))}, s AS (SELECT count(*) AS size FROM g GROUP BY side, x, z), m AS (SELECT max(size) AS largest FROM s)
SELECT count(*) AS groups, round(sum(CASE WHEN size < 10 THEN 1 ELSE 0 END) / count(*), 6) AS share_small, round(sum(CASE WHEN size > largest / 2 THEN 1 ELSE 0 END) / count(*), 6) AS share_heavy,
round(sum(CASE WHEN size > largest / 2 THEN size * (size - 1) // 2 ELSE 0 END) / greatest(sum(size * (size - 1) // 2), 1), 6) AS butterflies_heavy FROM s, m"""


def keys(spark, sf_dir, name: str, key: str) -> DataFrame:
    return catalog.table(spark, sf_dir, name).select(key)


def generated(**options):
    """Random edges between customers and parts; exact ones, drawn pair by pair, between customers and nations."""

    def run(spark, sf_dir):
        exact, left = options.get("exact", False), keys(spark, sf_dir, "customer", "c_custkey")
        right = keys(spark, sf_dir, "nation", "n_nationkey") if exact else keys(spark, sf_dir, "part", "p_partkey")
        law = (left, right, options.get("gamma_u", 2.5), options.get("gamma_v", 2.5), 20 if exact else 300, left.count() if exact else 300)
        g = hardness.power_law(spark, *law, seed=3, exact=exact)
        return hardness.balance(g, *hardness.expected_degrees(spark, *law, seed=3))

    return run


def census_sql(name: str) -> str:
    return f"""
WITH e AS ({catalog.edges_sql(name)}), p AS (SELECT DISTINCT u, v FROM e),
du AS (SELECT u, count(*) AS du FROM p GROUP BY u), dv AS (SELECT v, count(*) AS dv FROM p GROUP BY v)
SELECT (SELECT count(*) FROM p) AS pairs, (SELECT round(avg(least(du, dv)), 6) FROM p JOIN du USING (u) JOIN dv USING (v)) AS mean_min_degree,
(SELECT count(*) FROM e) AS edges, (SELECT count(DISTINCT t) FROM e) AS times,
(SELECT count(*) FROM du) AS n_u, (SELECT max(du) FROM du) AS max_u, (SELECT round(1 + count(*) / sum(ln(du / 0.5)), 6) FROM du) AS exponent_u,
(SELECT count(*) FROM dv) AS n_v, (SELECT max(dv) FROM dv) AS max_v, (SELECT round(1 + count(*) / sum(ln(dv / 0.5)), 6) FROM dv) AS exponent_v"""


def concentration_sql(name: str) -> str:
    return f"""
WITH {arcs_sql(catalog.edges_sql(name))}, s AS (SELECT side, x, z, count(*) AS size FROM g GROUP BY 1, 2, 3), h AS (SELECT size, count(*) AS groups FROM s GROUP BY 1)
SELECT size, groups, size * groups AS wedges, (size * (size - 1) // 2) * groups AS butterflies, round(groups / (SELECT sum(groups) FROM h), 6) AS share, size < 10 AS is_small FROM h"""


def counters_sql(name: str) -> str:
    return f"""
WITH {arcs_sql(catalog.edges_sql(name))}, s AS (SELECT side, x, z, count(*) AS size FROM g GROUP BY 1, 2, 3)
SELECT (SELECT CAST(sum(least(du.d, dv.d)) AS BIGINT) FROM q JOIN du ON q.u = du.u JOIN dv ON q.v = dv.v) AS candidates, CAST(sum(size) AS BIGINT) AS wedges, count(*) AS groups, CAST(sum(CASE WHEN size >= 2 THEN 1 ELSE 0 END) AS BIGINT) AS groups_many, CAST(sum(size * (size - 1) // 2) AS BIGINT) AS butterflies, max(size) AS largest FROM s"""


def signed_weight(spark, sf_dir):
    """Check sum: all signed points of the enumerated index, by sign."""
    points = indexes.build_enumerated(catalog.load(spark, sf_dir, "g9")).points
    return points.agg(F.sum("w").alias("total"))


def registry() -> dict[str, tuple[Query, str | None]]:
    day_edges = catalog.edges_sql
    q: dict[str, tuple[Query, str | None]] = {}
    for n in ("g1", "g2", "g3", "g4", "g5", "g6"):
        q[f"window_recount_{n}"] = with_windows(n, baselines.recount, end="u" if n in ("g4", "g5") else "v")
    for n in ("g2", "g4", "g9"):
        q[f"enumerated_{n}"] = with_windows(n, enumerated(), end="u" if n == "g4" else "v")
    for layout in ("grid", "dyadic", "sweep"):
        q[f"enumerated_{layout}_g2"] = with_windows("g2", enumerated(layout))
    q["enumerated_lateral_g4"] = with_windows("g4", lambda g, w: sqlapi.lateral_count(w.sparkSession, indexes.build_enumerated(g), w), end="u")
    for n in ("g1", "g2"):
        q[f"grouped_{n}"] = with_windows(n, grouped())
    q["grouped_packed_g4"] = with_windows("g4", grouped("packed"), end="u")
    for n in ("g1", "g2"):
        for tag, alpha in (("a0", 0.0), ("a01", 0.01), ("a10", 0.1), ("a50", 0.5), ("a100", 1.0)):
            q[f"hybrid_{n}_{tag}"] = with_windows(n, hybrid(alpha=alpha))
    q["hybrid_g7_a50"] = with_windows("g7", hybrid(alpha=0.5))
    q["hybrid_below_rule_g4"] = with_windows("g4", hybrid(alpha=0.5, rule="below"), end="u")
    q["hybrid_exact_ties_g2"] = with_windows("g2", hybrid(alpha=0.5, ties="exact"))
    q["hybrid_auto_alpha_g2"] = with_windows("g2", hybrid(limit_bytes=8_000_000))
    q["hybrid_parallel_g1"] = with_windows("g1", lambda g, w: indexes.query_hybrid(indexes.build_hybrid(g, alpha=0.5), w, parallelism=16))
    q["recount_parallel_g2"] = with_windows("g2", lambda g, w: baselines.recount(g, w, parallelism=16))
    q["recount_relabelled_g5"] = with_windows("g5", lambda g, w: baselines.recount(g, w, relabel=True), end="u")
    q["four_way_g5"] = with_windows("g5", baselines.four_way, end="u")
    q["skew_recount_g8"] = with_windows("g8", baselines.recount, k=2, sides="both")
    q["skew_recount_g8_k3"] = with_windows("g8", baselines.recount, k=3, sides="both")
    q["skew_recount_g8_one_side"] = with_windows("g8", baselines.recount, k=3, sides="v")
    q["skew_hybrid_g8_k3"] = with_windows("g8", hybrid(alpha=0.5), k=3, sides="both")
    q["random_windows_hybrid_g2"] = random_batch("g2", lambda g, w: indexes.query_hybrid(indexes.build_hybrid(g, alpha=1.0), w, layout="dyadic"))
    q["random_windows_5000_g2"] = plain(lambda s, d: indexes.query_hybrid(indexes.build_hybrid(catalog.load(s, d, "g2"), alpha=1.0), windows.random_windows(s, 5000, 0, 2404), layout="dyadic"))
    q["random_windows_recount_g4"] = random_batch("g4", baselines.recount)
    q["instances_g9"] = ((lambda s, d: duration.instance_counts(catalog.load(s, d, "g9"), windows.fixed(s, HOURS))), instance_sql(day_edges("g9"), windows.fixed_sql(HOURS)))
    q["sampled_one_g4"] = plain(sampled_one, SAMPLED_ONE_SQL)
    q["sampled_two_g1"] = plain(sampled_two, SAMPLED_TWO_SQL)
    q["sampled_error_g1"] = plain(sampled_error)
    q["memory_levels_g2"] = plain(memory_levels, memory_levels_sql("g2"))
    q["error_bounds_g1"] = plain(experiments.bounds)
    q["thread_counts_g6"] = plain(experiments.thread_counts, f"WITH c AS ({counts_sql(day_edges('g6'), windows.fixed_sql(HOURS))}) SELECT CAST(n AS BIGINT) AS threads, CAST(b AS BIGINT) AS hybrid, CAST(b AS BIGINT) AS recount FROM (SELECT sum(butterflies) AS b FROM c), (SELECT unnest([1, 8]) AS n)")
    q["power_law_counts"] = plain(experiments.generated_counts)
    q["grouped_dyadic_g2"] = with_windows("g2", grouped("dyadic"))
    q["grouped_sweep_g1"] = with_windows("g1", grouped("sweep"))
    q["hybrid_dyadic_g4_a10"] = with_windows("g4", lambda g, w: indexes.query_hybrid(indexes.build_hybrid(g, alpha=0.1), w, "dyadic", "dyadic"), end="u")
    for n in ("g1", "g4", "g6"):
        q[f"random_windows_hybrid_{n}_a10"] = random_batch(n, lambda g, w: indexes.query_hybrid(indexes.build_hybrid(g, alpha=0.1), w, "sweep", "sweep"), high=719 if n == "g6" else 2404)
    for n in ("g3", "g5", "g6"):
        q[f"hybrid_auto_alpha_{n}"] = with_windows(n, hybrid(limit_bytes=1_500_000), end="u" if n == "g5" else "v")
    q["skew_recount_g8_k11"] = with_windows("g8", baselines.recount, DAYS[:2], k=11, sides="both")
    q["skew_hybrid_g8_k11_one_side"] = with_windows("g8", hybrid(alpha=0.1), DAYS[:2], k=11, sides="v")
    for n, deltas in (("g2", MANY_DELTAS), ("g5", DELTAS), ("g6", [10, 40, 100])):
        q[f"duration_index_{n}"] = ((lambda s, d, n=n, deltas=deltas: duration.query(duration.build(catalog.load(s, d, n), max(deltas), 0.5), delta_table(s, deltas))), deltas_sql(day_edges(n), deltas))
    for n in ("g2", "g4", "g6", "g7"):
        q[f"concentration_share_{n}"] = ((lambda s, d, n=n: measures.concentration_share(indexes.wedge_sizes(catalog.load(s, d, n)))), concentration_share_sql(n))
    q["data_summary"] = plain(lambda s, d: experiments.summaries(s, d, ["g1", "g2", "g3", "g4", "g5", "g6", "g9"]), " UNION ALL ".join(f"SELECT '{n}' AS graph, pairs, edges, n_u, n_v, mean_min_degree FROM ({census_sql(n)})" for n in ("g1", "g2", "g3", "g4", "g5", "g6", "g9")))
    q["ego_busiest_window_g4"] = plain(lambda s, d: apps.busiest_window(s, catalog.load(s, d, "g4"), 3, 0, 2404 - 729, 730, 30), EGO_SQL.replace(day_edges("g2"), day_edges("g4")).replace("WHERE u = 7", "WHERE u = 3"))
    q["disjointness_suppliers"] = plain(supplier_sets, SUPPLIER_SETS_SQL)
    q["uniform_times"] = plain(lambda s, d: hardness.uniformity(hardness.power_law_arrow(s, keys(s, d, "customer", "c_custkey"), keys(s, d, "part", "p_partkey"), 2.5, 2.5, 300, 300, seed=3)))
    q["pair_sampling_g2"] = ((lambda s, d: baselines.pair_sampling(catalog.load(s, d, "g2"), windows.fixed(s, DAYS[:2]), 2000)), pair_sampling_sql(day_edges("g2"), windows.fixed_sql(DAYS[:2]), 2000, 1))
    q["pair_sampling_even_g2"] = plain(lambda s, d: baselines.pair_sampling(catalog.load(s, d, "g2"), windows.fixed(s, DAYS[:2]), 2000, weights="even"), pair_sampling_sql(day_edges("g2"), windows.fixed_sql(DAYS[:2]), 2000, 1, weights="even"))
    q["pair_sampling_right_g2"] = plain(lambda s, d: baselines.pair_sampling(catalog.load(s, d, "g2"), windows.fixed(s, DAYS[:2]), 2000, side="v"), pair_sampling_sql(day_edges("g2"), windows.fixed_sql(DAYS[:2]), 2000, 1, side="v"))
    q["pair_sampling_draws_g1"] = plain(lambda s, d: baselines.draws_to_error(baselines.sampled_pairs(catalog.load(s, d, "g1"), windows.fixed(s, DAYS[:2]), 2000), baselines.recount(catalog.load(s, d, "g1"), windows.fixed(s, DAYS[:2]))), f"{draws_sql(day_edges('g1'), windows.fixed_sql(DAYS[:2]), 2000, 1)}, ex AS ({counts_sql(day_edges('g1'), windows.fixed_sql(DAYS[:2]))}), run AS (SELECT window_id, draw, avg(value) OVER (PARTITION BY window_id ORDER BY draw) AS mean FROM val) SELECT CAST(run.window_id AS BIGINT) AS window_id, CAST(min(CASE WHEN abs(mean - butterflies) / butterflies <= 0.1 THEN draw END) AS BIGINT) AS draws FROM run JOIN ex ON run.window_id = ex.window_id GROUP BY 1")
    q["duration_spans_g2"] = ((lambda s, d: duration.query_spans(duration.build_spans(catalog.load(s, d, "g2")), delta_table(s, DELTAS))), deltas_sql(day_edges("g2"), DELTAS))
    q["duration_grouped_g2"] = ((lambda s, d: duration.grouped(catalog.load(s, d, "g2"), delta_table(s, DELTAS))), deltas_sql(day_edges("g2"), DELTAS))
    q["duration_hybrid_g2_many"] = ((lambda s, d: duration.hybrid(catalog.load(s, d, "g2"), delta_table(s, MANY_DELTAS))), deltas_sql(day_edges("g2"), MANY_DELTAS))
    q["duration_direct_g2"] = ((lambda s, d: baselines.duration_count(catalog.load(s, d, "g2"), 365)), deltas_sql(day_edges("g2"), [365]))
    q["duration_grouped_g6"] = ((lambda s, d: duration.grouped(catalog.load(s, d, "g6"), delta_table(s, [10, 40]))), deltas_sql(day_edges("g6"), [10, 40]))
    q["duration_list_g2"] = ((lambda s, d: baselines.duration_list(catalog.load(s, d, "g2"), 365, 100)), f"WITH {timed_sql(day_edges('g2'))} SELECT x, z, y1, y2, l, r FROM f WHERE r - l <= 365 ORDER BY l, r, x, z, y1, y2 LIMIT 100")
    q["duration_list_all_g2"] = ((lambda s, d: baselines.duration_list(catalog.load(s, d, "g2"), 365)), f"WITH {timed_sql(day_edges('g2'))} SELECT x, z, y1, y2, l, r FROM f WHERE r - l <= 365")
    q["bcc_trend_g4"] = plain(bcc_trend, BCC_SQL)
    q["three_paths_g2"] = ((lambda s, d: measures.three_paths(catalog.load(s, d, "g2"), windows.fixed(s, DAYS))), three_paths_sql(day_edges("g2"), windows.fixed_sql(DAYS)))
    q["publications_g4"] = (year_windows(measures.mean_degree), PROJECTED_YEARS + " SELECT CAST(window_id AS BIGINT) AS window_id, round(count(*) / count(DISTINCT u), 6) AS mean_degree FROM p GROUP BY 1")
    q["collaborators_g4"] = (year_windows(measures.mean_partners), PROJECTED_YEARS + ", m AS (SELECT DISTINCT a.window_id, a.u AS a, b.u AS b FROM p a JOIN p b ON a.window_id = b.window_id AND a.v = b.v AND a.u <> b.u), n AS (SELECT window_id, count(*) AS n FROM m GROUP BY 1), act AS (SELECT window_id, count(DISTINCT u) AS k FROM p GROUP BY 1) SELECT CAST(act.window_id AS BIGINT) AS window_id, round(coalesce(n, 0) / k, 6) AS mean_partners FROM act LEFT JOIN n ON act.window_id = n.window_id")
    q["trend_g4"] = ((lambda s, d: apps.trend(s, indexes.build_hybrid(catalog.load(s, d, "g4"), alpha=0.5), 0, 1800, 365, 90)), counts_sql(day_edges("g4"), "SELECT i // 90 AS window_id, i AS t_start, i + 364 AS t_end FROM (SELECT unnest(range(0, 1801, 90)) AS i)", "u"))
    q["ego_busiest_window_g2"] = plain(ego_busiest, EGO_SQL)
    q["community_trend_g1"] = plain(community, COMMUNITY_SQL)
    q["co_purchase_topk_g5"] = plain(co_purchase, CO_SQL)
    q["kernel_similarity_g2_g4"] = plain(kernel, KERNEL_SQL)
    q["disjointness_nations"] = plain(disjointness, DISJOINT_SQL)
    q["toy_windows"] = some_edges("u <= 60", "g1", DAYS)
    q["duplicate_edges_windows"] = some_edges("times > 1", "g9", HOURS)
    q["concentration_g2"] = ((lambda s, d: concentration(group_sizes(priority_wedges(catalog.load(s, d, "g2"))))), concentration_sql("g2"))
    q["concentration_g7"] = plain(lambda s, d: concentration(group_sizes(priority_wedges(catalog.load(s, d, "g7")))), concentration_sql("g7"))
    q["work_counters_g4"] = ((lambda s, d: measures.work_counters(catalog.load(s, d, "g4"))), counters_sql("g4"))
    for n in ("g1", "g4", "g8"):
        q[f"census_{n}"] = ((lambda s, d, n=n: graph.census(catalog.load(s, d, n))), census_sql(n))
    q["wedge_rows_g4"] = ((lambda s, d: priority_wedges(catalog.load(s, d, "g4"), with_times=False)), f"WITH {arcs_sql(day_edges('g4'))} SELECT CAST(side AS INTEGER) AS side, x, z, y FROM g")
    q["one_sided_wedges_g5"] = ((lambda s, d: one_sided_wedges(catalog.load(s, d, "g5"), "u").select("x", "z", "y")), f"WITH p AS (SELECT DISTINCT u, v FROM ({day_edges('g5')})) SELECT a.u AS x, b.u AS z, a.v AS y FROM p a JOIN p b ON a.v = b.v AND a.u < b.u")
    q["group_points_g4"] = ((lambda s, d: group_points(with_stairs(priority_wedges(catalog.load(s, d, "g4"))))), f"WITH {arcs_sql(day_edges('g4'), True)} SELECT CAST(side AS INTEGER) AS side, x, z, l, r, CAST(count(*) AS BIGINT) AS w FROM g GROUP BY 1, 2, 3, 4, 5")
    q["active_intervals_g4"] = ((lambda s, d: active_interval(catalog.load(s, d, "g4").edges, "u")), f"SELECT u, min(t) AS l, max(t) AS r FROM ({day_edges('g4')}) GROUP BY u")
    q["signed_points_g9"] = ((signed_weight), f"SELECT CAST(sum(butterflies) AS BIGINT) AS total FROM ({counts_sql(day_edges('g9'), 'SELECT 0 AS window_id, -100000 AS t_start, 100000 AS t_end')})")
    q["rectangles_g4"] = (
        (lambda s, d: dominance.rectangles(indexes.build_enumerated(catalog.load(s, d, "g4")).points, s.createDataFrame([(0, 0, 300, 200, 900), (1, 100, 700, 100, 800)], "box_id long, l1 long, l2 long, r1 long, r2 long"))),
        f"WITH {arcs_sql(day_edges('g4'), True)}, b AS (SELECT least(a.l, c.l) AS l, greatest(a.r, c.r) AS r FROM g a JOIN g c ON a.side = c.side AND a.x = c.x AND a.z = c.z AND a.y < c.y), box AS (SELECT CAST(c0 AS BIGINT) AS box_id, CAST(c1 AS BIGINT) AS l1, CAST(c2 AS BIGINT) AS l2, CAST(c3 AS BIGINT) AS r1, CAST(c4 AS BIGINT) AS r2 FROM (VALUES (0, 0, 300, 200, 900), (1, 100, 700, 100, 800)) AS t(c0, c1, c2, c3, c4)) SELECT box.*, CAST(count(b.l) AS BIGINT) AS cnt FROM box LEFT JOIN b ON b.l BETWEEN box.l1 AND box.l2 AND b.r BETWEEN box.r1 AND box.r2 GROUP BY ALL",
    )
    q["compact_time_g5"] = ((lambda s, d: graph.compact_time(catalog.load(s, d, "g5"))[0].edges.groupBy("t").agg(F.count("*").alias("edges"))), f"SELECT rank AS t, count(*) AS edges FROM (SELECT dense_rank() OVER (ORDER BY t) AS rank FROM ({day_edges('g5')})) GROUP BY 1")
    q["grain_month_g4"] = ((lambda s, d: baselines.recount(graph.grain(catalog.load(s, d, "g4"), 30), windows.fixed(s, [(0, 10), (5, 40)]))), counts_sql(f"SELECT u, v, t // 30 AS t FROM ({day_edges('g4')})", windows.fixed_sql([(0, 10), (5, 40)]), "u"))
    q["projection_g5"] = ((lambda s, d: graph.project(catalog.load(s, d, "g5"), windows.fixed(s, DAYS[:3]))), f"SELECT DISTINCT w.window_id, u, v FROM ({day_edges('g5')}) e JOIN ({windows.fixed_sql(DAYS[:3])}) w ON t BETWEEN t_start AND t_end")
    q["unique_degrees_g4"] = ((lambda s, d: graph.unique_degrees(catalog.load(s, d, "g4").pairs)), f"SELECT CAST(0 AS INTEGER) AS side, u AS id, count(DISTINCT v) AS deg FROM ({day_edges('g4')}) GROUP BY u UNION ALL SELECT 1, v, count(DISTINCT u) FROM ({day_edges('g4')}) GROUP BY v")
    q["butterfly_rows_g5"] = (
        (lambda s, d: indexes.butterflies(with_stairs(priority_wedges(catalog.load(s, d, "g5")))).select("side", "x", "z", "y", "w", F.col("stairs")[0]["l"].alias("l"), F.col("stairs")[0]["r"].alias("r"))),
        f"WITH {arcs_sql(day_edges('g5'), True)} SELECT CAST(a.side AS INTEGER) AS side, a.x, a.z, a.y, c.y AS w, least(a.l, c.l) AS l, greatest(a.r, c.r) AS r FROM g a JOIN g c ON a.side = c.side AND a.x = c.x AND a.z = c.z AND a.y < c.y",
    )
    q["duration_per_window_g2"] = ((lambda s, d: baselines.duration_per_window(catalog.load(s, d, "g2"), windows.fixed(s, DAYS))), f"WITH {timed_sql(day_edges('g2'))}, w AS ({windows.fixed_sql(DAYS)}) SELECT w.window_id, w.t_start, w.t_end, CAST(count(f.l) AS BIGINT) AS butterflies FROM w LEFT JOIN f ON f.l >= w.t_start AND f.r <= w.t_end GROUP BY ALL")
    q["index_sizes_g4"] = plain(lambda s, d: measures.index_size(indexes.build_hybrid(catalog.load(s, d, "g4"), alpha=0.5)), index_sizes_sql("g4", 0.5))
    q["exact_against_estimate_g4"] = plain(lambda s, d: measures.relative_error(indexes.query_sampled(indexes.build_sampled(catalog.load(s, d, "g4"), 1.0, 0.1), windows.fixed(s, DAYS)), baselines.recount(catalog.load(s, d, "g4"), windows.fixed(s, DAYS))), f"SELECT a.window_id, CASE WHEN b.butterflies > 0 THEN round(abs(a.estimate - b.butterflies) / b.butterflies, 9) END AS error FROM ({sampled_one_sql('g4', 0.1, 1)}) a JOIN ({counts_sql(day_edges('g4'), windows.fixed_sql(DAYS), 'u')}) b ON a.window_id = b.window_id")
    q["power_law_double"] = plain(generated())
    q["power_law_single"] = plain(generated(gamma_v=0.0))
    q["power_law_exact"] = plain(generated(exact=True))
    return q

