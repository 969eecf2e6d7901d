"""Operators around the methods: scans, sinks, joins, aggregates, windows, sets, functions, streams.

Each entry is a query on the graph tables and its DuckDB text (None where the engine's own hash,
randomness or stream has no twin).
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.hashing import hash_sql, kept, kept_sql, portable_hash
from ..operators import baselines, dominance, indexes
from ..operators.wedges import GROUP, group_points, priority_wedges, with_stairs
from ..sources import catalog, store, windows
from ..sources.scratch import scratch
from ..streaming import edges as stream
from ..streaming import maintenance
from . import sqlapi
from .graph_queries import arcs_sql, counts_sql, three_paths_sql, timed_sql

Query = Callable[[SparkSession, str], DataFrame]
G4, G1 = catalog.edges_sql("g4"), catalog.edges_sql("g1")
W2 = [(0, 729), (1000, 1300)]
W2_SQL = windows.fixed_sql(W2)


def g4(spark, sf_dir) -> DataFrame:
    return catalog.load(spark, sf_dir, "g4").edges


def g1(spark, sf_dir) -> DataFrame:
    return catalog.load(spark, sf_dir, "g1").edges


def t(name: str):
    return lambda spark, sf_dir: catalog.table(spark, sf_dir, name)


line, orders, customer, supplier, part, nation, region, events, documents, pages = map(t, "lineitem orders customer supplier part nation region events documents pages".split())


def per_day(edges: DataFrame) -> DataFrame:
    return edges.groupBy("t").agg(F.count("*").alias("edges"))


PER_DAY = "SELECT t, count(*) AS edges FROM ({}) GROUP BY t"


def through_file(fmt: str) -> Query:
    def run(spark, sf_dir):
        path = scratch(spark, fmt)
        g4(spark, sf_dir).write.format(fmt).save(path)
        return per_day(store.read_edges(spark, path, fmt, low=100, high=400).edges)

    return run


def through_text(spark, sf_dir):
    path = scratch(spark, "text")
    g4(spark, sf_dir).select(F.concat_ws(" ", "u", "v", F.lit(1), "t").alias("value")).write.text(path)
    return per_day(store.read_blank_separated(spark, path).edges)


def through_index(spark, sf_dir):
    path = scratch(spark, "index")
    store.save(indexes.build_hybrid(catalog.load(spark, sf_dir, "g4"), alpha=0.5), path)
    return indexes.query_hybrid(store.load(spark, path), windows.fixed(spark, W2))


def pruned_points(spark, sf_dir):
    path = scratch(spark, "index")
    store.save(indexes.build_enumerated(catalog.load(spark, sf_dir, "g4")), path)
    return store.points_from(store.load(spark, path), 1500).agg(F.sum("w").cast("long").alias("butterflies"))


def catalog_views(spark, sf_dir):
    sqlapi.register_graph(catalog.load(spark, sf_dir, "g4"), windows.fixed(spark, W2), "rel")
    return sqlapi.recount_sql(spark, "rel")


def events_stream(spark, sf_dir):
    return stream.event_edges(spark, f"{sf_dir}/events.parquet")


def streamed(build: Callable[[DataFrame], DataFrame], name: str, shape: Callable[[DataFrame], DataFrame], mode: str = "append") -> Query:
    return lambda spark, sf_dir: shape(stream.run_to_table(build(events_stream(spark, sf_dir)), name, mode))


BATCHES = 3


def events_in_batches(spark, sf_dir):
    """The events as a stream of several batches: files by remainder of the event id, so times go back and forth."""
    path = scratch(spark, "events")
    for k in range(BATCHES):
        events(spark, sf_dir).where(F.col("event_id") % BATCHES == k).coalesce(1).write.parquet(f"{path}/part={k}.parquet")
    schema = events(spark, sf_dir).schema
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(path)
    return rows.select(F.col("user_id").alias("u"), F.get_json_object("props", "$.k").cast("long").alias("v"), F.col("ts").cast("timestamp").alias("ts"), "event_type")


def stream_counts(spark, sf_dir):
    """Counts per window over all batches of a stream: each batch adds the points that it makes with all edges before it."""
    kept = stream.Maintained(spark)
    kept.follow(events_in_batches(spark, sf_dir))
    return maintenance.counts(kept.state, windows.fixed(spark, windows.FIXED_HOURS))


def butterfly_increments(spark, sf_dir):
    """batch, butterflies of the whole time line after it, by what each batch adds."""
    out: list[DataFrame] = []
    kept = stream.Maintained(spark, lambda state, added, k: out.append(added.agg(F.lit(k).cast("long").alias("batch"), F.coalesce(F.sum("w"), F.lit(0)).alias("added"))))
    kept.follow(events_in_batches(spark, sf_dir))
    every = out[0]
    for more in out[1:]:
        every = every.unionByName(more)
    return every.select("batch", F.sum("added").over(Window.orderBy("batch")).alias("butterflies"))  # a row per batch


def late_edges(spark, sf_dir):
    """A first batch of earlier events, then the rest, a tenth of whose earlier events comes late: what the watermark lets through, and the late ones as a delta of their own."""
    edges = events(spark, sf_dir).select("event_id", F.col("user_id").alias("u"), F.get_json_object("props", "$.k").cast("long").alias("v"), F.col("ts").cast("timestamp").alias("ts"))
    first = (F.col("ts") < F.lit("2024-01-20").cast("timestamp")) & (F.col("event_id") % 10 != 0)
    state, _ = maintenance.append(maintenance.empty(spark), stream.hours(edges.where(first)), "first")
    on_time, late = stream.in_order_and_late(edges.where(~first), edges.where(first).agg(F.max("ts").alias("ts")))
    state, _ = maintenance.append(state, stream.hours(on_time), "on-time")
    before = maintenance.counts(state, windows.fixed(spark, windows.FIXED_HOURS)).select("window_id", F.col("butterflies").alias("without_late"))
    state, _ = maintenance.append(state, stream.hours(late), "late")
    return maintenance.counts(state, windows.fixed(spark, windows.FIXED_HOURS)).join(before, "window_id").select("window_id", "without_late", "butterflies")


def late_points(spark, sf_dir):
    """The first part of the time line taken in, then the rest as a batch: its points come from its edges and the old points alone."""
    g = catalog.load(spark, sf_dir, "g4").edges
    state, _ = maintenance.append(maintenance.empty(spark), g.where("t <= 1200"), "old")
    state, _ = maintenance.append(state, g.where("t > 1200"), "new")
    return maintenance.counts(state, windows.fixed(spark, W2))


def packed_kernel(spark, sf_dir):
    points = group_points(with_stairs(priority_wedges(catalog.load(spark, sf_dir, "g4"))))
    w = windows.fixed(spark, W2)
    count = sqlapi.packed_udf(w)
    arrays = points.groupBy(*GROUP).agg(F.collect_list(F.struct("l", "r", "w")).alias("p"))
    counts = arrays.select(count(F.transform("p", lambda x: x["l"]), F.transform("p", lambda x: x["r"]), F.transform("p", lambda x: x["w"])).alias("c"))
    each = counts.select(F.posexplode("c").alias("window_id", "n"))
    return each.groupBy(F.col("window_id").cast("long").alias("window_id")).agg(F.sum(F.shiftright(F.col("n") * (F.col("n") - 1), 1)).alias("butterflies"))


def window_functions(spark, sf_dir):
    sqlapi.register_graph(catalog.load(spark, sf_dir, "g4"), windows.fixed(spark, W2), "rel")
    sqlapi.register_functions(spark, "rel")
    return spark.sql("SELECT bfly_count(0, 729) AS butterflies, bfly_three_paths(0, 729) AS three_paths")


def range_files(spark, sf_dir):
    """rows, files, overlaps: edges dealt by ranges of time; no file's times reach into another's."""
    dealt = g4(spark, sf_dir).repartitionByRange(4, "t").sortWithinPartitions("t").select("t", F.spark_partition_id().alias("p"))
    spans = dealt.groupBy("p").agg(F.min("t").alias("lo"), F.max("t").alias("hi"), F.count("*").alias("n"))
    before = F.lag("hi").over(Window.orderBy("lo"))  # a row per file
    marked = spans.withColumn("overlap", F.coalesce((F.col("lo") <= before).cast("int"), F.lit(0)))
    return marked.agg(F.sum("n").alias("rows"), F.count("*").alias("files"), F.sum("overlap").alias("overlaps"))


def near_estimates(spark, sf_dir):
    """Distinct right vertices exactly, and whether both sketches come within a twentieth of it."""
    row = g4(spark, sf_dir).agg(F.countDistinct("v").alias("vs"), F.approx_count_distinct("v", 0.02).alias("a"), F.hll_sketch_estimate(F.hll_sketch_agg("v", F.lit(12))).alias("h"))
    near = lambda c: F.abs(F.col(c) - F.col("vs")) * 20 <= F.col("vs")
    return row.select("vs", near("a").alias("sketch_near"), near("h").alias("hll_near"))


def sql_function(spark, sf_dir):
    sqlapi.register_functions(spark)
    g4(spark, sf_dir).createOrReplaceTempView("rel_edges_f")
    return spark.sql("SELECT u, choose2(count(DISTINCT v)) AS pairs FROM rel_edges_f GROUP BY u")


def tree_nodes(spark, sf_dir):
    sqlapi.register_functions(spark)
    g4(spark, sf_dir).select("t").distinct().createOrReplaceTempView("bfly_days")
    return spark.sql("SELECT t, level, node FROM bfly_days, LATERAL bfly_nodes(CAST(t AS INT), 12)")


def stair_union(spark, sf_dir):
    """x, z, l, r: the minimal intervals in which a group has a wedge at all, by a grouped pandas function."""
    points = with_stairs(priority_wedges(catalog.load(spark, sf_dir, "g4"))).select(*GROUP, F.inline("stairs"))
    return sqlapi.union_of_stairs(points, GROUP).select("x", "z", "l", "r")


def bucketed_join(spark, sf_dir):
    import uuid

    name = f"bfly_edges_{uuid.uuid4().hex[:12]}"
    e = g4(spark, sf_dir)
    path = scratch(spark, "bucketed")
    e.write.mode("overwrite").option("path", path).bucketBy(8, "v").sortBy("v").saveAsTable(name)
    a = spark.table(name)
    return a.alias("a").join(a.alias("b"), "v").where("a.u < b.u").groupBy("v").agg(F.count("*").alias("wedges"))


def by_u():
    return Window.partitionBy("u").orderBy("t", "v")


def registry() -> dict[str, tuple[Query, str | None]]:
    q: dict[str, tuple[Query, str | None]] = {}
    counts4 = f"WITH e AS ({G4}), w AS ({W2_SQL}), p AS (SELECT DISTINCT w.window_id, u, v FROM e JOIN w ON t BETWEEN t_start AND t_end), c AS (SELECT a.window_id, count(*) AS c FROM p a JOIN p b ON a.window_id = b.window_id AND a.v = b.v AND a.u < b.u GROUP BY a.window_id, a.u, b.u) SELECT w.window_id, w.t_start, w.t_end, CAST(coalesce(sum(c * (c - 1) // 2), 0) AS BIGINT) AS butterflies FROM w LEFT JOIN c ON w.window_id = c.window_id GROUP BY ALL"
    # scans, sources, sinks
    q["rel_s1_scan_filter"] = (lambda s, d: per_day(g4(s, d).where(F.col("t").between(100, 200)))), PER_DAY.format(f"SELECT * FROM ({G4}) WHERE t BETWEEN 100 AND 200")
    for fmt in ("csv", "json", "orc", "parquet"):
        q[f"rel_s2_{fmt}_edges"] = through_file(fmt), PER_DAY.format(f"SELECT * FROM ({G4}) WHERE t BETWEEN 100 AND 400")
    q["rel_s2_blank_separated"] = through_text, PER_DAY.format(G4)
    q["rel_s4_index_round_trip"] = through_index, counts4
    q["rel_s4_bucketed_join"] = bucketed_join, f"SELECT a.v, count(*) AS wedges FROM ({G4}) a JOIN ({G4}) b ON a.v = b.v AND a.u < b.u GROUP BY a.v"
    q["rel_s5_pruned_index"] = pruned_points, counts4.replace(W2_SQL, "SELECT 0 AS window_id, 1500 AS t_start, 100000 AS t_end").replace("SELECT w.window_id, w.t_start, w.t_end, ", "SELECT ").replace("GROUP BY ALL", "")
    q["rel_s6_catalog_views"] = catalog_views, counts4
    q["rel_s7_ranges"] = (lambda s, d: line(s, d).select(F.col("l_linenumber").cast("long").alias("id"), F.explode(F.sequence(F.lit(0), F.col("l_linenumber").cast("int"))).alias("k")).groupBy("id", "k").agg(F.count("*").alias("n"))), "SELECT id, CAST(k AS INTEGER) AS k, count(*) AS n FROM (SELECT CAST(l_linenumber AS BIGINT) AS id, unnest(range(l_linenumber + 1)) AS k FROM lineitem) GROUP BY 1, 2"
    q["rel_s8_literal"] = (lambda s, d: g4(s, d).join(F.broadcast(catalog.literal(s, catalog.TOY).edges.select("u").distinct()), "u", "left_semi")), f"SELECT u, v, t FROM ({G4}) WHERE u IN (SELECT a FROM (VALUES " + ", ".join(map(str, catalog.TOY)) + ") AS x(a, b, c))"
    q["rel_s10_text_to_edges"] = (lambda s, d: documents(s, d).select("doc_id", F.explode(F.array_distinct(F.split(F.regexp_replace(F.lower("text"), r"[^a-z]+", " "), " "))).alias("word")).where("word <> ''").groupBy("doc_id").agg(F.count("*").alias("words"))), "SELECT doc_id, count(DISTINCT w) AS words FROM (SELECT doc_id, unnest(string_split(regexp_replace(lower(text), '[^a-z]+', ' ', 'g'), ' ')) AS w FROM documents) WHERE w <> '' GROUP BY doc_id"
    q["rel_s11_url_parts"] = (lambda s, d: pages(s, d).select("page_id", F.regexp_extract("url", r"^https?://([^/]+)", 1).alias("host"), F.regexp_extract("url", r"^https?://[^/]+(/.*)$", 1).alias("path"))), r"SELECT page_id, regexp_extract(url, '^https?://([^/]+)', 1) AS host, regexp_extract(url, '^https?://[^/]+(/.*)$', 1) AS path FROM pages"
    # predicates
    q["rel_p2_dominance"] = (lambda s, d: dominance.scan(g4(s, d).select(F.col("t").alias("l"), (F.col("t") + F.col("u") % 30).alias("r"), F.lit(1).cast("long").alias("w")), windows.fixed(s, W2))), f"SELECT w.window_id, CAST(count(*) AS BIGINT) AS cnt FROM ({G4}) e JOIN ({W2_SQL}) w ON e.t >= w.t_start AND e.t + e.u % 30 <= w.t_end GROUP BY 1"
    q["rel_p3_priority"] = (lambda s, d: g4(s, d).groupBy("u").agg(F.countDistinct("v").alias("deg")).where(F.struct(-F.col("deg"), F.col("u")) < F.struct(F.lit(-60).cast("long"), F.lit(50).cast("long")))), f"SELECT * FROM (SELECT u, count(DISTINCT v) AS deg FROM ({G4}) GROUP BY u) WHERE deg > 60 OR (deg = 60 AND u < 50)"
    q["rel_p4_strict_times"] = (lambda s, d: baselines.timed_butterflies(catalog.load(s, d, "g2"), 400).agg(F.count("*").alias("n"))), f"WITH {timed_sql(catalog.edges_sql('g2'))} SELECT count(*) AS n FROM f WHERE r - l <= 400"
    q["rel_p5_bernoulli"] = (lambda s, d: g4(s, d).where(kept([F.col("u"), F.col("v")], 0.3, 9)).select("u", "v")), f"SELECT u, v FROM ({G4}) WHERE {kept_sql(['u', 'v'], 0.3, 9)}"
    q["rel_p6_in_list"] = (lambda s, d: per_day(g4(s, d).where(F.col("u").isin(1, 2, 3)))), PER_DAY.format(f"SELECT * FROM ({G4}) WHERE u IN (1, 2, 3)")
    q["rel_p7_nulls_and_case"] = (lambda s, d: events(s, d).select("event_id", F.coalesce(F.get_json_object("props", "$.missing").cast("long"), F.lit(-1).cast("long")).alias("x"), F.when(F.col("value") > 50, "high").otherwise("low").alias("band"))), "SELECT event_id, CAST(coalesce(CAST(json_extract_string(props, '$.missing') AS BIGINT), -1) AS BIGINT) AS x, CASE WHEN value > 50 THEN 'high' ELSE 'low' END AS band FROM events"
    # joins
    q["rel_j1_middle_self_join"] = (lambda s, d: g4(s, d).alias("a").join(g4(s, d).alias("b"), "v").groupBy("v").agg(F.count("*").alias("n"))), f"SELECT a.v, count(*) AS n FROM ({G4}) a JOIN ({G4}) b ON a.v = b.v GROUP BY a.v"
    q["rel_j2_equi_with_residual"] = (lambda s, d: g4(s, d).alias("a").join(g4(s, d).alias("b"), (F.col("a.v") == F.col("b.v")) & (F.col("a.u") < F.col("b.u"))).select(F.col("a.v").alias("v"), F.col("a.u").alias("x"), F.col("b.u").alias("z"))), f"SELECT a.v, a.u AS x, b.u AS z FROM ({G4}) a JOIN ({G4}) b ON a.v = b.v AND a.u < b.u"
    q["rel_j5_interval_join"] = (lambda s, d: g1(s, d).join(F.broadcast(windows.fixed(s, W2)), F.col("t").between(F.col("t_start"), F.col("t_end"))).groupBy("window_id").agg(F.count("*").alias("edges"))), f"SELECT w.window_id, count(*) AS edges FROM ({G1}) e JOIN ({W2_SQL}) w ON e.t BETWEEN w.t_start AND w.t_end GROUP BY 1"

    def cell_join(s, d, width=90):
        w = windows.random_windows(s, 40, 0, 2404)
        cells = w.withColumn("cell", F.explode(F.sequence(F.floor(F.col("t_start") / width), F.floor(F.col("t_end") / width))))
        e = g4(s, d).withColumn("cell", F.floor(F.col("t") / width))
        return e.join(cells, "cell").where(F.col("t").between(F.col("t_start"), F.col("t_end"))).groupBy("window_id").agg(F.count("*").alias("edges"))

    q["rel_j5_cell_interval_join"] = cell_join, f"SELECT w.window_id, count(*) AS edges FROM ({G4}) e JOIN ({windows.random_sql(40, 0, 2404)}) w ON e.t BETWEEN w.t_start AND w.t_end GROUP BY 1"

    def as_of(s, d):
        e = g4(s, d).groupBy("u", "t").agg(F.count("*").alias("n"))
        asks = s.range(0, 2400, 300).select(F.col("id").alias("t"))
        both = e.select("u", "t", "n", F.lit(0).alias("ask")).unionByName(e.select("u").distinct().crossJoin(asks).select("u", "t", F.lit(None).cast("long").alias("n"), F.lit(1).alias("ask")))
        w = Window.partitionBy("u").orderBy("t", "ask").rowsBetween(Window.unboundedPreceding, 0)
        return both.withColumn("last_n", F.last("n", ignorenulls=True).over(w)).where("ask = 1").select("u", "t", "last_n")

    q["rel_j7_as_of"] = as_of, f"WITH e AS (SELECT u, t, count(*) AS n FROM ({G4}) GROUP BY 1, 2), q AS (SELECT u, t FROM (SELECT DISTINCT u FROM e), (SELECT unnest(range(0, 2400, 300)) AS t)) SELECT q.u, q.t, e.n AS last_n FROM q ASOF LEFT JOIN e ON q.u = e.u AND q.t >= e.t"
    q["rel_j8_semi"] = (lambda s, d: customer(s, d).join(orders(s, d).where("o_totalprice > 300000"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")), "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_totalprice > 300000)"
    q["rel_j8_anti"] = (lambda s, d: customer(s, d).join(orders(s, d), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")), "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)"
    q["rel_j9_left_outer_zero"] = (lambda s, d: dominance.all_windows(windows.fixed(s, [(0, 10), (90000, 90001)]), dominance.scan(g4(s, d).select(F.col("t").alias("l"), F.col("t").alias("r"), F.lit(1).cast("long").alias("w")), windows.fixed(s, [(0, 10), (90000, 90001)])))), f"SELECT w.window_id, w.t_start, w.t_end, CAST(count(e.t) AS BIGINT) AS cnt FROM ({windows.fixed_sql([(0, 10), (90000, 90001)])}) w LEFT JOIN ({G4}) e ON e.t BETWEEN w.t_start AND w.t_end GROUP BY ALL"
    q["rel_j10_full_outer"] = (lambda s, d: per_day(g4(s, d).where("t < 50")).join(g4(s, d).where("t > 20 and t < 80").groupBy("t").agg(F.countDistinct("u").alias("us")), "t", "full_outer")), f"SELECT coalesce(a.t, b.t) AS t, edges, us FROM (SELECT t, count(*) AS edges FROM ({G4}) WHERE t < 50 GROUP BY t) a FULL JOIN (SELECT t, count(DISTINCT u) AS us FROM ({G4}) WHERE t > 20 AND t < 80 GROUP BY t) b ON a.t = b.t"
    q["rel_j11_bounded_cross"] = (lambda s, d: region(s, d).select("r_name").crossJoin(nation(s, d).select("n_name"))), "SELECT r_name, n_name FROM region CROSS JOIN nation"
    q["rel_j13_star"] = (lambda s, d: line(s, d).join(orders(s, d), F.col("l_orderkey") == F.col("o_orderkey")).join(customer(s, d), F.col("o_custkey") == F.col("c_custkey")).join(nation(s, d), F.col("c_nationkey") == F.col("n_nationkey")).join(region(s, d), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name").agg(F.count("*").alias("lines"))), "SELECT r_name, count(*) AS lines FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1"

    def salted(s, d, salts=8):
        e = g1(s, d)
        a = e.select("v", F.col("u").alias("x"), F.pmod(F.hash("u"), F.lit(salts)).alias("salt"))
        b = e.select("v", F.col("u").alias("z"), F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("salt"))
        return a.join(b, ["v", "salt"]).where("x < z").groupBy("v", "salt").agg(F.count("*").alias("n")).groupBy("v").agg(F.sum("n").alias("n"))

    q["rel_j14_salted"] = salted, f"SELECT a.v, CAST(count(*) AS BIGINT) AS n FROM ({G1}) a JOIN ({G1}) b ON a.v = b.v AND a.u < b.u GROUP BY a.v"
    # aggregates
    q["rel_a1_by_key"] = (lambda s, d: g4(s, d).groupBy("u").agg(F.count("*").alias("n"), F.sum("t").alias("s"), F.min("t").alias("lo"), F.max("t").alias("hi"), F.round(F.avg("t"), 6).alias("mean"))), f"SELECT u, count(*) AS n, CAST(sum(t) AS BIGINT) AS s, min(t) AS lo, max(t) AS hi, round(avg(t), 6) AS mean FROM ({G4}) GROUP BY u"
    q["rel_a3_distinct"] = (lambda s, d: g4(s, d).agg(F.countDistinct("u").alias("us"), F.countDistinct("v").alias("vs"))), f"SELECT count(DISTINCT u) AS us, count(DISTINCT v) AS vs FROM ({G4})"
    q["rel_a3_approximate"] = near_estimates, f"SELECT count(DISTINCT v) AS vs, true AS sketch_near, true AS hll_near FROM ({G4})"
    q["rel_a4_compaction"] = (lambda s, d: g4(s, d).groupBy("t").agg(F.sum(F.when(F.col("u") % 2 == 0, 1).otherwise(-1)).alias("w")).where("w <> 0")), f"SELECT * FROM (SELECT t, CAST(sum(CASE WHEN u % 2 = 0 THEN 1 ELSE -1 END) AS BIGINT) AS w FROM ({G4}) GROUP BY t) WHERE w <> 0"
    q["rel_a5_filtered"] = (lambda s, d: line(s, d).groupBy("l_returnflag").agg(F.count(F.when(F.col("l_discount") > 0.05, 1)).alias("high"), F.count("*").alias("n"))), "SELECT l_returnflag, count(*) FILTER (WHERE l_discount > 0.05) AS high, count(*) AS n FROM lineitem GROUP BY 1"
    q["rel_a6_rollup"] = (lambda s, d: customer(s, d).join(nation(s, d), F.col("c_nationkey") == F.col("n_nationkey")).rollup("n_regionkey", "n_nationkey").agg(F.count("*").alias("n"))), "SELECT n_regionkey, n_nationkey, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY ROLLUP (n_regionkey, n_nationkey)"
    q["rel_a6_cube"] = (lambda s, d: orders(s, d).cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))), "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)"
    q["rel_a6_grouping_sets"] = (lambda s, d: orders(s, d).groupingSets([["o_orderstatus"], ["o_orderpriority"]], "o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))), "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority))"
    q["rel_a7_pivot"] = (lambda s, d: orders(s, d).groupBy(F.year("o_orderdate").alias("y")).pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count("o_orderkey"))), "SELECT year(o_orderdate) AS y, nullif(count(*) FILTER (WHERE o_orderstatus = 'F'), 0) AS F, nullif(count(*) FILTER (WHERE o_orderstatus = 'O'), 0) AS O, nullif(count(*) FILTER (WHERE o_orderstatus = 'P'), 0) AS P FROM orders GROUP BY 1"
    q["rel_a8_sorted_lists"] = (lambda s, d: g4(s, d).groupBy("v").agg(F.array_join(F.transform(F.array_sort(F.collect_list("u")), lambda x: x.cast("string")), ",").alias("us"))), f"SELECT v, string_agg(CAST(u AS VARCHAR), ',' ORDER BY u) AS us FROM ({G4}) GROUP BY v"
    q["rel_a10_histogram"] = (lambda s, d: g4(s, d).groupBy("v").agg(F.count("*").alias("k")).groupBy(F.width_bucket("k", F.lit(0.0), F.lit(8.0), F.lit(4)).alias("bucket")).agg(F.count("*").alias("n"))), f"SELECT CAST(least(k // 2, 4) + 1 AS BIGINT) AS bucket, count(*) AS n FROM (SELECT v, count(*) AS k FROM ({G4}) GROUP BY v) GROUP BY 1"
    q["rel_a10_percentiles"] = (lambda s, d: g4(s, d).agg(F.percentile("t", 0.5).alias("median"), F.percentile("t", 0.9).alias("p90"))), f"SELECT quantile_cont(t, 0.5) AS median, quantile_cont(t, 0.9) AS p90 FROM ({G4})"
    q["rel_a11_arg_max"] = (lambda s, d: per_day(g4(s, d)).agg(F.max_by("t", F.struct("edges", "t")).alias("t"))), f"SELECT t FROM ({PER_DAY.format(G4)}) ORDER BY edges DESC, t DESC LIMIT 1"
    q["rel_a12_spread"] = (lambda s, d: per_day(g4(s, d)).agg(F.round(F.avg("edges"), 6).alias("mean"), F.round(F.stddev_samp("edges"), 6).alias("sd"))), f"SELECT round(avg(edges), 6) AS mean, round(stddev_samp(edges), 6) AS sd FROM ({PER_DAY.format(G4)})"
    q["rel_a13_bitmaps"] = (lambda s, d: g4(s, d).where("u < 60").groupBy("v").agg(F.bit_or(F.expr("shiftleft(1L, cast(u as int))")).alias("m")).select("v", F.bit_count("m").alias("n"))), f"SELECT v, CAST(count(DISTINCT u) AS INTEGER) AS n FROM ({G4}) WHERE u < 60 GROUP BY v"
    words = lambda e: e.groupBy("v", F.shiftright("u", 6).alias("word")).agg(F.bit_or(F.expr("shiftleft(1L, cast(u & 63 as int))")).alias("m"))
    q["rel_a13_bitmaps_all"] = (lambda s, d: words(g4(s, d)).groupBy("v").agg(F.sum(F.bit_count("m")).cast("int").alias("n"))), f"SELECT v, CAST(count(DISTINCT u) AS INTEGER) AS n FROM ({G4}) GROUP BY v"
    # window functions
    over = "OVER (PARTITION BY u ORDER BY t, v)"
    q["rel_n1_lead_lag"] = (lambda s, d: g4(s, d).select("u", "v", "t", F.lead("t").over(by_u()).alias("next_t"), F.lag("t").over(by_u()).alias("last_t"))), f"SELECT u, v, t, lead(t) {over} AS next_t, lag(t) {over} AS last_t FROM ({G4})"
    q["rel_n2_running_min"] = (lambda s, d: g4(s, d).select("u", "v", "t", F.min("v").over(Window.partitionBy("u").orderBy(F.desc("t"), "v").rowsBetween(Window.unboundedPreceding, -1)).alias("least"))), f"SELECT u, v, t, min(v) OVER (PARTITION BY u ORDER BY t DESC, v ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS least FROM ({G4})"
    q["rel_n3_running_sum"] = (lambda s, d: g4(s, d).groupBy("v").agg(F.count("*").alias("size")).groupBy("size").agg(F.count("*").alias("n")).select("size", F.sum("n").over(Window.orderBy("size")).alias("upto"))), f"SELECT size, CAST(sum(n) OVER (ORDER BY size) AS BIGINT) AS upto FROM (SELECT size, count(*) AS n FROM (SELECT v, count(*) AS size FROM ({G4}) GROUP BY v) GROUP BY size)"
    q["rel_n5_ranks"] = (lambda s, d: g4(s, d).groupBy("u").agg(F.count("*").alias("n")).select("u", F.rank().over(Window.orderBy(F.desc("n"))).alias("r"), F.dense_rank().over(Window.orderBy(F.desc("n"))).alias("dr"), F.ntile(4).over(Window.orderBy(F.desc("n"), "u")).alias("q"))), f"SELECT u, CAST(rank() OVER (ORDER BY n DESC) AS INTEGER) AS r, CAST(dense_rank() OVER (ORDER BY n DESC) AS INTEGER) AS dr, CAST(ntile(4) OVER (ORDER BY n DESC, u) AS INTEGER) AS q FROM (SELECT u, count(*) AS n FROM ({G4}) GROUP BY u)"
    q["rel_n8_range_frame"] = (lambda s, d: g4(s, d).select("u", "v", "t", F.count("*").over(Window.partitionBy("u").orderBy("t").rangeBetween(-30, 0)).alias("recent"))), f"SELECT u, v, t, count(*) OVER (PARTITION BY u ORDER BY t RANGE BETWEEN 30 PRECEDING AND CURRENT ROW) AS recent FROM ({G4})"
    q["rel_n9_nth"] = (lambda s, d: g4(s, d).select("u", "v", F.first("t").over(by_u()).alias("first_t"), F.nth_value("t", 2).over(by_u()).alias("second_t"))), f"SELECT u, v, first_value(t) {over} AS first_t, nth_value(t, 2) {over} AS second_t FROM ({G4})"
    # order and limits
    degs = f"SELECT u, count(*) AS n FROM ({G4}) GROUP BY u"
    q["rel_t2_top_k"] = (lambda s, d: g4(s, d).groupBy("u").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "u").limit(10)), f"{degs} ORDER BY n DESC, u LIMIT 10"
    q["rel_t3_top_k_per_vertex"] = (lambda s, d: g4(s, d).withColumn("k", F.row_number().over(Window.partitionBy("u").orderBy(F.desc("t"), "v"))).where("k <= 3").select("u", "v", "t")), f"SELECT u, v, t FROM (SELECT *, row_number() OVER (PARTITION BY u ORDER BY t DESC, v) AS k FROM ({G4})) WHERE k <= 3"
    q["rel_t4_range_partitioned"] = range_files, f"SELECT count(*) AS rows, CAST(4 AS BIGINT) AS files, CAST(0 AS BIGINT) AS overlaps FROM ({G4})"
    q["rel_t5_offset"] = (lambda s, d: g4(s, d).groupBy("u").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "u").offset(5).limit(5)), f"{degs} ORDER BY n DESC, u LIMIT 5 OFFSET 5"
    # set operations
    early, late = f"SELECT DISTINCT u, v FROM ({G1}) WHERE t < 1200", f"SELECT DISTINCT u, v FROM ({G1}) WHERE t > 900"

    def halves(s, d):
        return g1(s, d).where("t < 1200").select("u", "v").distinct(), g1(s, d).where("t > 900").select("u", "v").distinct()

    for name, f, word in (("u1_union_all", lambda a, b: a.unionAll(b), "UNION ALL"), ("u2_union", lambda a, b: a.union(b).distinct(), "UNION"), ("u3_intersect", lambda a, b: a.intersect(b), "INTERSECT"), ("u4_except", lambda a, b: a.subtract(b), "EXCEPT"), ("u4_except_all", lambda a, b: a.exceptAll(b), "EXCEPT ALL"), ("u5_intersect_all", lambda a, b: a.intersectAll(b), "INTERSECT ALL")):
        q[f"rel_{name}"] = (lambda s, d, f=f: f(*halves(s, d))), f"{early} {word} {late}"
    q["rel_u6_union_by_name"] = (lambda s, d: halves(s, d)[0].unionByName(halves(s, d)[1].select("v", "u"))), f"{early} UNION ALL {late}"
    # functions
    q["rel_f1_math"] = (lambda s, d: g4(s, d).select("u", "v", F.least("u", "v").alias("a"), F.pmod(-F.col("u"), F.lit(7)).alias("b"), F.round(F.sqrt("v"), 6).alias("c"), F.round(F.log(F.col("v") + 1), 6).alias("e"))), f"SELECT u, v, least(u, v) AS a, ((-u) % 7 + 7) % 7 AS b, round(sqrt(v), 6) AS c, round(ln(v + 1), 6) AS e FROM ({G4})"
    q["rel_f3_dates"] = (lambda s, d: orders(s, d).select("o_orderkey", F.year("o_orderdate").alias("y"), F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM").alias("m"), F.datediff(F.add_months("o_orderdate", 1), F.col("o_orderdate")).alias("k"))), "SELECT o_orderkey, CAST(year(o_orderdate) AS INTEGER) AS y, strftime(date_trunc('month', o_orderdate), '%Y-%m') AS m, CAST(date_diff('day', CAST(o_orderdate AS DATE), CAST(o_orderdate + INTERVAL 1 MONTH AS DATE)) AS INTEGER) AS k FROM orders"
    q["rel_f4_strings"] = (lambda s, d: part(s, d).select("p_partkey", F.lower("p_brand").alias("a"), F.concat_ws("/", "p_brand", "p_type").alias("b"), F.substring("p_name", 1, 4).alias("c"), F.length("p_name").alias("n"))), "SELECT p_partkey, lower(p_brand) AS a, concat_ws('/', p_brand, p_type) AS b, substr(p_name, 1, 4) AS c, CAST(length(p_name) AS INTEGER) AS n FROM part"
    q["rel_f5_arrays"] = (lambda s, d: g4(s, d).groupBy("v").agg(F.array_sort(F.collect_set("u")).alias("us")).select("v", F.size("us").alias("n"), F.array_max("us").alias("top"), F.aggregate("us", F.lit(0).cast("long"), lambda a, x: a + x).alias("total"), F.size(F.array_intersect("us", F.sequence(F.lit(1).cast("long"), F.lit(50).cast("long")))).alias("low"))), f"SELECT v, CAST(count(DISTINCT u) AS INTEGER) AS n, max(u) AS top, CAST(sum(DISTINCT u) AS BIGINT) AS total, CAST(count(DISTINCT u) FILTER (WHERE u BETWEEN 1 AND 50) AS INTEGER) AS low FROM ({G4}) GROUP BY v"
    q["rel_f6_maps"] = (lambda s, d: g4(s, d).groupBy("u").agg(F.map_from_entries(F.array_sort(F.collect_set(F.struct((F.col("t") % 5).alias("k"), F.lit(1).alias("x"))))).alias("m")).select("u", F.size(F.map_keys("m")).alias("kinds"))), f"SELECT u, CAST(count(DISTINCT t % 5) AS INTEGER) AS kinds FROM ({G4}) GROUP BY u"
    q["rel_f7_json"] = (lambda s, d: events(s, d).select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"), F.from_json("props", "k long")["k"].alias("k2"))), "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k2 FROM events"
    q["rel_f8_structs"] = (lambda s, d: g4(s, d).where("u = 1").select(F.inline(F.array(F.struct(F.col("u").alias("a"), F.col("v").alias("b")), F.struct(F.col("v").alias("a"), F.col("u").alias("b")))))), f"SELECT u AS a, v AS b FROM ({G4}) WHERE u = 1 UNION ALL SELECT v, u FROM ({G4}) WHERE u = 1"
    q["rel_f8_structs_all"] = (lambda s, d: g4(s, d).select(F.inline(F.array(F.struct(F.col("u").alias("a"), F.col("v").alias("b")), F.struct(F.col("v").alias("a"), F.col("u").alias("b")))))), f"SELECT u AS a, v AS b FROM ({G4}) UNION ALL SELECT v, u FROM ({G4})"
    q["rel_f9_hash"] = (lambda s, d: g4(s, d).select("u", "v", portable_hash([F.col("u"), F.col("v")], 9).alias("h"))), f"SELECT u, v, CAST({hash_sql(['u', 'v'], 9)} AS BIGINT) AS h FROM ({G4})"
    q["rel_f10_bits"] = (lambda s, d: g4(s, d).select("u", "v", F.shiftright("v", 2).alias("a"), F.bit_count("v").alias("b"))), f"SELECT u, v, v >> 2 AS a, CAST(bit_count(v) AS INTEGER) AS b FROM ({G4})"
    # streams
    q["rel_x1_deduplicated"] = streamed(stream.deduplicated, "bfly_x1", lambda t: t.select("u", "v")), "SELECT user_id AS u, CAST(json_extract_string(props, '$.k') AS BIGINT) AS v FROM events"
    day = lambda t: t.select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "edges")
    q["rel_x2_tumbling"] = streamed(stream.tumbling, "bfly_x2a", day, "complete"), "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, count(*) AS edges FROM events GROUP BY 1"
    q["rel_x2_sliding"] = streamed(stream.sliding, "bfly_x2b", day, "complete"), "SELECT strftime(date_trunc('day', ts) - to_days(CAST(k AS INTEGER)), '%Y-%m-%d') AS day, count(*) AS edges FROM events, (SELECT unnest(range(7)) AS k) GROUP BY 1"
    stamp = lambda c: F.date_format(c, "yyyy-MM-dd HH:mm:ss")
    q["rel_x2_sessions"] = (
        streamed(stream.sessions, "bfly_x2c", lambda t: t.select("u", stamp("session_window.start").alias("start"), stamp("session_window.end").alias("end"), "edges"), "complete"),
        "WITH s AS (SELECT user_id AS u, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 1 HOUR THEN 0 ELSE 1 END AS fresh FROM events), k AS (SELECT u, ts, sum(fresh) OVER (PARTITION BY u ORDER BY ts) AS k FROM s) SELECT u, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, strftime(max(ts) + INTERVAL 1 HOUR, '%Y-%m-%d %H:%M:%S') AS \"end\", count(*) AS edges FROM k GROUP BY u, k",
    )
    G6 = catalog.edges_sql("g6")
    q["rel_x3_foreach_batch"] = stream_counts, counts_sql(G6, windows.fixed_sql(windows.FIXED_HOURS))
    prefix = lambda k: counts_sql(G6 + f" WHERE event_id % {BATCHES} <= {k}", "SELECT 0 AS window_id, -100000 AS t_start, 100000 AS t_end")
    q["rel_x4_butterfly_increments"] = butterfly_increments, " UNION ALL ".join(f"SELECT CAST({k} AS BIGINT) AS batch, butterflies FROM ({prefix(k)})" for k in range(BATCHES))
    cut = "TIMESTAMP '2024-01-20'"
    on_time = f" WHERE (ts < {cut} AND event_id % 10 <> 0) OR ts >= (SELECT max(ts) - INTERVAL 1 DAY FROM events WHERE ts < {cut} AND event_id % 10 <> 0)"
    q["rel_x5_late_edges"] = late_edges, f"SELECT a.window_id, b.butterflies AS without_late, a.butterflies FROM ({counts_sql(G6, windows.fixed_sql(windows.FIXED_HOURS))}) a JOIN ({counts_sql(G6 + on_time, windows.fixed_sql(windows.FIXED_HOURS))}) b ON a.window_id = b.window_id"
    q["rel_x4_stateful"] = streamed(stream.partner_increments, "bfly_x4", lambda t: t.groupBy("v").agg(F.sum("partners").alias("wedges"))), "SELECT v, CAST(n * (n - 1) // 2 AS BIGINT) AS wedges FROM (SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS v, count(DISTINCT user_id) AS n FROM events GROUP BY 1)"
    q["rel_x6_stream_static"] = (lambda s, d: stream.run_to_table(stream.labelled(events_stream(s, d), customer(s, d).select(F.col("c_custkey").alias("u"), "c_mktsegment")), "bfly_x6").groupBy("c_mktsegment").agg(F.count("*").alias("edges"))), "SELECT c_mktsegment, count(*) AS edges FROM events JOIN customer ON user_id = c_custkey GROUP BY 1"
    q["rel_x6_stream_stream"] = (lambda s, d: stream.run_to_table(stream.paired(events_stream(s, d), events_stream(s, d)), "bfly_x6b").agg(F.count("*").alias("pairs"))), "SELECT count(*) AS pairs FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR"
    q["rel_x7_delta_points"] = late_points, counts4
    # functions of our own
    q["rel_v1_sql_function"] = sql_function, f"SELECT u, CAST(n * (n - 1) // 2 AS BIGINT) AS pairs FROM (SELECT u, count(DISTINCT v) AS n FROM ({G4}) GROUP BY u)"
    q["rel_v2_packed_kernel"] = packed_kernel, f"SELECT window_id, butterflies FROM ({counts4})"
    q["rel_v3_sweep_kernel"] = (lambda s, d: dominance.count(indexes.build_enumerated(catalog.load(s, d, "g4")).points, windows.fixed(s, W2), "sweep").withColumnRenamed("cnt", "butterflies")), counts4
    q["rel_v1_window_functions"] = window_functions, f"SELECT a.butterflies, b.three_paths FROM ({counts_sql(G4, windows.fixed_sql(W2[:1]), 'u')}) a JOIN ({three_paths_sql(G4, windows.fixed_sql(W2[:1]))}) b ON a.window_id = b.window_id"
    q["rel_v4_grouped_pandas"] = stair_union, f"WITH {arcs_sql(G4, True)}, d AS (SELECT DISTINCT side, x, z, l, r FROM g), m AS (SELECT *, min(r) OVER (PARTITION BY side, x, z ORDER BY l DESC RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS least, min(r) OVER (PARTITION BY side, x, z ORDER BY l DESC RANGE BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS later FROM d) SELECT x, z, l, r FROM m WHERE r = least AND (later IS NULL OR r < later)"
    q["rel_v6_tree_nodes"] = tree_nodes, f"SELECT t, CAST(level AS INTEGER) AS level, (t + (1 << level) - 1) >> level AS node FROM (SELECT DISTINCT t FROM ({G4})), (SELECT unnest(range(13)) AS level) WHERE ((t + (1 << level) - 1) >> level) % 2 = 1 AND (t + (1 << level) - 1) >> level < 1 << (12 - level) OR (level = 12 AND t = 0)"
    return q
