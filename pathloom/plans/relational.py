"""Queries that build graphs, choose seeds and post-process answers: one for each kind of relational operator, with its SQL."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.automaton import compile_expr
from ..functions.expr import parse_pattern
from ..functions.vertices import number, vid
from ..operators import reach
from ..sources import triples
from ..sources.graph import dictionary, given_graph
from ..sources.store import new_path
from ..streaming import incremental, windows
from . import evaluate, oracles

E, V = oracles.EDGES, oracles.v
QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    """Register a function under its name."""

    def keep(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return keep


def _t(spark: SparkSession, d: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{d}/{name}.parquet")


# Scans, sources, sinks.


@query(f"SELECT src, dst FROM ({E['ordered_by']})")
def scan_edges(spark, d):
    return given_graph(spark, d).edges("ordered_by")


@query(f"SELECT 'within' AS label, src, dst FROM ({E['within']}) UNION ALL SELECT 'adjacent', src, dst FROM ({E['adjacent']})")
def scan_label_pruned(spark, d):
    path = new_path(spark, "graph")
    triples.save_by_label(given_graph(spark, d), path, ["adjacent", "within", "resident_of"])
    return triples.load_by_label(spark, path).triples(["adjacent", "within"])


@query(f"SELECT 'within' AS label, src, dst FROM ({E['within']})")
def src_triples_roundtrip(spark, d):
    path = new_path(spark, "triples")
    rows = given_graph(spark, d).triples(["within"]).select(F.col("src").cast("string").alias("subject"), F.col("label").alias("predicate"), F.col("dst").cast("string").alias("object"))
    rows.write.option("sep", "\t").csv(path)
    back = triples.read_delimited(spark, path)
    return back.select(F.col("predicate").alias("label"), F.col("subject").cast("long").alias("src"), F.col("object").cast("long").alias("dst"))


@query("SELECT 'n' || n_nationkey AS subject, 'in' AS predicate, 'r' || n_regionkey AS object FROM nation")
def src_ntriples(spark, d):
    path = new_path(spark, "ntriples")
    lines = _t(spark, d, "nation").select(F.format_string("<n%d> <in> <r%d> .", "n_nationkey", "n_regionkey").alias("value")).unionAll(spark.createDataFrame([("# a comment",)], "value string"))
    lines.write.text(path)
    return triples.read_ntriples(spark, path)


@query("SELECT count(*) AS n_edges, count(DISTINCT src) AS n_src FROM (SELECT n_nationkey AS src FROM nation)")
def src_numbered(spark, d):
    rows = _t(spark, d, "nation").select(F.format_string("n%d", "n_nationkey").alias("subject"), F.lit("in").alias("predicate"), F.format_string("r%d", "n_regionkey").alias("object"))
    edges, _ = triples.numbered(rows)
    return edges.agg(F.count("*").alias("n_edges"), F.countDistinct("src").alias("n_src"))


@query("SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1")
def fn_json_props(spark, d):
    return _t(spark, d, "events").select(F.from_json("props", "k bigint")["k"].alias("k")).groupBy("k").agg(F.count("*").alias("n"))


@query("SELECT event_id, json_extract_string(props, '$.k') AS k FROM events WHERE user_id = 5")
def fn_json_path(spark, d):
    return _t(spark, d, "events").filter("user_id = 5").select("event_id", F.get_json_object("props", "$.k").alias("k"))


@query(f"SELECT label, count(*) AS n FROM ({oracles.edge_cte(['adjacent', 'resident_of'])}) GROUP BY label")
def sink_partitioned(spark, d):
    path = new_path(spark, "graph")
    triples.save_by_label(given_graph(spark, d), path, ["adjacent", "resident_of"])
    return triples.load_by_label(spark, path).triples(["adjacent", "resident_of"]).groupBy("label").agg(F.count("*").alias("n"))


@query(oracles.one_seed("bench20_d", True, number("region", 3)))
def sink_bucketed(spark, d):
    """The widest pattern over two bucketed copies of the edges, which are not shuffled."""
    name = new_path(spark, "bucketed").rpartition("-")[2]
    graph = triples.save_bucketed(given_graph(spark, d), f"edges_{name}", 4, ["located", "resident_of", "adjacent", "within"], new_path(spark, "bucketed"))
    return reach.traverse(graph, compile_expr(parse_pattern("(located|resident_of)(adjacent|within)*")).reverse(), [number("region", 3)], literal_cap=0).answers().select("v")


# Projection and filters.


@query(f"SELECT {V(7, 'l_orderkey * 8 + l_linenumber')} AS v, l_quantity FROM lineitem WHERE l_orderkey < 10")
def proj_vid(spark, d):
    return _t(spark, d, "lineitem").filter("l_orderkey < 10").select(vid("item", F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("v"), "l_quantity")


@query(f"SELECT {V(5, 'p_partkey')} AS v FROM part WHERE p_size BETWEEN 10 AND 20 AND p_brand LIKE 'Brand#1%' AND p_name IS NOT NULL AND NOT p_retailprice < 950")
def filter_seeds(spark, d):
    keep = F.col("p_size").between(10, 20) & F.col("p_brand").like("Brand#1%") & F.col("p_name").isNotNull() & ~(F.col("p_retailprice") < 950)
    return _t(spark, d, "part").filter(keep).select(vid("part", "p_partkey").alias("v"))


@query("SELECT c_custkey FROM customer c WHERE c_nationkey IN (1, 3, 5) AND EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o_orderkey % 7 = 0)")
def filter_in_exists(spark, d):
    some = _t(spark, d, "orders").filter("o_orderkey % 7 = 0")
    return _t(spark, d, "customer").filter(F.col("c_nationkey").isin(1, 3, 5)).join(some, F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


# Joins.


@query(f"SELECT a.src AS row, b.dst AS col FROM ({E['ordered_by']}) a JOIN ({E['resident_of']}) b ON b.src = a.dst")
def join_broadcast(spark, d):
    g = given_graph(spark, d)
    a = g.edges("ordered_by").select(F.col("src").alias("row"), F.col("dst").alias("m"))
    b = g.edges("resident_of").select(F.col("src").alias("m"), F.col("dst").alias("col"))
    return a.join(F.broadcast(b) if b.count() <= 1_000_000 else b, "m").select("row", "col")


@query(f"SELECT a.src AS row, b.dst AS col FROM ({E['placed']}) a JOIN ({E['follows']}) b ON b.src = a.dst")
def join_sortmerge(spark, d):
    g = given_graph(spark, d)
    return g.edges("placed").select(F.col("src").alias("row"), F.col("dst").alias("m")).join(g.edges("follows").select(F.col("src").alias("m"), F.col("dst").alias("col")).hint("merge"), "m").select("row", "col")


@query(f"SELECT a.src AS row, b.dst AS col FROM ({E['ordered_by']}) a JOIN ({E['in_segment']}) b ON b.src = a.dst")
def join_shufflehash(spark, d):
    g = given_graph(spark, d)
    return g.edges("ordered_by").select(F.col("src").alias("row"), F.col("dst").alias("m")).join(g.edges("in_segment").select(F.col("src").alias("m"), F.col("dst").alias("col")).hint("shuffle_hash"), "m").select("row", "col")


@query(f"SELECT src, dst FROM ({E['quotes']})")
def join_theta_contains(spark, d):
    return given_graph(spark, d).edges("quotes")


@query(f"SELECT {V(5, 'p_partkey')} AS v, s.src IS NOT NULL AS linked FROM part LEFT JOIN (SELECT DISTINCT src FROM ({E['succ_part']})) s ON s.src = {V(5, 'p_partkey')}")
def join_outer_unlabelled(spark, d):
    heads = given_graph(spark, d).edges("succ_part").select(F.col("src").alias("v")).distinct().withColumn("_has", F.lit(True))
    return _t(spark, d, "part").select(vid("part", "p_partkey").alias("v")).join(heads, "v", "left").select("v", F.col("_has").isNotNull().alias("linked"))


@query(f"""SELECT coalesce(a.v, b.v) AS v, CAST(coalesce(a.m, 0) | coalesce(b.m, 0) AS BIGINT) AS mask FROM (SELECT DISTINCT src AS v, 1 AS m FROM ({E['follows']})) a
           FULL OUTER JOIN (SELECT DISTINCT dst AS v, 2 AS m FROM ({E['follows']})) b ON a.v = b.v""")
def join_full_bitmask(spark, d):
    e = given_graph(spark, d).edges("follows")
    a, b = e.select(F.col("src").alias("v")).distinct().withColumn("a", F.lit(1).cast("long")), e.select(F.col("dst").alias("v")).distinct().withColumn("b", F.lit(2).cast("long"))
    return a.join(b, "v", "full_outer").select("v", F.coalesce("a", F.lit(0)).bitwiseOR(F.coalesce("b", F.lit(0))).cast("long").alias("mask"))


@query("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def join_interval_events(spark, d):
    """Events of a user within an hour: both sides meet in hour buckets, so a user's long history is not paired with itself."""
    e = _t(spark, d, "events").select("event_id", "user_id", "ts").withColumn("hour", F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / 3600))
    left = e.select("user_id", F.col("event_id").alias("a"), F.col("ts").alias("ta"), F.explode(F.array("hour", F.col("hour") + 1)).alias("hour"))
    right = e.select("user_id", F.col("event_id").alias("b"), F.col("ts").alias("tb"), "hour")
    near = (F.col("tb") > F.col("ta")) & (F.col("tb") <= F.col("ta") + F.expr("INTERVAL 1 HOUR"))
    return left.join(right, ["user_id", "hour"]).filter(near).select("a", "b")


@query("""SELECT o_orderkey, e.event_id FROM orders ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events GROUP BY user_id, ts) e
          ON o_custkey = e.user_id AND o_orderdate >= e.ts""")
def join_asof(spark, d):
    """For each order the last event of its user at or before the order date. Rows are sorted by user and day; of earlier days only the last event of
    each is carried on, so a user's long history is not sorted in one task."""
    orders = _t(spark, d, "orders").select(F.col("o_custkey").alias("user_id"), F.col("o_orderdate").alias("ts"), F.lit(1).alias("side"), "o_orderkey", F.lit(None).cast("long").alias("event_id"))
    events = _t(spark, d, "events").select("user_id", "ts", F.lit(0).alias("side"), F.lit(None).cast("long").alias("o_orderkey"), "event_id")
    rows = orders.unionByName(events).withColumn("day", F.to_date("ts"))
    own = Window.partitionBy("user_id", "day").orderBy("ts", "side", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    here = rows.withColumn("last", F.last("event_id", True).over(own)).filter("side = 1").select("user_id", "day", "o_orderkey", "last")
    days = rows.groupBy("user_id", "day").agg(F.max(F.when(F.col("side") == 0, F.struct("ts", "event_id")))["event_id"].alias("of_day"))
    earlier = Window.partitionBy("user_id").orderBy("day").rowsBetween(Window.unboundedPreceding, -1)
    before = days.select("user_id", "day", F.last("of_day", True).over(earlier).alias("before"))
    return here.join(before, ["user_id", "day"]).select("o_orderkey", F.coalesce("last", "before").alias("event_id"))


# Aggregates.


@query(f"SELECT src AS v, count(*) AS n, min(dst) AS lo, max(dst) AS hi FROM (SELECT DISTINCT src, dst FROM ({E['bulk_supply']})) GROUP BY src")
def agg_degree(spark, d):
    return given_graph(spark, d).edges("bulk_supply").groupBy(F.col("src").alias("v")).agg(F.count("*").alias("n"), F.min("dst").alias("lo"), F.max("dst").alias("hi"))


@query(f"SELECT count(DISTINCT src) AS n_src, count(DISTINCT dst) AS n_dst, avg(dst - src) AS gap FROM (SELECT DISTINCT src, dst FROM ({E['adjacent']}))")
def agg_distinct(spark, d):
    return given_graph(spark, d).edges("adjacent").agg(F.countDistinct("src").alias("n_src"), F.countDistinct("dst").alias("n_dst"), F.avg(F.col("dst") - F.col("src")).alias("gap"))


@query("SELECT n_regionkey, CAST(bit_or(1 << (n_nationkey % 20)) AS BIGINT) AS mask FROM nation GROUP BY n_regionkey")
def agg_bitor(spark, d):
    return _t(spark, d, "nation").groupBy("n_regionkey").agg(F.bit_or(F.expr("shiftleft(1L, n_nationkey % 20)")).alias("mask"))


@query(f"SELECT quantile_cont(CAST(n AS DOUBLE), 0.5) AS median FROM (SELECT count(*) AS n FROM (SELECT DISTINCT src, dst FROM ({E['placed']})) GROUP BY src)")
def agg_median(spark, d):
    return given_graph(spark, d).edges("placed").groupBy("src").agg(F.count("*").alias("n")).agg(F.percentile("n", F.lit(0.5)).alias("median"))


@query("SELECT c_nationkey, min_by(c_custkey, (c_acctbal, c_custkey)) AS poorest, max_by(c_custkey, (c_acctbal, c_custkey)) AS richest FROM customer GROUP BY c_nationkey")
def agg_min_by(spark, d):
    by = F.struct("c_acctbal", "c_custkey")
    return _t(spark, d, "customer").groupBy("c_nationkey").agg(F.min_by("c_custkey", by).alias("poorest"), F.max_by("c_custkey", by).alias("richest"))


@query("SELECT c_mktsegment, c_nationkey, count(*) AS n FROM customer GROUP BY ROLLUP (c_mktsegment, c_nationkey)")
def agg_rollup(spark, d):
    return _t(spark, d, "customer").rollup("c_mktsegment", "c_nationkey").agg(F.count("*").alias("n"))


@query("SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
def agg_cube(spark, d):
    return _t(spark, d, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@query("SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority))")
def agg_grouping_sets(spark, d):
    return _t(spark, d, "orders").groupingSets([["o_orderstatus"], ["o_orderpriority"]], "o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@query()
def agg_approx_vertices(spark, d):
    """An estimate of the number of vertices; for statistics only."""
    e = given_graph(spark, d).triples(["placed", "has_item"])
    return e.agg(F.approx_count_distinct("dst", 0.02).alias("n_dst"))


# Windows, sorting, sets.


@query("SELECT event_id, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS next_id FROM events")
def win_lead_next(spark, d):
    return _t(spark, d, "events").select("event_id", F.lead("event_id").over(Window.partitionBy("user_id").orderBy("ts", "event_id")).alias("next_id"))


@query(f"SELECT v, n, CAST(rank() OVER (PARTITION BY n % 10 ORDER BY n DESC) AS INTEGER) AS place FROM (SELECT src AS v, count(*) AS n FROM (SELECT DISTINCT src, dst FROM ({E['placed']})) GROUP BY src)")
def win_rank_degree(spark, d):
    n = given_graph(spark, d).edges("placed").groupBy(F.col("src").alias("v")).agg(F.count("*").alias("n"))
    return n.withColumn("place", F.rank().over(Window.partitionBy(F.col("n") % 10).orderBy(F.desc("n"))))


@query("SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS so_far FROM orders")
def win_running(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(Window.unboundedPreceding, 0)
    return _t(spark, d, "orders").select("o_orderkey", F.count("*").over(w).alias("so_far"))


@query("SELECT value, CAST(dense_rank() OVER (ORDER BY value) AS BIGINT) AS key FROM (SELECT DISTINCT p_brand AS value FROM part)")
def win_dictionary(spark, d):
    return dictionary(F.col("p_brand"), _t(spark, d, "part"))


@query(f"SELECT dst AS v, count(*) AS n FROM (SELECT DISTINCT src, dst FROM ({E['located']})) GROUP BY dst ORDER BY n DESC, v LIMIT 10")
def topk_hubs(spark, d):
    return given_graph(spark, d).edges("located").groupBy(F.col("dst").alias("v")).agg(F.count("*").alias("n")).orderBy(F.desc("n"), "v").limit(10)


_PLACED, _ORDERED = f"SELECT src, dst FROM ({E['placed']})", f"SELECT dst AS src, src AS dst FROM ({E['ordered_by']})"


def _sides(spark, d):
    g = given_graph(spark, d)
    return g.edges("placed").filter("dst % 3 <> 0"), g.edges("ordered_by").select(F.col("dst").alias("src"), F.col("src").alias("dst")).filter("dst % 2 = 0")


@query(f"{_PLACED} WHERE dst % 3 <> 0 UNION {_ORDERED} WHERE src % 2 = 0")
def set_union(spark, d):
    a, b = _sides(spark, d)
    return a.union(b).distinct()


@query(f"{_PLACED} WHERE dst % 3 <> 0 INTERSECT {_ORDERED} WHERE src % 2 = 0")
def set_intersect(spark, d):
    a, b = _sides(spark, d)
    return a.intersect(b)


@query(f"{_PLACED} WHERE dst % 3 <> 0 EXCEPT {_ORDERED} WHERE src % 2 = 0")
def set_except(spark, d):
    a, b = _sides(spark, d)
    return a.exceptAll(b).distinct()


# Functions.


@query("SELECT DISTINCT page_id, unnest(regexp_extract_all(html, '<a href=\"(/[^\"]*)\"', 1)) AS href FROM pages")
def fn_links(spark, d):
    return given_graph(spark, d).hrefs().withColumnRenamed("value", "href")


@query("SELECT page_id, lower(split_part(split_part(split_part(split_part(url, '://', 2), '/', 1), '?', 1), '#', 1)) AS host FROM pages")
def fn_host(spark, d):
    return _t(spark, d, "pages").select("page_id", F.lower(F.regexp_extract("url", r"://([^/?#]*)", 1)).alias("host"))


@query("SELECT md5(text) AS digest, count(*) AS n FROM documents GROUP BY 1 HAVING count(*) > 1")
def fn_md5_groups(spark, d):
    return _t(spark, d, "documents").groupBy(F.md5("text").alias("digest")).agg(F.count("*").alias("n")).filter("n > 1")


@query("SELECT 'placed_' || year(o_orderdate) AS label, count(*) AS n, min(date_diff('day', CAST(date_trunc('year', o_orderdate) AS DATE), CAST(o_orderdate AS DATE))) AS first_day FROM orders GROUP BY 1")
def fn_time_labels(spark, d):
    days = F.datediff("o_orderdate", F.date_trunc("year", "o_orderdate")).cast("long")
    return _t(spark, d, "orders").groupBy(F.concat(F.lit("placed_"), F.year("o_orderdate")).alias("label")).agg(F.count("*").alias("n"), F.min(days).alias("first_day"))


@query("SELECT c_custkey, (c_custkey % 2147483648) * 2654435761 % 4294967296 AS h FROM customer")
def fn_seed_hash(spark, d):
    return _t(spark, d, "customer").select("c_custkey", (F.col("c_custkey") % (1 << 31) * 2654435761 % 4294967296).alias("h"))


@query(f"SELECT DISTINCT src, dst FROM ({E['bulk_supply']})")
def fn_adjacency_pack_unpack(spark, d):
    packed = given_graph(spark, d).edges("bulk_supply").groupBy("src").agg(F.sort_array(F.collect_set("dst")).alias("dsts"))
    return packed.select("src", F.explode("dsts").alias("dst"))


@query("SELECT n_regionkey, count(*) AS n, max(n_nationkey) AS top, count(*) FILTER (WHERE n_nationkey % 2 = 0) AS even FROM nation GROUP BY n_regionkey")
def fn_state_map(spark, d):
    """Arrays and maps in one pass: a map from key to parity, its size, largest key and number of even keys."""
    pairs = F.map_from_entries(F.collect_list(F.struct("n_nationkey", (F.col("n_nationkey") % 2).alias("p"))))
    g = _t(spark, d, "nation").groupBy("n_regionkey").agg(pairs.alias("m"))
    even = F.size(F.filter(F.map_values("m"), lambda x: x == 0)).cast("long")
    return g.select("n_regionkey", F.size("m").cast("long").alias("n"), F.aggregate(F.map_keys("m"), F.lit(-1), lambda a, x: F.greatest(a, x)).alias("top"), even.alias("even"))


_WORDS = (("adjacent within", True), ("within", True), ("adjacent", False), ("adjacent adjacent within", True), ("within adjacent", False), ("^within", False))


@query(f"SELECT * FROM (VALUES {', '.join(f"('{w}', {str(a).lower()})" for w, a in _WORDS)}) t(word, accepted)")
def udf_accepts(spark, d):
    return spark.createDataFrame([(w,) for w, _ in _WORDS], "word string").select("word", evaluate.accepts_udf("adjacent* within")("word").alias("accepted"))


@query("SELECT c_nationkey, quantile_cont(c_acctbal, 0.5) AS median FROM customer GROUP BY c_nationkey")
def udaf_median(spark, d):
    @F.pandas_udf("double")
    def median(x: pd.Series) -> float:
        return x.median()

    return _t(spark, d, "customer").groupBy("c_nationkey").agg(median("c_acctbal").alias("median"))


@query("SELECT * FROM (VALUES (0, 'adjacent', 0, 0, true, false), (0, 'within', 0, 1, true, true)) t(q, label, inv, q2, is_start, is_final)")
def udtf_automaton(spark, d):
    evaluate.register_functions(spark)
    return spark.sql("SELECT * FROM path_query('adjacent* within')")


@query(f"SELECT {V(2, 'n_nationkey')} AS v FROM nation")
def udf_sql_vid(spark, d):
    evaluate.register_functions(spark)
    _t(spark, d, "nation").createOrReplaceTempView("nation_for_vid")
    return spark.sql("SELECT vid(2L, CAST(n_nationkey AS BIGINT)) AS v FROM nation_for_vid")


# Streams, run to the end of their input.


@query(oracles.one_seed("bench19_s", False, number("order", 42)))
def stream_incremental(spark, d):
    """The answers of a query whose edges arrive in three files."""
    folder = new_path(spark, "edges-in")
    g = given_graph(spark, d)
    rows = g.triples(["adjacent", "within", "resident_of"]).unionAll(g.triples(["located"]).filter(F.col("src") == number("order", 42)))
    rows.repartition(3).write.parquet(folder)
    q = incremental.GrowingQuery(spark, compile_expr(parse_pattern("(located|resident_of)(adjacent|within)*")), [number("order", 42)])
    run = incremental.edge_stream(spark, folder).writeStream.foreachBatch(q.add).option("checkpointLocation", new_path(spark, "stream")).trigger(availableNow=True).start()
    run.awaitTermination()
    return q.answers().select("v")


@query("SELECT CAST(epoch(time_bucket(INTERVAL 1 HOUR, ts)) AS BIGINT) AS begin, count(*) AS n_edges, count(DISTINCT user_id) AS n_users FROM events GROUP BY 1")
def stream_tumbling(spark, d):
    return windows.tumbling(windows.timed(_t(spark, d, "events"))).select(F.unix_timestamp("begin").alias("begin"), "n_edges", "n_users")


@query("""SELECT CAST(epoch(time_bucket(INTERVAL 30 MINUTE, ts)) - 1800 * k AS BIGINT) AS begin, count(*) AS n_edges FROM events, (VALUES (0), (1)) t(k) GROUP BY 1""")
def stream_sliding(spark, d):
    return windows.sliding(windows.timed(_t(spark, d, "events"))).select(F.unix_timestamp("begin").alias("begin"), "n_edges")


@query("""WITH e AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
               s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM e)
          SELECT user_id, CAST(floor(epoch(min(ts))) AS BIGINT) AS begin, count(*) AS n_edges FROM s GROUP BY user_id, k""")
def stream_sessions(spark, d):
    return windows.sessions(windows.timed(_t(spark, d, "events"))).select("user_id", F.unix_timestamp("begin").alias("begin"), "n_edges")
