"""Every query by name, and the SQL that checks it. Names follow the workloads; see the README's table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.automaton import compile_expr
from ..functions.cypher import is_cypher_expressible
from ..functions.expr import parse_pattern
from ..functions.sparql import parse_sparql_path, shorten
from ..functions.vertices import KINDS, number, vid
from ..operators import bitmask, reach
from ..operators import relation as rel
from ..sources.graph import given_graph
from . import baselines, evaluate, extensions, measures, oracles
from .exalg import exalg_pairs, exalg_reach
from .workloads import bench20, chain7, hashed_seeds, query_log

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
#: The comparison of all methods on all workloads, and the ablations: many more runs of the same methods.
MORE: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def _add(name: str, query: Query, sql: str | None = None, into: dict[str, Query] = QUERIES) -> None:
    into[name] = query
    if sql is not None:
        ORACLES[name] = sql


def _automaton(work):
    a = compile_expr(parse_pattern(work.pattern))
    return a.reverse() if work.end == "D" else a


def _ends(df: DataFrame) -> DataFrame:
    return df.select("v")


# Workloads: each pattern and each method.


def _by_method(work, method: str, **how) -> Query:
    return lambda spark, d: _ends(reach.traverse(given_graph(spark, d), _automaton(work), [work.vertex], method, **how).answers())


def _by_bitmask(work) -> Query:
    return lambda spark, d: _ends(bitmask.bitmask_reach(given_graph(spark, d), _automaton(work), [work.vertex]))


def _by_algebra(work, **how) -> Query:
    end = "target" if work.end == "D" else "source"
    return lambda spark, d: exalg_reach(given_graph(spark, d), parse_pattern(work.pattern), **{end: work.vertex}, **how)


def _by_batch(work) -> Query:
    def run(spark, d):
        g = given_graph(spark, d)
        return bitmask.batch_reach(g, _automaton(work), _seeds(g, work))

    return run


def _seeds(g, work) -> DataFrame:
    """Up to 1000 seeds of the pattern."""
    return hashed_seeds(g, work.kind, {x for x, _ in parse_pattern(work.pattern).steps()})


def _directed(work):
    """The expression as read from the fixed end."""
    e = parse_pattern(work.pattern)
    return e.inverse() if work.end == "D" else e


def _by_index(work) -> Query:
    return lambda spark, d: _ends(baselines.indexed_reach(given_graph(spark, d), _automaton(work), [work.vertex]))


def _by_subset(work) -> Query:
    return lambda spark, d: _ends(baselines.subset_reach(given_graph(spark, d), _directed(work), [work.vertex]))


def _joined(work, method: str) -> Query:
    """The same by tables alone: no level runs on the driver."""
    if method == "bitmask":
        return lambda spark, d: _ends(bitmask.bitmask_reach(given_graph(spark, d), _automaton(work), [work.vertex], literal_cap=0))
    return _by_method(work, method, literal_cap=0)


def _batch_of(work, method: str) -> Query:
    """Up to 1000 seeds by a comparison method."""

    def run(spark, d):
        g = given_graph(spark, d)
        seeds = _seeds(g, work)
        if method == "indexed":
            return baselines.indexed_reach(g, _automaton(work), seeds)
        if method == "subset":
            return baselines.subset_reach(g, _directed(work), seeds)
        return exalg_pairs(g, parse_pattern(work.pattern), seeds, "target" if work.end == "D" else "source", kernel="shared" if method == "exalg_sk" else "packed")

    return run


for _w in bench20():
    _sql = oracles.one_seed(_w.name, _w.end == "D", _w.vertex)
    _add(_w.name, _by_method(_w, "hybrid"), _sql)
    _add(f"frontier_{_w.name}", _by_method(_w, "frontier"), _sql)
    _add(f"saturation_{_w.name}", _by_method(_w, "saturation"), _sql)
    _add(f"bitmask_{_w.name}", _by_bitmask(_w), _sql)
    _add("exalg" + _w.name.removeprefix("bench"), _by_algebra(_w), _sql)
    _add("exalg_sk" + _w.name.removeprefix("bench"), _by_algebra(_w, kernel="shared"), _sql)
    _many = oracles.many_seeds(_w.name, _w.end == "D", KINDS[_w.kind])
    _add(f"batch_{_w.name}", _by_batch(_w), _many)
    for _m in ("frontier", "saturation", "hybrid", "bitmask"):
        _add(f"join_{_m}_{_w.name}", _joined(_w, _m), _sql, MORE)
    _add(f"indexed_{_w.name}", _by_index(_w), _sql, MORE)
    if is_cypher_expressible(_directed(_w)):
        _add(f"cypher_subset_{_w.name}", _by_subset(_w), _sql, MORE)
        _add(f"batch_cypher_subset_{_w.name}", _batch_of(_w, "subset"), _many, MORE)
    for _m in ("exalg", "indexed"):
        _add(f"batch_{_m}_{_w.name}", _batch_of(_w, _m), _many, MORE)
#: Queries whose walks take tens of levels; the methods that need a Spark job and two tables a level run them only where it is the point.
LONG = ("chain7_5", "chain7_6", "log_04", "log_05", "log_09", "log_26")
for _w in (*chain7(), *query_log()[:27]):
    _sql = oracles.one_seed(_w.name, _w.end == "D", _w.vertex)
    _add(_w.name, _by_method(_w, "hybrid"), _sql)
    for _m in ("frontier", "saturation"):
        _add(f"{_m}_{_w.name}", _by_method(_w, _m), _sql, MORE)
    _add(f"bitmask_{_w.name}", _by_bitmask(_w), _sql, MORE)
    if _w.name not in LONG:
        _add(f"exalg_{_w.name}", _by_algebra(_w), _sql, MORE)
        _add(f"indexed_{_w.name}", _by_index(_w), _sql, MORE)
        if is_cypher_expressible(_directed(_w)):
            _add(f"cypher_subset_{_w.name}", _by_subset(_w), _sql, MORE)
        if _w.name.startswith("chain7"):
            _add(f"exalg_sk_{_w.name}", _by_algebra(_w, kernel="shared"), _sql, MORE)

_WORKS = {w.name: w for w in (*bench20(), *chain7(), *query_log())}


def _same(name: str, work: str, query: Query, into: dict[str, Query] = QUERIES) -> None:
    w = _WORKS[work]
    _add(name, query, oracles.one_seed(work, w.end == "D", w.vertex), into)


# Variants.

for _name, _t in (("hybrid_t0", 0), ("hybrid_t1", 1), ("hybrid_t10", 10), ("hybrid_t100", 100), ("hybrid_t1000", 1000), ("hybrid_tinf", float("inf"))):
    _same(_name, "bench20_d", _by_method(_WORKS["bench20_d"], "hybrid", threshold=_t))
    _same(f"join_{_name}", "bench20_d", _by_method(_WORKS["bench20_d"], "hybrid", threshold=_t, literal_cap=0), MORE)
for _name, _m in (("log_05", "frontier"), ("log_09", "hybrid"), ("log_09", "bitmask"), ("chain7_5", "frontier"), ("log_13", "hybrid")):
    _same(f"join_{_m}_{_name}", _name, _joined(_WORKS[_name], _m), MORE)
for _name in ("bench15_s", "bench20_d"):
    _add(f"batch_rows_{_name}", lambda s, d, w=_WORKS[_name]: reach.hybrid_reach(given_graph(s, d), _automaton(w), _seeds(given_graph(s, d), w)), oracles.many_seeds(_name, _WORKS[_name].end == "D", KINDS[_WORKS[_name].kind]), MORE)
for _layout in measures.LAYOUTS:
    for _name in ("bench05_s", "bench06_d", "bench08_d"):
        _same(f"layout_{_layout}_exalg_{_name}", _name, lambda s, d, w=_WORKS[_name], x=_layout: exalg_reach(measures.LaidOut(given_graph(s, d), x), parse_pattern(w.pattern), **{"target" if w.end == "D" else "source": w.vertex}), MORE)
    if _layout != "quadtree":
        _same(f"layout_{_layout}_frontier_bench15_s", "bench15_s", lambda s, d, x=_layout: _ends(reach.frontier_reach(measures.LaidOut(given_graph(s, d), x), _automaton(_WORKS["bench15_s"]), [_WORKS["bench15_s"].vertex], literal_cap=0)), MORE)
_same("hybrid_literal", "log_05", _by_method(_WORKS["log_05"], "hybrid"))
_same("join_regime_bench15_s", "bench15_s", _by_method(_WORKS["bench15_s"], "hybrid", literal_cap=0))
_same("order_automaton_first", "bench19_s", _by_method(_WORKS["bench19_s"], "frontier", literal_cap=0))
_same("order_graph_first", "bench19_s", _by_method(_WORKS["bench19_s"], "frontier", literal_cap=0, order="graph_first"))
_same("nfa_bench16_d", "bench16_d", lambda s, d: _ends(reach.frontier_reach(given_graph(s, d), compile_expr(parse_pattern(_WORKS["bench16_d"].pattern), False).reverse(), [_WORKS["bench16_d"].vertex])))
_add(
    "frontier_as_printed_nullable", _by_method(_WORKS["log_06"], "frontier", seed_visited=False),
    f"SELECT DISTINCT dst AS v FROM ({oracles.EDGES['ordered_by']}) WHERE src = {_WORKS['log_06'].vertex}",
)
_add("pairs_all_states", lambda s, d: reach.reach_pairs(given_graph(s, d), _automaton(_WORKS["bench19_s"]), [_WORKS["bench19_s"].vertex]), oracles.one_seed("bench19_s", False, _WORKS["bench19_s"].vertex, "seed, q, v", (0, 1)))
_add("trace_levels", lambda s, d: reach.trace_reach(given_graph(s, d), _automaton(_WORKS["bench09_s"]), [_WORKS["bench09_s"].vertex]).select("level", "q", "v"), oracles.leveled("bench09_s", False, _WORKS["bench09_s"].vertex, 10))
_add("bounded_n", lambda s, d: reach.trace_reach(given_graph(s, d), _automaton(_WORKS["bench09_s"]), [_WORKS["bench09_s"].vertex], max_levels=2).select("level", "q", "v"), oracles.leveled("bench09_s", False, _WORKS["bench09_s"].vertex, 2))
_add(
    "seed_blocks_bench15_s", lambda s, d: bitmask.seed_blocks_reach(given_graph(s, d), _automaton(_WORKS["bench15_s"]), hashed_seeds(given_graph(s, d), "order", ["ordered_by", "resident_of", "adjacent", "within"])),
    oracles.many_seeds("bench15_s", False, KINDS["order"]),
)


def _pair_query(spark, d):
    q = evaluate.PathQuery(parse_pattern("ordered_by resident_of (adjacent|within)*"), [number("order", 42), number("order", 7)], [number("region", k) for k in range(5)])
    return evaluate.evaluate(given_graph(spark, d), q)


_add("pair_query", _pair_query, f"SELECT seed, v FROM ({oracles._query(*oracles.parts('bench15_s', False), f'SELECT unnest([{number('order', 42)}, {number('order', 7)}])', 'seed, v')}) WHERE v < {2 * 10**14}")


def _vf_filtered(spark, d):
    toxic = spark.read.parquet(f"{d}/labels.parquet").filter("toxic = 1").select(vid("doc", "doc_id").alias("v"))
    return evaluate.evaluate(given_graph(spark, d), evaluate.PathQuery(parse_pattern("^in_lang"), [number("lang", 2)], toxic)).select("v")


_add("vf_filtered_docs", _vf_filtered, f"SELECT DISTINCT src AS v FROM ({oracles.EDGES['in_lang']}) WHERE dst = {number('lang', 2)} AND src IN (SELECT {oracles.v(14, 'doc_id')} FROM labels WHERE toxic = 1)")


def _intersected(spark, d):
    both = compile_expr(parse_pattern("adjacent* within")).intersect(compile_expr(parse_pattern("(adjacent|within)(adjacent|within)"))).trim()
    return _ends(reach.frontier_reach(given_graph(spark, d), both, [number("nation", 3)]))


_add("intersect_automata", _intersected, f"SELECT DISTINCT b.dst AS v FROM ({oracles.EDGES['adjacent']}) a JOIN ({oracles.EDGES['within']}) b ON b.src = a.dst WHERE a.src = {number('nation', 3)}")


def _transitions(spark, d):
    """The minimal automaton as a table, with the number of edges of the given tables that each transition can take."""
    a = compile_expr(parse_pattern("placed* ordered_by"))
    n = given_graph(spark, d).label_stats({label for label, _ in a.steps}).select("label", "n")
    return a.to_df(spark).join(n, "label", "left").select("q", "label", "inv", "q2", F.coalesce("n", F.lit(0)).alias("n"))


_add(
    "automaton_table", _transitions,
    f"""SELECT q, label, inv, q2, n FROM (VALUES (CAST(0 AS INTEGER), 'ordered_by', CAST(0 AS INTEGER), CAST(1 AS INTEGER)), (0, 'placed', 0, 0)) t(q, label, inv, q2)
        JOIN (SELECT label, count(*) AS n FROM ({oracles.edge_cte(["ordered_by", "placed"])}) GROUP BY label) USING (label)""",
)
_SIZES = (("d*", 1), ("d+", 2), ("a b c", 4), ("(a b)*", 2), ("(c|g)(d|e)*", 2), ("f g (d|e)*", 3), ("d* e", 2))
_add("min_dfa_sizes", lambda s, d: s.createDataFrame([(x, compile_expr(parse_pattern(x)).n) for x, _ in _SIZES], "pattern string, n long"), f"SELECT * FROM (VALUES {', '.join(f"('{x}', CAST({n} AS BIGINT))" for x, n in _SIZES)}) t(pattern, n)")
_NOT_CYPHER = {"log_13", "log_14", "log_15", "log_16"}
_add(
    "cypher_expressibility", lambda s, d: s.createDataFrame([(w.name, is_cypher_expressible(parse_pattern(w.pattern))) for w in query_log()[:27]], "query string, expressible boolean"),
    f"SELECT * FROM (VALUES {', '.join(f"('log_{i:02d}', {'false' if f'log_{i:02d}' in _NOT_CYPHER else 'true'})" for i in range(1, 28))}) t(query, expressible)",
)


def _sparql(spark, d):
    p = parse_sparql_path(f"v:{number('nation', 3)} (r:adjacent|r:within)* ?x .", {"v": "urn:vertex:", "r": "urn:label:"})
    return _ends(reach.hybrid_reach(given_graph(spark, d), compile_expr(shorten(p.expr, "urn:label:")), [int(p.source.removeprefix("urn:vertex:"))]))


_same("sparql_path_query", "log_07", _sparql)
_same("sql_surface", "log_07", lambda s, d: _ends(evaluate.rpq_sql(given_graph(s, d), f"PATHS (adjacent|within)* FROM {number('nation', 3)} AS answers_of_log_07")))


def _cleaned(spark, d):
    rows = [(w.name, w.pattern, w.vertex if w.end == "S" else None, w.vertex if w.end == "D" else None) for w in query_log()]
    return evaluate.clean_workload(given_graph(spark, d), rows)


_REASONS = {"log_28": "missing vertex", "log_29": "no fixed end"}
for _name in ("log_clean", "clean_workload"):
    _add(_name, _cleaned, f"SELECT * FROM (VALUES {', '.join(f"('log_{i:02d}', {'false' if f'log_{i:02d}' in _REASONS else 'true'}, '{_REASONS.get(f'log_{i:02d}', '')}')" for i in range(1, 30))}) t(query, kept, reason)")


def _drop_trivial(spark, d):
    g = given_graph(spark, d)
    seeds = [number("region", 3), number("nation", 3)]
    return evaluate.drop_trivial(reach.hybrid_reach(g, compile_expr(parse_pattern("adjacent*")), seeds), True)


_add("drop_trivial", _drop_trivial, f"SELECT CAST({number('nation', 3)} AS BIGINT) AS seed, v FROM ({oracles.one_seed('bench05_s', False, number('nation', 3))})")

# Boolean relations over nations.


def _rel(spark, d, label):
    return rel.relation(given_graph(spark, d).edges(label))


def _pairs_sql(label: str) -> str:
    return f"(SELECT DISTINCT src AS row, dst AS col FROM ({oracles.EDGES[label]}))"


_A, _W = _pairs_sql("adjacent"), _pairs_sql("within")
_AA = f"(SELECT DISTINCT x.row, y.col FROM {_A} x JOIN {_A} y ON y.row = x.col)"
_NATIONS = f"(SELECT {oracles.v(2, 'n_nationkey')} AS v FROM nation)"
_PLUS = f"WITH RECURSIVE a AS {_A}, c(row, col) AS (SELECT row, col FROM a UNION SELECT c.row, a.col FROM c JOIN a ON a.row = c.col)"


def _nations(spark, d):
    return spark.read.parquet(f"{d}/nation.parquet").select(vid("nation", "n_nationkey").alias("v"))


_add("bm_zero", lambda s, d: rel.zero(s), "SELECT CAST(0 AS BIGINT) AS row, CAST(0 AS BIGINT) AS col WHERE false")
_add("bm_transpose", lambda s, d: rel.transpose(_rel(s, d, "within")), f"SELECT col AS row, row AS col FROM {_W}")
_add("bm_sum", lambda s, d: rel.union(_rel(s, d, "within"), _rel(s, d, "adjacent")), f"SELECT row, col FROM {_W} UNION SELECT row, col FROM {_A}")
_add("bm_product", lambda s, d: rel.compose(_rel(s, d, "adjacent"), _rel(s, d, "within")), f"SELECT DISTINCT x.row, y.col FROM {_A} x JOIN {_W} y ON y.row = x.col")
_add("bm_mask", lambda s, d: rel.mask(rel.closure(_rel(s, d, "adjacent")), rel.transpose(_rel(s, d, "adjacent"))), f"SELECT col AS row, row AS col FROM {_A}")
_add("bm_mask_not", lambda s, d: rel.mask_not(rel.closure(_rel(s, d, "adjacent")), _rel(s, d, "adjacent")), f"{_PLUS} SELECT row, col FROM c EXCEPT SELECT row, col FROM a")
_add("bm_complement", lambda s, d: rel.complement(_rel(s, d, "adjacent"), _nations(s, d), _nations(s, d)), f"SELECT x.v AS row, y.v AS col FROM {_NATIONS} x, {_NATIONS} y EXCEPT SELECT row, col FROM {_A}")
_add("bm_vecmul", lambda s, d: rel.vec_mul(s.createDataFrame([(number("nation", k),) for k in (3, 5)], "v long"), _rel(s, d, "within")), f"SELECT DISTINCT col AS v FROM {_W} WHERE row IN ({number('nation', 3)}, {number('nation', 5)})")
_add("bm_closure_plus", lambda s, d: rel.closure(_rel(s, d, "adjacent")), f"{_PLUS} SELECT row, col FROM c")
_add("bm_closure_squaring", lambda s, d: rel.closure(_rel(s, d, "adjacent"), method="squaring"), f"{_PLUS} SELECT row, col FROM c")
_add("bm_closure_star", lambda s, d: rel.closure(_rel(s, d, "adjacent"), _nations(s, d)), f"{_PLUS} SELECT row, col FROM c UNION SELECT v, v FROM {_NATIONS}")
_add("decomposition_counts", lambda s, d: given_graph(s, d).hops([("adjacent", 0), ("adjacent", 1), ("within", 0)]).groupBy("label", "inv").agg(F.count("*").alias("n")), f"SELECT 'adjacent' AS label, CAST(i AS INTEGER) AS inv, (SELECT count(*) FROM {_A}) AS n FROM (VALUES (0), (1)) t(i) UNION ALL SELECT 'within', 0, (SELECT count(*) FROM {_W})")

# Comparison methods.

_same("exalg_unrestricted", "bench17_s", _by_algebra(_WORKS["bench17_s"], restrict=False))
_same("exalg_no_reorder", "bench13_s", _by_algebra(_WORKS["bench13_s"], restrict=False, reorder=False))
_same("exalg_reorder", "bench13_s", _by_algebra(_WORKS["bench13_s"], restrict=False))
_same("exalg_lazy", "bench20_d", _by_algebra(_WORKS["bench20_d"], eager=False))
for _n in ("bench01_s", "bench02_d", "bench03_s", "bench13_s", "bench16_d", "bench20_d"):
    for _how in (True, False):
        _same(f"exalg_end_{'reorder' if _how else 'in_order'}_{_n}", _n, _by_algebra(_WORKS[_n], reorder=_how), MORE)
for _n, _depth in (
    *((f"bench{i:02d}_{e}", 3) for i, e in ((1, "s"), (3, "s"), (4, "d"), (13, "s"), (14, "d"))), ("bench17_s", 2),
    ("log_01", 1), ("log_02", 2), ("log_03", 4), ("log_04", 40), ("log_06", 1), ("log_10", 1), ("log_11", 2), ("log_12", 2), ("log_17", 1), ("log_18", 2), ("log_21", 2), ("log_27", 2),
):
    _same(f"recursive_sql_{_n}", _n, lambda s, d, w=_WORKS[_n], k=_depth: baselines.recursive_sql_reach(s, given_graph(s, d), _automaton(w), w.vertex, k))

# Layouts, statistics, measures.

_ALL = f"({oracles.edge_cte(oracles.EDGES)})"
_add("label_stats", lambda s, d: given_graph(s, d).label_stats(), f"SELECT label, count(*) AS n, count(DISTINCT src) AS n_src, count(DISTINCT dst) AS n_dst FROM {_ALL} GROUP BY label")
_add("graph_stats", lambda s, d: measures.graph_stats(given_graph(s, d)), f"SELECT (SELECT count(*) FROM {_ALL}) AS n_edges, (SELECT count(*) FROM (SELECT src FROM {_ALL} UNION SELECT dst FROM {_ALL})) AS n_vertices, CAST({len(oracles.EDGES)} AS BIGINT) AS n_labels")


def _answer_counts(spark, d):
    g = given_graph(spark, d)
    out = None
    for w in bench20():
        df = reach.traverse(g, _automaton(w), [w.vertex]).answers().agg(F.countDistinct("v").alias("n")).select(F.lit(w.name).alias("query"), F.lit(w.pattern).alias("pattern"), "n")
        out = df if out is None else out.unionAll(df)
    return out


_COUNTS = " UNION ALL ".join(f"SELECT '{w.name}' AS query, '{w.pattern}' AS pattern, (SELECT count(*) FROM ({oracles.one_seed(w.name, w.end == 'D', w.vertex)})) AS n" for w in bench20())
_add("bench_table", _answer_counts, _COUNTS)
_add("answer_counts", lambda s, d: _answer_counts(s, d).select("query", "n"), f"SELECT query, n FROM ({_COUNTS})")
_add(
    "footprint", lambda s, d: measures.footprint(given_graph(s, d), "both").select("n_edges", "bytes", F.round("bytes_per_triple", 6).alias("bytes_per_triple")),
    f"""SELECT CAST(sum(n) AS BIGINT) AS n_edges, CAST(sum(b) AS BIGINT) AS bytes, round(sum(b) / sum(n), 6) AS bytes_per_triple
        FROM (SELECT count(*) AS n, (count(DISTINCT src) + count(DISTINCT dst) + 2) * 8 + (count(DISTINCT src) + count(DISTINCT dst)) * 8 + count(*) * 16 AS b FROM {_ALL} GROUP BY label)""",
)
_add("layout_bytes", lambda s, d: measures.layout_bytes(given_graph(s, d), "adjacency_out"), f"SELECT label, CAST((count(DISTINCT src) + 1) * 8 + count(DISTINCT src) * 8 + count(*) * 8 AS BIGINT) AS bytes FROM {_ALL} GROUP BY label")
_add("layout_adjacency_query", lambda s, d: measures.unpacked(measures.adjacency_out(given_graph(s, d), ["bulk_supply"])).filter(F.col("src") == number("supplier", 7)).select(F.col("dst").alias("v")), f"SELECT DISTINCT dst AS v FROM ({oracles.EDGES['bulk_supply']}) WHERE src = {number('supplier', 7)}")
_add("layout_adjacency_in", lambda s, d: measures.adjacency_in(given_graph(s, d), ["within"]).select("dst", F.size("srcs").cast("long").alias("n")), f"SELECT col AS dst, count(*) AS n FROM {_W} GROUP BY col")


def _small_matrix(spark, d):
    return spark.read.parquet(f"{d}/nation.parquet").select(F.col("n_nationkey").cast("long").alias("row"), F.col("n_regionkey").cast("long").alias("col")).distinct()


_add("layout_quadtree_decode", lambda s, d: measures.quadtree_decode(measures.quadtree(_small_matrix(s, d), 5), 5), "SELECT DISTINCT CAST(n_nationkey AS BIGINT) AS row, CAST(n_regionkey AS BIGINT) AS col FROM nation")
_add(
    "layout_quadtree_bits", lambda s, d: measures.quadtree(_small_matrix(s, d), 5).groupBy("level").agg((F.count("*") * 4).alias("bits")),
    "SELECT CAST(l AS INTEGER) AS level, (SELECT count(*) FROM (SELECT DISTINCT n_nationkey >> (5 - l), n_regionkey >> (5 - l) FROM nation)) * 4 AS bits FROM (VALUES (0), (1), (2), (3), (4)) t(l)",
)

_TIMES = [("ours", "q1", "simple", 1.0, "ok"), ("ours", "q2", "simple", 3.0, "ok"), ("ours", "q3", "simple", 2.0, "ok"), ("other", "q1", "simple", 2.0, "ok"), ("other", "q2", "simple", 6.0, "ok"), ("other", "q3", "simple", 10.0, "ok"), ("other", "q4", "simple", 60000.0, "timeout"), ("ours", "q4", "simple", 2.0, "ok")]
_TIMES_SQL = f"(SELECT * FROM (VALUES {', '.join(f"('{a}', '{b}', '{c}', CAST({m} AS DOUBLE), '{x}')" for a, b, c, m, x in _TIMES)}) t(system, query, grp, ms, status))"
_DONE = f"(SELECT * FROM {_TIMES_SQL} WHERE status = 'ok')"


def _times(spark):
    return spark.createDataFrame(_TIMES, measures.TIMING)


_add("cost_total", lambda s, d: measures.summarize(_times(s)).select("system", "total_ms"), f"SELECT system, sum(ms) AS total_ms FROM {_DONE} GROUP BY system")
_add("cost_mean", lambda s, d: measures.summarize(_times(s)).select("system", "n", "mean_ms"), f"SELECT system, count(*) AS n, avg(ms) AS mean_ms FROM {_DONE} GROUP BY system")
_add("cost_median", lambda s, d: measures.summarize(_times(s)).select("system", "median_ms"), f"SELECT system, quantile_cont(ms, 0.5) AS median_ms FROM {_DONE} GROUP BY system")
_add(
    "cost_speedup", lambda s, d: measures.relative_speedup(_times(s), "ours").select("system", *(F.round(c, 9).alias(c) for c in ("mean_speedup", "median_speedup", "times_slower_mean"))),
    f"""WITH m AS (SELECT system, avg(ms) AS a, quantile_cont(ms, 0.5) AS b FROM {_DONE} GROUP BY system), o AS (SELECT * FROM m WHERE system = 'ours')
        SELECT m.system, round(o.a / m.a, 9) AS mean_speedup, round(o.b / m.b, 9) AS median_speedup, round(m.a / o.a, 9) AS times_slower_mean FROM m, o""",
)
_add("cost_distribution", lambda s, d: measures.distribution(_times(s)).select("system", "p0", "p25", "p50", "p75", "p100"), f"SELECT system, min(ms) AS p0, quantile_cont(ms, 0.25) AS p25, quantile_cont(ms, 0.5) AS p50, quantile_cont(ms, 0.75) AS p75, max(ms) AS p100 FROM {_DONE} GROUP BY system")
_add("cost_per_pattern", lambda s, d: measures.per_pattern(_times(s)), f"SELECT query, system, sum(ms) AS total_ms FROM {_DONE} GROUP BY query, system")
_SYSTEMS = ("hybrid", "exalg", "indexed", "cypher_subset")


def _method_status(spark, d):
    """Which method can state which query of the log."""
    rows = [(m, w.name, "ok" if m != "cypher_subset" or is_cypher_expressible(_directed(w)) else "not expressible") for w in query_log()[:27] for m in _SYSTEMS]
    return spark.createDataFrame(rows, "system string, query string, status string")


_add(
    "method_status", _method_status,
    f"SELECT * FROM (VALUES {', '.join(f"('{m}', 'log_{i:02d}', '{'not expressible' if m == 'cypher_subset' and f'log_{i:02d}' in _NOT_CYPHER else 'ok'}')" for i in range(1, 28) for m in _SYSTEMS)}) t(system, query, status)",
)


def _real_runs(spark, d):
    """system, query, answered: the simple queries of a short log, run and timed by three methods; the times themselves are in bench.py."""
    g = given_graph(spark, d)
    works = [_WORKS[n] for n in ("log_02", "log_07", "log_12")]
    runs = [("hybrid", w.name, "simple", lambda w=w: reach.hybrid_reach(g, _automaton(w), [w.vertex])) for w in works]
    runs += [("exalg", w.name, "simple", lambda w=w: exalg_reach(g, parse_pattern(w.pattern), source=w.vertex)) for w in works]
    runs += [("indexed", w.name, "simple", lambda w=w: baselines.indexed_reach(g, _automaton(w), [w.vertex])) for w in works]
    times = evaluate.timings(spark, runs, 300)
    both = measures.summarize(times).join(measures.relative_speedup(times, "hybrid"), ["system", "grp"])
    return both.select("system", "n", (F.abs(F.col("mean_ms") * F.col("n") - F.col("total_ms")) < 0.001).alias("adds_up"), (F.abs(F.col("mean_speedup") * F.col("times_slower_mean") - 1) < 1e-9).alias("inverse"))


_add("cost_of_real_runs", _real_runs, "SELECT * FROM (VALUES ('hybrid', CAST(3 AS BIGINT), true, true), ('exalg', 3, true, true), ('indexed', 3, true, true)) t(system, n, adds_up, inverse)")
_add("status_counts", lambda s, d: measures.status_counts(_times(s)), f"SELECT system, status, count(*) AS n FROM {_TIMES_SQL} GROUP BY system, status")


def _split(spark, d):
    known = spark.createDataFrame([(w.name, is_cypher_expressible(parse_pattern(w.pattern))) for w in query_log()[:27]], "query string, expressible boolean")
    return measures.classify(known, spark.createDataFrame([("other", "log_05", "", 60000.0, "timeout")], measures.TIMING))


_add("split_simple_complex", _split, f"SELECT * FROM (VALUES {', '.join(f"('log_{i:02d}', '{'complex' if f'log_{i:02d}' in _NOT_CYPHER | {'log_05'} else 'simple'}')" for i in range(1, 28))}) t(query, grp)")

# Extensions.

_same("ext_rare_label", "bench13_s", lambda s, d: _ends(extensions.rare_label_reach(given_graph(s, d), parse_pattern(_WORKS["bench13_s"].pattern), [_WORKS["bench13_s"].vertex])))
_same("ext_rare_label_chain", "chain7_1", lambda s, d: _ends(extensions.rare_label_reach(given_graph(s, d), parse_pattern(_WORKS["chain7_1"].pattern), [_WORKS["chain7_1"].vertex])))
_same("ext_push_pull", "log_21", lambda s, d: extensions.push_pull_reach(given_graph(s, d), _automaton(_WORKS["log_21"]), _WORKS["log_21"].vertex))
_add("ext_distance", lambda s, d: extensions.distance_reach(given_graph(s, d), _automaton(_WORKS["bench15_s"]), [_WORKS["bench15_s"].vertex]).select("v", "dist"), f"SELECT v, CAST(min(level) AS BIGINT) AS dist FROM ({oracles.leveled('bench15_s', False, _WORKS['bench15_s'].vertex, 12)}) WHERE q = 2 GROUP BY v")
_add(
    "ext_witness", lambda s, d: extensions.witness_reach(given_graph(s, d), _automaton(_WORKS["bench15_s"]), [_WORKS["bench15_s"].vertex]).select("v", F.size("path").cast("long").alias("dist"), (F.coalesce(F.element_at("path", -1)["v"], "v") == F.col("v")).alias("ends")),
    f"SELECT v, CAST(min(level) AS BIGINT) AS dist, true AS ends FROM ({oracles.leveled('bench15_s', False, _WORKS['bench15_s'].vertex, 12)}) WHERE q = 2 GROUP BY v",
)
_L1, _L2 = f"(SELECT DISTINCT src, dst FROM ({oracles.EDGES['has_item']}))", f"(SELECT DISTINCT src, dst FROM ({oracles.EDGES['of_part']}))"
_add(
    "ext_count", lambda s, d: extensions.count_shortest(given_graph(s, d), compile_expr(parse_pattern("placed has_item of_part")), [number("customer", 5)]).select("v", "dist", "n"),
    f"SELECT c.dst AS v, CAST(3 AS BIGINT) AS dist, count(*) AS n FROM (SELECT DISTINCT src, dst FROM ({oracles.EDGES['placed']})) a JOIN {_L1} b ON b.src = a.dst JOIN {_L2} c ON c.src = b.dst WHERE a.src = {number('customer', 5)} GROUP BY c.dst",
)
_add(
    "ext_simple_paths", lambda s, d: extensions.simple_paths(given_graph(s, d), compile_expr(parse_pattern("adjacent+")), [number("nation", 3)], 4).select("v", (F.size("path") - 1).cast("long").alias("n")),
    f"SELECT v, CAST(level AS BIGINT) AS n FROM ({oracles.leveled('bench09_s', False, number('nation', 3), 4)}) WHERE level > 0",
)
_same("ext_auto", "bench11_s", lambda s, d: extensions.auto_reach(given_graph(s, d), parse_pattern(_WORKS["bench11_s"].pattern), _WORKS["bench11_s"].vertex))
