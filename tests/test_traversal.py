import random

import pytest

from pathloom.functions.automaton import compile_expr, to_nfa
from pathloom.functions.expr import Alt, Concat, Label, Opt, Plus, Star, parse_pattern
from pathloom.operators import bitmask, levels, reach
from pathloom.plans import baselines, evaluate, extensions
from pathloom.plans.exalg import Size, estimate, exalg_reach, product_order

from .graphs import CHAIN, DIAMOND, HUB, LOOP, RARE, RING, STEP, TWO, ZIGZAG, dfa, ends, graph, pairs

METHODS = ("frontier", "saturation", "hybrid")


@pytest.mark.parametrize("method", METHODS)
@pytest.mark.parametrize("cap", [0, 1000])
@pytest.mark.parametrize("order", ["automaton_first", "graph_first"])
def test_worked_step(spark, method, cap, order):
    g = graph(spark, STEP)
    assert ends(reach.traverse(g, dfa("a* b"), [3], method, literal_cap=cap, order=order).answers()) == [4, 5]


def test_levels_of_worked_step(spark):
    rows = reach.trace_reach(graph(spark, STEP), dfa("a* b"), [3]).collect()
    by = {}
    for r in rows:
        by.setdefault(r["level"], set()).add((r["q"], r["v"]))
    assert by == {0: {(0, 3)}, 1: {(0, 1), (1, 5)}, 2: {(0, 2)}, 3: {(0, 6), (1, 4)}}
    counts = reach.level_counts(graph(spark, STEP), dfa("a* b"), [3])
    assert [c.new for c in counts] == [2, 1, 2, 0] and counts[-1].known == 6 and {c.regime for c in counts} == {"literal"}


def test_zero_length_answers(spark):
    g = graph(spark, CHAIN)
    for seed, whole, printed in ((3, [3], []), (1, [1, 2, 3], [2, 3])):
        assert ends(reach.frontier_reach(g, dfa("a*"), [seed])) == whole
        for cap in (0, 1000):
            assert ends(reach.frontier_reach(g, dfa("a*"), [seed], seed_visited=False, literal_cap=cap)) == printed
    g = graph(spark, LOOP)
    assert ends(reach.frontier_reach(g, dfa("a*"), [1])) == ends(reach.frontier_reach(g, dfa("a*"), [1], seed_visited=False)) == [1, 2]


def test_each_pair_is_extended_once(spark):
    for rows, text, seed in ((LOOP, "a*", 1), (RING, "d+", 1), (HUB, "(c|g)(d|e)*", 10)):
        found = reach.traverse(graph(spark, rows), dfa(text), [seed], "frontier")
        assert sum(x.frontier for x in found.plan.trace) == found.known.size


def test_two_way(spark):
    g = graph(spark, ZIGZAG)
    assert ends(reach.hybrid_reach(g, dfa("a ^a"), [1])) == [1, 3]
    assert ends(reach.hybrid_reach(g, dfa("(a ^a)*"), [1])) == [1, 3, 5]


def test_reversing_inverts_labels(spark):
    assert ends(reach.reverse_reach(graph(spark, TWO), dfa("a b"), [3])) == [1]
    g = graph(spark, CHAIN)
    assert ends(reach.reverse_reach(g, dfa("a*"), [1])) == [1] and ends(reach.reverse_reach(g, dfa("a*"), [3])) == [1, 2, 3]


def test_edges_are_a_set(spark):
    g = graph(spark, [("a", 1, 2), ("a", 1, 2), ("b", 1, 2)])
    assert g.triples().count() == 2 and ends(reach.hybrid_reach(g, dfa("a|b"), [1])) == [2]


def test_nulls_and_empty_graphs(spark):
    from pathloom.sources.graph import EDGE, EdgeTable

    g = EdgeTable(spark.createDataFrame([(None, 1, 2), ("a", None, 2), ("a", 1, None), ("a", 1, 2)], EDGE))
    assert g.triples().count() == 1
    none = EdgeTable(spark.createDataFrame([], EDGE))
    assert none.labels() == [] and ends(reach.hybrid_reach(none, dfa("a*"), [1])) == [1] and ends(reach.hybrid_reach(none, dfa("a"), [1])) == []


@pytest.mark.parametrize("cap", [0, 1000])
def test_bounded(spark, cap):
    g = graph(spark, RING)
    for n in range(5):
        found = reach.reach_pairs(g, dfa("d*"), [1], max_levels=n, literal_cap=cap)
        assert ends(found) == list(range(1, n + 2))
    assert len(reach.level_counts(g, dfa("d+"), [1])) == 6 and len(reach.level_counts(g, dfa("d*"), [1])) == 5


def test_absent_labels(spark):
    g = graph(spark, STEP)
    assert ends(reach.hybrid_reach(g, dfa("zzz|b"), [3])) == [5] and ends(reach.hybrid_reach(g, dfa("zzz"), [3])) == []


@pytest.mark.parametrize("threshold", [0, 1, 3, 100, 10**12])
@pytest.mark.parametrize("cap", [0, 1000])
def test_hybrid_thresholds(spark, threshold, cap):
    assert ends(reach.hybrid_reach(graph(spark, HUB), dfa("(c|g)(d|e)*"), [10], threshold, literal_cap=cap)) == [1, 2, 3, 9]
    assert ends(reach.hybrid_reach(graph(spark, RING), dfa("d+"), [1], threshold, literal_cap=cap)) == [1, 2, 3, 4, 5]


def test_hub_backward(spark):
    g, a = graph(spark, HUB), dfa("(c|g)(d|e)*")
    assert ends(reach.reverse_reach(g, a, [9])) == [10, 11, 12] and ends(reach.reverse_reach(g, a, [1])) == [10, 11]


def test_seeds_do_not_mix(spark):
    g = graph(spark, CHAIN)
    want = [(1, 1), (1, 2), (1, 3), (2, 2), (2, 3)]
    seeds = spark.createDataFrame([(1,), (2,), (2,), (None,)], "v long")
    for cap in (0, 1000):
        assert pairs(reach.hybrid_reach(g, dfa("a*"), seeds, literal_cap=cap)) == want
        assert pairs(bitmask.bitmask_reach(g, dfa("a*"), seeds, literal_cap=cap)) == want
    assert pairs(bitmask.seed_blocks_reach(g, dfa("a*"), seeds)) == want


def test_missing_seed(spark):
    g = graph(spark, STEP)
    assert ends(reach.hybrid_reach(g, dfa("a"), [99])) == [] and ends(reach.hybrid_reach(g, dfa("a*"), [99])) == [99]


def test_fetch_bound_leaves_the_literal_regime(spark, monkeypatch):
    from pathloom.operators import levels

    monkeypatch.setattr(levels, "FETCH_CAP", 3)
    g = graph(spark, [("a", 1, i) for i in range(2, 12)] + [("b", i, 100 + i % 3) for i in range(2, 12)])
    counts = reach.level_counts(g, dfa("a b"), [1])
    assert counts[0].regime == "join" and ends(reach.hybrid_reach(g, dfa("a b"), [1])) == [100, 101, 102]


def test_pair_queries(spark):
    g, e = graph(spark, HUB), parse_pattern("(c|g)(d|e)*")
    run = lambda s, t: pairs(evaluate.evaluate(g, evaluate.PathQuery(e, s, t)))
    assert run([10, 12], [9, 3]) == [(10, 3), (10, 9), (12, 3), (12, 9)] and run([10, 11, 12], [1]) == [(10, 1), (11, 1)]
    assert run(None, [1]) == [(10, 1), (11, 1)] and run([12], None) == [(12, 2), (12, 3), (12, 9)]
    assert len(run(None, None)) == 11
    assert pairs(evaluate.evaluate(g, evaluate.PathQuery(e, [10], spark.createDataFrame([(9,), (4,)], "x long")))) == [(10, 9)]
    assert evaluate.PathQuery.to_target("a", 3).finals == [3] and evaluate.PathQuery.from_source("a", 3).sources == [3]


def test_statement(spark):
    g = graph(spark, HUB)
    assert pairs(evaluate.rpq_sql(g, "paths (c|g)(d|e)* from 10 to 9 as hubs")) == [(10, 9)] and spark.table("hubs").count() == 1


def random_case(rng):
    rows = list({(rng.choice("abc"), rng.randrange(8), rng.randrange(8)) for _ in range(rng.randrange(4, 18))})

    def expr(depth):
        k = rng.random()
        if depth == 0 or k < 0.3:
            return Label(rng.choice("abc"), int(rng.random() < 0.3))
        if k < 0.55:
            return Concat((expr(depth - 1), expr(depth - 1)))
        if k < 0.75:
            return Alt((expr(depth - 1), expr(depth - 1)))
        return rng.choice((Star, Plus, Opt))(expr(depth - 1))

    return rows, expr(3)


@pytest.mark.parametrize("case", range(12))
def test_all_methods_agree_with_brute_force(spark, case):
    rng = random.Random(case)
    rows, e = random_case(rng)
    g, a, seed = graph(spark, rows), compile_expr(e), rng.randrange(8)
    g.table = g.table.persist()
    want = sorted(baselines.brute_reach(rows, a, seed))
    for method in METHODS:
        assert ends(reach.traverse(g, a, [seed], method).answers()) == want
    assert ends(reach.traverse(g, a, [seed], "hybrid", 3, literal_cap=0).answers()) == want
    assert ends(reach.frontier_reach(g, to_nfa(e), [seed])) == want
    assert ends(bitmask.bitmask_reach(g, a, [seed])) == want
    assert ends(exalg_reach(g, e, source=seed, kernel=rng.choice(("packed", "shared")), eager=rng.random() < 0.5)) == want
    back = sorted(v for v in range(8) if seed in baselines.brute_reach(rows, a, v))
    assert ends(reach.reverse_reach(g, a, [seed])) == (back if not a.nullable else sorted({*back, seed}))
    g.table.unpersist()


def test_brute_force_by_words():
    for case in range(200):
        rng = random.Random(1000 + case)
        rows, e = random_case(rng)
        rows = rows[:6]
        a = compile_expr(e)
        short = baselines.brute_words(rows, a.accepts, a.steps, 0, 3)
        assert short <= baselines.brute_reach(rows, a, 0)
        assert baselines.brute_reach(rows, a, 0) == baselines.brute_reach(rows, to_nfa(e), 0)
        assert all((u in baselines.brute_reach(rows, a.reverse(), 0)) == (0 in baselines.brute_reach(rows, a, u)) for u in range(1, 8))


def test_expression_algebra(spark):
    g, e = graph(spark, HUB), parse_pattern("(c|g)(d|e)*")
    for how in ({}, {"eager": False}, {"kernel": "shared"}, {"restrict": False}, {"restrict": False, "reorder": False}):
        assert ends(exalg_reach(g, e, source=10, **how)) == [1, 2, 3, 9] and ends(exalg_reach(g, e, target=9, **how)) == [10, 11, 12]
    assert ends(exalg_reach(g, e, source=10, target=9, reorder=False)) == [9] and ends(exalg_reach(g, e, source=10, target=12)) == []
    formed = []
    exalg_reach(g, parse_pattern("(c|g)(d|e)*"), target=9, reorder=False, algebra=formed)
    assert "^c|^g" in formed[0].formed  # the dense part away from the fixed end is formed whole
    with pytest.raises(ValueError, match="fixed end"):
        exalg_reach(g, e)


def test_product_order():
    cost, plan = product_order([Size(1000, 1000, 10), Size(1000, 10, 1000), Size(5, 5, 5)])
    assert plan == [0, [1, 2]] and cost > 0
    assert product_order([Size(5, 5, 5), Size(1000, 5, 1000), Size(10**6, 1000, 1000)])[1] == [[0, 1], 2]
    assert estimate(parse_pattern("a b"), {"a": (10, 10, 5), "b": (20, 4, 20)}).n == 40


def test_baselines(spark):
    g, a = graph(spark, STEP), dfa("a* b")
    assert pairs(baselines.indexed_reach(g, a, [3, 7])) == [(3, 4), (3, 5), (7, 3)]
    assert pairs(baselines.subset_reach(g, parse_pattern("a* b"), [3])) == [(3, 4), (3, 5)]
    assert ends(baselines.recursive_sql_reach(spark, g, a, 3, 6)) == [4, 5]
    with pytest.raises(baselines.NotExpressible):
        baselines.subset_reach(g, parse_pattern("(a b)*"), [3])


def test_extensions(spark):
    g = graph(spark, RARE)
    assert pairs(extensions.rare_label_reach(g, parse_pattern("p+ r p"), [1])) == [(1, 5)]
    assert pairs(extensions.rare_label_reach(g, parse_pattern("r p"), [3])) == [(3, 5)] and pairs(extensions.rare_label_reach(g, parse_pattern("p+"), [4])) == [(4, 5)]
    g, a = graph(spark, DIAMOND), dfa("p p")
    assert [tuple(r) for r in extensions.distance_reach(g, a, [1]).collect()] == [(1, 4, 2)]
    assert [tuple(r) for r in extensions.count_shortest(g, a, [1]).collect()] == [(1, 4, 2, 2)]
    path = extensions.witness_reach(g, a, [1]).collect()
    assert len(path) == 1 and [tuple(s) for s in path[0]["path"]] in ([("p", 0, 2), ("p", 0, 4)], [("p", 0, 3), ("p", 0, 4)])
    assert sorted(tuple(r["path"]) for r in extensions.simple_paths(g, dfa("p+"), [1], 3).collect()) == [(1, 2), (1, 2, 4), (1, 3), (1, 3, 4)]
    for ratio in (0.0, 0.5, 10.0):
        assert ends(extensions.push_pull_reach(graph(spark, HUB), dfa("(c|g)(d|e)*"), 10, ratio)) == [1, 2, 3, 9]
    for method in ("rare_label", "exalg", "hybrid", None):
        assert ends(extensions.auto_reach(graph(spark, RARE), parse_pattern("p+ r p"), 1, method)) == [5]


def test_cleaning(spark):
    g = graph(spark, STEP)
    rows = evaluate.clean_workload(g, [("one", "a", 3, None), ("two", "b", None, 5), ("three", "a", None, None), ("four", "a", 999, None), ("five", "zzz", 3, None)]).collect()
    assert {r["query"]: r["reason"] for r in rows} == {"one": "", "two": "", "three": "no fixed end", "four": "missing vertex", "five": "missing label" if rows[4]["reason"] != "missing vertex" else "missing vertex"}
    found = spark.createDataFrame([(1, 1), (2, 2), (2, 3), (4, 5)], "seed long, v long")
    assert pairs(evaluate.drop_trivial(found, True)) == [(2, 2), (2, 3), (4, 5)] and evaluate.drop_trivial(found, False) is found


def test_time_limit(spark):
    import time

    slow = lambda: spark.range(10**12).selectExpr("sum(id % 7) as x")
    assert evaluate.run_with_limit(spark, slow, 1, "slow").status == "timeout"

    def between():  # the limit passes while no job runs: the next one is cancelled
        spark.range(3).count()
        time.sleep(1.2)
        return slow()

    def late():  # no job before the limit, and a short one after it
        time.sleep(0.7)
        return spark.range(3)

    began = time.perf_counter()
    assert evaluate.run_with_limit(spark, between, 1, "between").status == "timeout" and time.perf_counter() - began < 30
    assert evaluate.run_with_limit(spark, late, 0.5, "late").status == "timeout"
    good = evaluate.run_with_limit(spark, lambda: spark.range(5), 60, "good")
    assert (good.status, good.n) == ("ok", 5)
    assert evaluate.run_with_limit(spark, lambda: spark.range(5).select("none"), 60, "bad").status == "error"
    assert evaluate.time_methods(spark, {"x": lambda: spark.range(3)}, times=1)["x"].n == 3
    rows = evaluate.timings(spark, [("a", "q", "g", lambda: spark.range(3)), ("a", "r", "g", lambda: spark.range(3).select("none"))], 60).collect()
    assert [(r["system"], r["query"], r["status"]) for r in rows] == [("a", "q", "ok"), ("a", "r", "error")]


def line(n):
    return [("d", i, i + 1) for i in range(n)]


@pytest.mark.parametrize("method", METHODS)
def test_many_join_levels(spark, monkeypatch, method):
    from pathloom.operators import levels

    monkeypatch.setattr(levels, "MOST_PIECES", 4)
    g = graph(spark, line(14))
    g.table = g.table.persist()
    assert ends(reach.traverse(g, dfa("d*"), [0], method, 3, literal_cap=0).answers()) == list(range(15))
    monkeypatch.setattr(reach, "KNOWN_CAP", 5)  # leaves the literal regime on the way
    found = reach.traverse(g, dfa("d*"), [0], method, 3)
    assert ends(found.answers()) == list(range(15)) and {x.regime for x in found.plan.trace} == {"literal", "join"}
    g.table.unpersist()


def test_trace_and_other_loops_over_many_levels(spark, monkeypatch):
    from pathloom.operators import levels

    monkeypatch.setattr(levels, "MOST_PIECES", 4)
    g = graph(spark, line(12))
    g.table = g.table.persist()
    rows = reach.trace_reach(g, dfa("d*"), [0], literal_cap=0).collect()
    assert sorted((r["level"], r["v"]) for r in rows) == [(i, i) for i in range(13)]
    assert pairs(baselines.indexed_reach(g, dfa("d+"), [0, 5])) == [(0, i) for i in range(1, 13)] + [(5, i) for i in range(6, 13)]
    assert pairs(baselines.subset_reach(g, parse_pattern("d+"), [3])) == [(3, i) for i in range(4, 13)]
    assert ends(exalg_reach(g, parse_pattern("d+"), source=2)) == list(range(3, 13))
    assert [r["dist"] for r in extensions.distance_reach(g, dfa("d+"), [0]).orderBy("v").collect()] == list(range(1, 13))
    assert [len(r["path"]) for r in extensions.witness_reach(g, dfa("d+"), [0]).orderBy("v").collect()] == list(range(1, 13))
    assert ends(extensions.push_pull_reach(g, dfa("d*"), 0)) == list(range(13))
    g.table.unpersist()


def test_long_walks_take_few_levels(spark, monkeypatch):
    from pathloom.operators import walks
    from pathloom.plans import exalg

    for module in (reach, bitmask, baselines, exalg):
        monkeypatch.setattr(module, "LONG", 4)
    steps = []
    monkeypatch.setattr(walks.Jumps, "closure", lambda self, *a, f=walks.Jumps.closure: steps.append(1) or f(self, *a))
    rows = line(40) + [("d", 100 + i, 100 + (i + 1) % 30) for i in range(30)] + [("e", i, 1000 + i % 3) for i in range(40)] + [("c", 500, 0), ("c", 500, 105), ("e", 1001, 1002)]
    g = graph(spark, rows)
    g.table = g.table.persist()
    a, want = dfa("c d* e+"), [1000, 1001, 1002]
    assert sorted(baselines.brute_reach(rows, a, 500)) == want
    for method, cap in (("frontier", 0), *((m, 1000) for m in METHODS)):
        found = reach.traverse(g, a, [500], method, literal_cap=cap)
        assert ends(found.answers()) == want and len(found.plan.trace) < 12 and any(x.regime == "walk" for x in found.plan.trace)
        assert found.known.size == 1 + 41 + 30 + 3
    whole = dfa("c d*")
    for cap in (0, 1000):
        steps.clear()
        assert ends(bitmask.bitmask_reach(g, a, [500], literal_cap=cap)) == want and steps
    steps.clear()
    assert pairs(baselines.indexed_reach(g, dfa("d* e"), [7, 110])) == sorted((7, v) for v in want) and steps
    steps.clear()
    assert ends(exalg_reach(g, parse_pattern("d+"), source=110)) == list(range(100, 130)) and steps
    assert len(reach.level_counts(g, whole, [500])) == 42  # levels are counted one by one
    assert not walks.Jumps(graph(spark, [("a", 1, 2), ("a", 1, 3)]).edges("a")).single()
    g.table.unpersist()


def test_a_task_follows_long_walks(spark, monkeypatch):
    from pathloom.operators import walks

    edges = [(i, i + 1) for i in range(300)] + [(1000, 150), (1001, 1000)] + [(2000 + i, 2000 + (i + 1) % 7) for i in range(7)]  # a line, a branch into it, a ring
    after = dict(edges)
    starts = [(1, 0), (1, 290), (2, 1001), (3, 2003), (4, 300), (5, 9999), *((100 + i, i) for i in range(90))]

    def reached(v):
        out = set()
        while v is not None and v not in out:
            out.add(v)
            v = after.get(v)
        return out

    want = sorted({(s, w) for s, v in starts for w in reached(v)})
    rows = spark.createDataFrame([*starts, starts[0]], "seed long, v long")
    made = []
    monkeypatch.setattr(walks, "written", lambda *a, f=walks.written: made.append(1) or f(*a))
    for most, share, copies, tables in ((10**6, 64, 8, 2), (10**6, 7, 8, 2), (1000, 64, 100, 2), (100, 64, 8, 18), (10**6, 1, 0, 18)):  # the last two by jump tables
        monkeypatch.setattr(walks, "FOLLOWED", most)
        monkeypatch.setattr(walks, "SHARE", share)
        monkeypatch.setattr(walks, "COPIES", copies)
        made.clear()
        jumps = walks.Jumps(spark.createDataFrame(edges, "src long, dst long"))
        found, n = jumps.closure(rows, ["seed"])
        assert pairs(found) == want and n == len(want) and (len(made) <= 2) == (tables == 2), (most, share, copies)
        assert jumps.closure(rows.filter("false"), ["seed"])[1] == 0
    a = dfa("p f+ d*")  # f and d have single successors; the frontier after the first levels holds the state of d alone
    g = graph(spark, [("p", 0, 1), ("f", 1, 2), *(("d", i, i + 1) for i in range(2, 40))])
    asked = []
    monkeypatch.setattr(walks.Jumps, "single", lambda self, f=walks.Jumps.single: asked.append(self) or f(self))
    assert ends(reach.frontier_reach(g, a, [0])) == list(range(2, 41)) and len(set(asked)) == 1


def test_the_driver_follows_walks_of_its_rows(spark, monkeypatch):
    from pathloom.operators import walks

    rows = [*line(1500), *(("d", 5000 + i, 5000 + (i + 1) % 40) for i in range(40)), ("c", 9000, 0), ("c", 9000, 5003), ("e", 1499, 7000), ("e", 5020, 7001)]
    g, made, want = graph(spark, rows), [], [7000, 7001]
    g.table = g.table.persist()
    for module in (reach, bitmask, walks):
        monkeypatch.setattr(module, "written", lambda *a, f=module.written: made.append(1) or f(*a))

    def answers():
        for method in METHODS:
            found = reach.traverse(g, dfa("c d* e"), [9000], method)
            yield ends(found.answers()), found.known.size, len(found.plan.trace) <= 6
        yield ends(bitmask.bitmask_reach(g, dfa("c d* e"), [9000])), None, True

    size = 1 + 1501 + 40 + 2
    assert list(answers()) == [*[(want, size, True)] * len(METHODS), (want, None, True)] and not made  # no level of 1500, and no table
    assert pairs(reach.hybrid_reach(g, dfa("d+"), [1400, 5001])) == [(1400, v) for v in range(1401, 1501)] + [(5001, v) for v in range(5000, 5040)] and not made
    monkeypatch.setattr(walks, "WALKED", 1000)  # more than the driver takes: tasks follow them
    assert [x[:2] for x in answers()] == [*[(want, size)] * len(METHODS), (want, None)] and made
    monkeypatch.setattr(walks, "WALKED", 10**6)
    for module in (reach, bitmask):
        monkeypatch.setattr(module, "KNOWN_CAP", 1000)  # the driver follows them, and tables take what they give
    assert [x[:2] for x in answers()] == [*[(want, size)] * len(METHODS), (want, None)]
    g.table.unpersist()


def test_walks_that_end_a_traversal_stay_on_the_driver(spark, monkeypatch):
    from pathloom.operators import walks

    rows = [*line(1500), *(("d", 5000 + i, 5000 + (i + 1) % 40) for i in range(40)), ("c", 9000, 0), ("c", 9000, 5003), ("d", 9001, 1400)]
    g, made, want = graph(spark, rows), [], [*range(1, 1501), *range(5000, 5040)]
    g.table = g.table.persist()
    for module in (reach, bitmask, walks, levels):
        monkeypatch.setattr(module, "written", lambda *a, f=module.written: made.append(1) or f(*a))
    for module in (reach, bitmask):
        monkeypatch.setattr(module, "KNOWN_CAP", 1000)  # fewer than the walks give, which nothing follows
    for method in METHODS:
        found = reach.traverse(g, dfa("c d+"), [9000], method)
        assert ends(found.answers()) == want and found.known.size == 1 + 2 + len(want)
    assert ends(bitmask.bitmask_reach(g, dfa("c d+"), [9000])) == want and not made
    assert ends(reach.frontier_reach(g, dfa("c d* ^d"), [9000])) == sorted({*range(1500), *range(5000, 5040), 9001}) and made  # here more steps follow
    g.table.unpersist()


def test_tables_follow_walks_from_the_second_level(spark, monkeypatch):
    rows = [*line(1500), ("c", 9000, 0), ("e", 1499, 7000)]
    g, asked = graph(spark, rows), []
    g.table = g.table.persist()
    monkeypatch.setattr(type(g), "passed", lambda self, steps: asked.append(sorted(x for x, _ in steps)) or self.hops(steps))
    found = reach.traverse(g, dfa("c d* e"), [9000], "frontier", literal_cap=0)
    assert ends(found.answers()) == [7000] and found.known.size == 1 + 1501 + 1 and len(found.plan.trace) <= 6
    assert ["d", "e"] in asked and not any("c" in x for x in asked[1:])  # a level reads the labels that its states take
    asked.clear()
    assert ends(bitmask.bitmask_reach(g, dfa("c d* e"), [9000], literal_cap=0)) == [7000] and len(asked) <= 5
    g.table.unpersist()


def test_the_driver_asks_for_a_vertex_once(spark, monkeypatch):
    g, asked = graph(spark, [("a", 1, 2), ("a", 2, 3), ("b", 3, 4), ("b", 2, 5)]), []
    monkeypatch.setattr(type(g), "passed", lambda self, steps: asked.append(sorted(steps)) or self.hops(steps))
    assert ends(reach.saturate_reach(g, dfa("a a b"), [1])) == [4] and asked == [[("a", 0)], [("a", 0)], [("b", 0)]]
    monkeypatch.setattr(levels, "FETCH_CAP", 1)  # what was fetched is dropped and looked up again
    assert ends(reach.saturate_reach(g, dfa("a a b"), [1])) == [4] and ends(reach.saturate_reach(g, dfa("a (a|b)"), [1])) == [3, 5]


def test_index_copies_the_directions_walked(spark, monkeypatch):
    rng = random.Random(8)
    rows = list({("abc"[i % 3], rng.randrange(12), 10**14 * rng.randrange(3) + rng.randrange(12)) for i in range(60)})
    g, copies = graph(spark, rows), []
    monkeypatch.setattr(baselines, "written", lambda df, name, *a, f=baselines.written, **how: (copies.append(f(df, name, *a, **how)) if name == "by-vertex" else None) or (copies[-1] if name == "by-vertex" else f(df, name, *a, **how)))
    for text, held in (("a b*", [0]), ("(^a)+", [0, 1]), ("a (^b|c)*", [0, 1])):
        a = dfa(text)
        assert pairs(baselines.indexed_reach(g, a, range(12))) == sorted((s, v) for s in range(12) for v in baselines.brute_reach(rows, a, s))
        assert [c.select("inv").distinct().collect()[0][0] for c in copies] == held and all(c.count() == len(rows) for c in copies)
    monkeypatch.setattr(baselines, "SPANS", 0)  # levels read whole copies
    assert pairs(baselines.indexed_reach(g, dfa("a b*"), [3])) == sorted((3, v) for v in baselines.brute_reach(rows, dfa("a b*"), 3))


def test_many_seeds_share_rows_in_the_comparison_methods(spark, monkeypatch):
    from pathloom.plans import exalg

    taken = []
    for module in (baselines, exalg):
        monkeypatch.setattr(module, "SEEDS", 4)
        monkeypatch.setattr(module, "packed_levels", lambda known, new, step, keys, f=module.packed_levels: taken.append(new.count()) or f(known, new, step, keys))
    rng = random.Random(5)
    rows = list({("ab"[i % 2], rng.randrange(20), rng.randrange(20)) for i in range(70)})
    g, seeds = graph(spark, rows), spark.createDataFrame([(i,) for i in range(70)], "v long")
    for text in ("(a b)*", "(a b)+"):
        a = dfa(text)
        want = sorted((s, v) for s in range(70) for v in baselines.brute_reach(rows, a, s))
        assert pairs(baselines.indexed_reach(g, a, seeds)) == want
        assert pairs(exalg.exalg_pairs(g, parse_pattern(text), seeds)) == want
    assert taken == [70] * 4


def test_batches(spark, monkeypatch):
    monkeypatch.setattr(bitmask, "SEEDS", 4)
    g = graph(spark, line(10))
    seeds = spark.createDataFrame([(i,) for i in range(9)], "v long").repartition(3)
    want = [(i, j) for i in range(9) for j in range(i + 1, 11)]
    assert pairs(bitmask.batch_reach(g, dfa("d+"), seeds)) == want
    blocks = bitmask.numbered_blocks(seeds).collect()
    assert sorted((r["block"], r["bit"]) for r in blocks) == [(i // 4, i % 4) for i in range(9)]
    assert pairs(bitmask.batch_reach(g, dfa("d+"), seeds.limit(0))) == []


def test_tables_of_a_run_are_deleted(spark):
    import os

    from pathloom.sources.store import scratch, shared_folder

    folder = shared_folder(spark).removeprefix("file://")
    before = set(os.listdir(folder))
    with scratch(spark):
        assert ends(reach.frontier_reach(graph(spark, line(5)), dfa("d*"), [0], literal_cap=0)) == list(range(6))
        assert set(os.listdir(folder)) > before
    assert set(os.listdir(folder)) == before
    g = graph(spark, line(3))
    for _ in range(2):  # what a graph keeps outlives the run that made it
        with scratch(spark):
            assert pairs(baselines.indexed_reach(g, dfa("d+"), [0])) == [(0, 1), (0, 2), (0, 3)]


def test_reordering_with_a_fixed_end(spark):
    # From one seed a fans out to 60 vertices with 20 ends each; c takes one of all those ends on, so the products are cheapest from the far end.
    rows = [("a", 0, 100 + i) for i in range(60)] + [("b", 100 + i, 1000 + 20 * i + j) for i in range(60) for j in range(20)] + [("c", 1000, 1)]
    g = graph(spark, rows)
    orders = []
    for reorder in (True, False):
        work = []
        assert ends(exalg_reach(g, parse_pattern("a b c"), source=0, reorder=reorder, algebra=work)) == [1]
        assert ends(exalg_reach(g, parse_pattern("a b c"), target=1, reorder=reorder)) == [0]
        orders.append(work[0].orders[0])
    assert orders == [[0, [1, [2, 3]]], [[[0, 1], 2], 3]]
    assert ends(exalg_reach(g, parse_pattern("a* b* c*"), source=77)) == [77]
    from pathloom.plans.exalg import exalg_pairs

    seeds = spark.createDataFrame([(0,), (101,), (1000,), (None,)], "v long")
    assert pairs(exalg_pairs(g, parse_pattern("a? b? c"), seeds)) == [(0, 1), (1000, 1)]
    assert pairs(exalg_pairs(g, parse_pattern("a? b? c"), spark.createDataFrame([(1,)], "v long"), "target")) == [(1, 0), (1, 100), (1, 1000)]


@pytest.mark.parametrize("layout", ["pairs", "rows", "columns", "both", "quadtree"])
def test_evaluation_on_layouts(spark, layout):
    from pathloom.plans.measures import LaidOut

    g = LaidOut(graph(spark, HUB), layout)
    assert ends(exalg_reach(g, parse_pattern("(c|g)(d|e)*"), source=10)) == [1, 2, 3, 9] and ends(exalg_reach(g, parse_pattern("(c|g)(d|e)*"), target=9)) == [10, 11, 12]
    assert ends(reach.hybrid_reach(g, dfa("(c|g)(d|e)*"), [10])) == [1, 2, 3, 9] and ends(reach.hybrid_reach(g, dfa("^e ^d"), [9], literal_cap=0)) == [2]
    assert all(n > 0 for n in g.stored_bytes(["d", "e"]).values())
    assert ends(reach.hybrid_reach(g, dfa("zzz"), [10])) == []


def test_counters(spark):
    from pathloom.plans.measures import plan_counters

    g = graph(spark, line(30))
    found = plan_counters(spark, lambda: reach.frontier_reach(g, dfa("d d"), [0], literal_cap=0).collect())
    assert found["queries"] > 2 and found["join_rows"] > 0
