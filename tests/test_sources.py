from pathloom.operators.levels import Plan
from pathloom.operators.reach import hybrid_reach, reverse_reach
from pathloom.operators.relation import compose, relation
from pathloom.sources import triples
from pathloom.sources.graph import GivenTables, dictionary, given_graph
from pyspark.sql import functions as F

from .conftest import SF
from .graphs import HUB, dfa, ends, graph

#: Edges of each label at scale factor 0.001.
COUNTS = {
    "bulk_supply": 513, "sourced_from": 1877, "located": 7345, "adjacent": 25, "within": 25, "ordered_by": 1500, "resident_of": 150, "placed": 1500, "has_item": 4599, "of_part": 5996, "made_by": 200, "of_type": 200,
    "succ_part": 175, "follows": 1350, "in_segment": 150, "has_priority": 1500, "acted": 1000, "then": 985, "event_kind": 1000, "is_customer": 15, "reply": 67, "links": 279, "on_host": 50, "from_source": 200, "in_lang": 200,
    "same_text": 21, "quotes": 3, "near": 1500, "in_class": 500,
}


def test_label_counts(spark):
    g = given_graph(spark, SF)
    assert {r["label"]: r["n"] for r in g.label_stats().collect()} == COUNTS and sum(COUNTS.values()) == 32925


def test_dictionary_is_dense_and_ordered(spark):
    df = spark.createDataFrame([(f"w{i % 57:03d}",) for i in range(500)] + [(None,)], "x string").repartition(7)
    got = sorted(map(tuple, dictionary(F.col("x"), df).collect()))
    assert got == [(f"w{i:03d}", i + 1) for i in range(57)]


def test_save_and_load(spark, tmp_path):
    path = f"file://{tmp_path}/g"
    triples.save_by_label(graph(spark, HUB), path)
    back = triples.load_by_label(spark, path)
    assert sorted(map(tuple, back.triples().collect())) == sorted(HUB)
    plan = back.edges("c").filter("src = 10")._jdf.queryExecution().toString()
    assert "PartitionFilters: [isnotnull(label" in plan and "PushedFilters: [IsNotNull(src), IsNotNull(dst), EqualTo(src,10)]" in plan.replace("GreaterThan", "") or "EqualTo(src,10)" in plan


def test_bucketed_traversal_moves_no_edges(spark, tmp_path):
    g = triples.save_bucketed(graph(spark, HUB), "hub_edges", 4, folder=f"file://{tmp_path}/b")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        p = Plan(g, dfa("(c|g)(d|e)*"))
        text = p.step(p.rows([(1, 0, 10)]))._jdf.queryExecution().executedPlan().toString()
        assert text.count("SortMergeJoin") == 4 and text.count("Exchange hashpartitioning(v") == 4 and "Exchange hashpartitioning(src" not in text and text.count("SelectedBucketsCount") == 4
        assert ends(hybrid_reach(g, dfa("(c|g)(d|e)*"), [10], literal_cap=0)) == [1, 2, 3, 9]
        assert ends(reverse_reach(g, dfa("(c|g)(d|e)*"), [9], literal_cap=0)) == ends(reverse_reach(g, dfa("(c|g)(d|e)*"), [9])) == [10, 11, 12]
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def test_step_broadcasts_transitions_and_prunes_labels(spark, tmp_path):
    path = f"file://{tmp_path}/g"
    triples.save_by_label(graph(spark, HUB), path)
    p = Plan(triples.load_by_label(spark, path), dfa("(c|g)(d|e)*"))
    text = p.step(p.rows([(1, 0, 10)]))._jdf.queryExecution().toString()
    assert "BroadcastHashJoin" in text and "PartitionFilters" in text and "CartesianProduct" not in text


def test_product_has_partial_distinct(spark):
    a = relation(graph(spark, HUB).edges("d"))
    text = compose(a, a)._jdf.queryExecution().executedPlan().toString()
    assert text.count("HashAggregate") >= 2


def test_ntriples_and_numbers(spark, tmp_path):
    (tmp_path / "t.nt").write_text('# comment\n<a> <p> <b> .\n<b> <q> "lit \\" x"@en .\n_:n <p> <a> .\nbroken line\n')
    t = triples.read_ntriples(spark, f"file://{tmp_path}/t.nt")
    assert t.count() == 3
    edges, names = triples.numbered(t)
    assert edges.count() == 3 and names.count() == 4


def test_literal_regime_reads_one_label(spark):
    g = given_graph(spark, SF)
    assert len(ends(Plan(g, dfa("within")).step(Plan(g, dfa("within")).rows([(1, 0, 2 * 10**14 + 3)])))) == 1


def test_quotes_and_near_on_odd_rows(spark, tmp_path):
    docs = ["a b c d", "x a b c y", " b ", "a  b", "", None, "b", "ab c", "the cat sat on", "cat  sat on mat", "\u00e9 \u00fc \u00f1 \u00f6"]
    items = ["a b c", "b", "a b", "", " b ", "  ", "at sat o", "cat sat on", "zz cat sat", None, "\u00e9 \u00fc \u00f1", "a  b"]
    vectors = [[(i * k) % 3 - 1.0 for k in (1, 2, 5, 7)] for i in range(40)]  # many ties
    vectors[4], vectors[6] = None, [1.0, 0.5, 0.25, 2.0]
    for name, rows, schema in (
        ("documents", list(enumerate(docs)), "doc_id long, text string"), ("benchmark", list(enumerate(items)), "item_id long, text string"), ("embeddings", list(enumerate(vectors)), "vec_id long, embedding array<float>"),
    ):
        spark.createDataFrame(rows, schema).write.parquet(f"{tmp_path}/{name}.parquet")
    g = GivenTables(spark, str(tmp_path), keep=False)
    quotes = g.edges("quotes")
    got = sorted((r["src"] - 14 * 10**14, r["dst"] - 19 * 10**14) for r in quotes.collect())
    assert got == [(i, j) for i, d in enumerate(docs) for j, x in enumerate(items) if d is not None and x is not None and x in d]
    assert "array_intersect" in quotes._jdf.queryExecution().optimizedPlan().toString()
    unit = {i: [x / max(sum(y * y for y in v) ** 0.5, 1e-300) for x in v] for i, v in enumerate(vectors) if v is not None}
    like = {(i, j): round(sum(x * y for x, y in zip(unit[i], unit[j], strict=True)), 6) for i in unit for j in unit if i != j}
    near = g.edges("near")
    got = sorted((r["src"] - 17 * 10**14, r["dst"] - 17 * 10**14) for r in near.collect())
    assert got == sorted((i, j) for i in unit for j in sorted((j for j in unit if j != i), key=lambda j: (-like[i, j], j))[:3])
    assert "RepartitionByExpression [block" in near._jdf.queryExecution().optimizedPlan().toString()


def test_plain_labels_are_scanned_before_they_are_kept(spark):
    from pathloom.sources.graph import PASSES

    g, whole = GivenTables(spark, SF), GivenTables(spark, SF)
    for steps in ([("bulk_supply", 1)], [("bulk_supply", 1), ("placed", 0), ("succ_part", 0)], [("bulk_supply", 1)] * 2):
        assert sorted(map(tuple, g.passed(steps).distinct().collect())) == sorted(map(tuple, whole.hops(set(steps)).collect()))
    assert "bulk_supply" not in g._kept and "succ_part" in g._kept
    for _ in range(PASSES):
        g.passed([("bulk_supply", 1)])
    assert "bulk_supply" in g._kept and "placed" not in g._kept
    g.close()
    whole.close()


def _odd_tables(spark, folder):
    """Keys that are null, repeated or negative, so that a vertex's number falls among those of other kinds; brands that are null, empty or beyond ASCII."""
    for name, rows, schema in (
        ("part", [(i, ["b", "a", "", None, "é", "\U0001f600"][i % 6]) for i in (*range(-9, 30), 4, 4)] + [(None, "a")], "p_partkey long, p_brand string"),
        ("orders", [(i, i % 4 - 1 if i % 5 else None) for i in (*range(-6, 20), 3)], "o_orderkey long, o_custkey long"),
        ("lineitem", [(i % 9 - 3, i % 7 - 2 if i % 8 else None, n) for i in range(40) for n in (1, 7, 9, -20, 2**31 - 1)], "l_orderkey long, l_partkey long, l_linenumber int"),
    ):
        spark.createDataFrame(rows, schema).repartition(3).write.parquet(f"{folder}/{name}.parquet")


def test_lookups_with_conditions_on_keys(spark, tmp_path):
    _odd_tables(spark, tmp_path)
    whole = GivenTables(spark, str(tmp_path))
    for label in ("placed", "ordered_by", "has_item", "of_part", "made_by"):
        for inv in (0, 1):
            edges = sorted({(r["src"], r["dst"]) for r in whole.hops([(label, inv)]).collect()})
            sources = {v for v, _ in edges[::2]} | {v for v, _ in edges[:2]} | {5, -(1 << 63), (1 << 63) - 1}
            g = GivenTables(spark, str(tmp_path))
            found = g.looked_up(label, inv, sources)
            assert label not in g._kept and {(r["src"], r["dst"]) for r in found.collect()} == {x for x in edges if x[0] in sources}, (label, inv)
    plan = GivenTables(spark, str(tmp_path)).looked_up("placed", 0, [3 * 10**14 + 1])._jdf.queryExecution().executedPlan().toString()
    assert "EqualTo(o_custkey,1)]" in plan  # of the scan
    whole.close()


def test_few_names_are_numbered_on_the_driver(spark, tmp_path, monkeypatch):
    from pathloom.sources import graph as module

    _odd_tables(spark, tmp_path)
    made, found = [], []
    monkeypatch.setattr(module, "dictionary", lambda *a, f=module.dictionary: made.append(1) or f(*a))
    for few, longest, tables in ((100, 1000, 0), (4, 1000, 1), (100, 3, 2)):
        monkeypatch.setattr(module, "FEW", few)
        monkeypatch.setattr(module, "LONGEST", longest)
        g = GivenTables(spark, str(tmp_path))
        found.append(sorted(map(tuple, g.edges("made_by").collect())))
        assert len(made) == tables
        g.close()
    assert found[0] == found[1] == found[2] and {b - 20 * 10**14 for _, b in found[0]} == {1, 2, 3, 4, 5}


def test_sequences_come_to_the_driver_at_once(spark, tmp_path, monkeypatch):
    from pathloom.functions.automaton import compile_expr
    from pathloom.functions.expr import parse_pattern
    from pathloom.operators import bitmask, reach, walks
    from pathloom.sources import graph as module

    _odd_tables(spark, tmp_path)
    first, answers = 5 * 10**14 + 1, []
    for text, seed in (("succ_part*/made_by", first), ("succ_part+ made_by+", first), ("(^succ_part)+", first + 18), ("has_item of_part+ succ_part+", 6 * 10**14 + 2)):
        a = compile_expr(parse_pattern(text))
        for bytes_ in (1 << 25, 0):  # 0: the label is kept and counted first
            monkeypatch.setattr(module, "BROUGHT", bytes_)
            for run in (lambda g: reach.hybrid_reach(g, a, [seed]), lambda g: reach.saturate_reach(g, a, [seed]), lambda g: bitmask.bitmask_reach(g, a, [seed])):
                g = GivenTables(spark, str(tmp_path))
                asked = []
                g.passed = lambda steps, where=None, f=g.passed, asked=asked: asked.append(steps) or f(steps, where)
                answers.append((text, sorted(map(tuple, run(g).collect()))))
                assert (("succ_part" in g._kept) == (not bytes_)) and (not bytes_ or len(asked) <= 5), (text, asked)
                g.close()
    by_text = {text: [rows for t, rows in answers if t == text] for text, _ in answers}
    assert all(rows == own[0] and rows for own in by_text.values() for rows in own)
    twice = walks.Jumps(None)
    twice.take(*(walks.np.array(x) for x in zip(*[(1, 2), (2, 3), (1, 2), (2, 3)], strict=True)))
    assert twice.size == 2 and twice.single() and twice.ends([3, 2, 1], 2) == [(2, 3), (1, 2)] and twice.ends([1, 2], 1) is None
