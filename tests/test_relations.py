import random

import pytest

from pathloom.operators import relation as rel
from pathloom.plans import measures

from .graphs import HUB, graph


def m(spark, pairs):
    return spark.createDataFrame(sorted(pairs), rel.PAIR)


def got(df):
    rows = [(r["row"], r["col"]) for r in df.collect()]
    assert len(rows) == len(set(rows))
    return set(rows)


A, B = {(1, 2), (2, 3)}, {(2, 1), (3, 3)}


def test_operations(spark):
    a, b = m(spark, A), m(spark, B)
    v = spark.createDataFrame([(1,), (2,), (3,)], "v long")
    assert got(rel.compose(a, b)) == {(1, 1), (2, 3)} and got(rel.union(a, b)) == A | B and got(rel.transpose(a)) == {(2, 1), (3, 2)}
    assert got(rel.mask(a, rel.transpose(a))) == set() and got(rel.mask_not(a, b)) == A
    assert len(got(rel.complement(a, v, v))) == 7
    for method in ("semi_naive", "squaring"):
        assert got(rel.closure(a, method=method)) == {(1, 2), (2, 3), (1, 3)}
    assert got(rel.closure(a, v)) == {(1, 2), (2, 3), (1, 3), (1, 1), (2, 2), (3, 3)}
    assert got(rel.closure(a, start=v.filter("v = 2"))) == {(2, 3)}
    assert rel.nnz(a) == 2 and rel.is_empty(rel.zero(spark)) and rel.equal(a, a) and not rel.equal(a, b)
    assert sorted(r["v"] for r in rel.vec_mul(v.filter("v < 3"), a).collect()) == [2, 3]
    with pytest.raises(ValueError, match="nothing"):
        rel.closure(a, method="nothing")


@pytest.mark.parametrize("case", range(4))
def test_laws(spark, case):
    rng = random.Random(case)
    one = lambda: {(rng.randrange(5), rng.randrange(5)) for _ in range(8)}
    x, y, z = one(), one(), one()
    a, b, c = m(spark, x), m(spark, y), m(spark, z)
    product = lambda p, q: {(i, k) for i, j in p for j2, k in q if j == j2}
    assert got(rel.compose(a, b)) == product(x, y)
    assert got(rel.compose(rel.compose(a, b), c)) == got(rel.compose(a, rel.compose(b, c))) == product(product(x, y), z)
    assert got(rel.transpose(rel.compose(a, b))) == got(rel.compose(rel.transpose(b), rel.transpose(a)))
    assert got(rel.mask(a, b)) == x & y and got(rel.mask_not(a, b)) == x - y
    long = {(i, i + 1) for i in range(12)}
    assert got(rel.closure(m(spark, long))) == {(i, j) for i in range(13) for j in range(i + 1, 13)}


def test_quadtree(spark):
    tree = measures.quadtree(m(spark, {(0, 0), (3, 3)}), 2)
    assert tree.count() * 4 == 12 and got(measures.quadtree_decode(tree, 2)) == {(0, 0), (3, 3)}
    rng = random.Random(3)
    x = {(rng.randrange(16), rng.randrange(16)) for _ in range(40)}
    assert got(measures.quadtree_decode(measures.quadtree(m(spark, x), 4), 4)) == x


def test_layouts(spark):
    g = graph(spark, HUB)
    back = measures.unpacked(measures.adjacency_out(g)).collect()
    assert sorted(map(tuple, back)) == sorted(HUB)
    foot = measures.footprint(g, "pairs").first()
    assert (foot["n_edges"], foot["bytes"], foot["bytes_per_triple"]) == (7, 112, 16.0)
    assert tuple(measures.graph_stats(g).first()) == (7, 7, 4)
    s = {r["label"]: tuple(r)[1:] for r in g.label_stats().collect()}
    assert s["c"] == (2, 2, 1) and s["e"] == (2, 2, 1)
    assert spark.range(1).select(measures.bytes_per_triple(*(__import__("pyspark.sql.functions", fromlist=["lit"]).lit(x) for x in (1630, 100)))).first()[0] == 16.3


def test_measures(spark):
    rows = [("ours", f"q{i}", "g", t, "ok") for i, t in enumerate((1.0, 3.0, 2.0))] + [("other", f"q{i}", "g", t, "ok") for i, t in enumerate((2.0, 6.0, 10.0))] + [("other", "q9", "g", 60000.0, "timeout")]
    t = spark.createDataFrame(rows, measures.TIMING)
    s = {r["system"]: r for r in measures.summarize(t).collect()}
    assert (s["ours"]["total_ms"], s["ours"]["mean_ms"], s["ours"]["median_ms"]) == (6, 2, 2) and (s["other"]["total_ms"], s["other"]["mean_ms"], s["other"]["median_ms"]) == (18, 6, 6)
    r = {x["system"]: x for x in measures.relative_speedup(t, "ours").collect()}["other"]
    assert round(r["mean_speedup"], 3) == round(r["median_speedup"], 3) == 0.333 and r["times_slower_mean"] == 3
    c = {(x["system"], x["status"]): x["n"] for x in measures.status_counts(t).collect()}
    assert c["other", "timeout"] == 1
    known = spark.createDataFrame([("q1", True), ("q9", True), ("q2", False)], "query string, expressible boolean")
    assert {x["query"]: x["grp"] for x in measures.classify(known, t).collect()} == {"q1": "simple", "q9": "complex", "q2": "complex"}
    assert measures.distribution(t).filter("system = 'ours'").first()["p50"] == 2
