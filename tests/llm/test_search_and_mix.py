import random

import numpy as np

from pathloom.llm import mixing, top_k

from .cases import docs

VEC = "vec_id long, embedding array<float>, rank int"


def brute(rows, k=5):
    fine = [(i, np.floor(256 * np.array(v, np.float64)).astype(int).astype(object)) for i, v in rows if i is not None and v and all(x is not None and np.isfinite(x) for x in v)]
    out = set()
    for q, a in fine:
        if q % 50 == 0:
            near = sorted((-int(a @ b), i) for i, b in fine if i != q and len(a) == len(b))[:k]
            out |= {(q, r, i, -s) for r, (s, i) in enumerate(near, 1)}
    return out


def test_top_k_is_exact(spark, monkeypatch):
    rng = np.random.default_rng(3)
    rows = [(i, [float(np.float32(x)) for x in rng.normal(0, 0.2, 16)]) for i in range(700)]
    rows[10] = (10, rows[11][1])  # ties
    rows += [(None, rows[0][1]), (800, None), (850, []), (801, [1.0, None] + [0.0] * 14), (802, [float("nan")] * 16), (803, [float("inf")] * 16), (900, [1.0, 2.0])]
    df = spark.createDataFrame([(i, v, 1) for i, v in rows], VEC)
    for cells, queries in ((64 * 16, 4), (1 << 21, 256)):
        monkeypatch.setattr(top_k, "CELLS", cells)
        monkeypatch.setattr(top_k, "QUERIES", queries)
        got = {tuple(r) for r in top_k.top_k(df, df.filter("vec_id % 50 = 0")).collect()}
        assert got == brute(rows)


def test_search_stops_on_proof():
    rng = np.random.default_rng(1)
    rows = rng.integers(-100, 100, (3000, 8)).astype(float)
    rows[:50] *= 3
    index, read, rescored = top_k.ImpactIndex(np.arange(3000), rows), [], []
    for q in range(0, 3000, 171):
        ids, scores = index.search(rows[q], q, 5)
        read.append(index.read), rescored.append(index.rescored)
        s = (rows @ rows[q]).astype(int)
        want = [i for i in np.lexsort((np.arange(3000), -s)) if i != q][:5]
        assert ids.tolist() == want and scores.tolist() == s[want].tolist()
    assert max(read) < len(index.segments) and np.mean(read) < 0.8 * len(index.segments) and max(rescored) <= 5 * top_k.FEW


def test_search_prunes_the_given_vectors():
    import pyarrow.parquet as pq

    table = pq.read_table("/root/testdata/sf0.01/embeddings.parquet")
    rows = np.floor(256 * np.array(table["embedding"].to_pylist(), float))
    ids = table["vec_id"].to_numpy()
    index, few, early = top_k.ImpactIndex(ids, rows), 0, 0
    for q in np.flatnonzero(ids % 50 == 0):
        index.search(rows[q], int(ids[q]), 5)
        few += index.rescored <= 5 * top_k.FEW
        early += index.read < len(index.segments)
        assert index.rescored < len(rows) // 2
    assert few == early == np.count_nonzero(ids % 50 == 0)


def test_large_components(spark):
    rng = np.random.default_rng(8)
    rows = [(i, [float(np.float32(x)) for x in rng.normal(0, 30000, 4)]) for i in range(60)]
    rows += [(100, [3000000.0, 0.0, 0.0, 1.0]), (150, [0.0, 2.0**30, 0.0, -1.0]), (101, [2.0**22, -(2.0**21), 1.0, 0.0])]
    df = spark.createDataFrame([(i, v, 1) for i, v in rows], VEC)
    got = {tuple(r) for r in top_k.top_k(df, df.filter("vec_id % 50 = 0")).collect()}
    assert got == brute(rows) and {100, 150} <= {r[0] for r in got}
    far = spark.createDataFrame([(0, [2.0**70, 1.0], 1), (1, [1.0, -5.0], 1), (2, [0.0, 7.0], 1)], VEC)
    try:
        top_k.top_k(far, far.filter("vec_id = 0")).collect()
        raise AssertionError
    except Exception as e:  # a member's score does not fit
        assert "beyond 64 bits" in str(e)
    near = far.filter("vec_id <> 1")
    assert [tuple(r) for r in top_k.top_k(near, near.filter("vec_id = 0")).collect()] == [(0, 1, 2, 256 * 256 * 7)]


def test_repeated_queries_and_ids(spark):
    df = spark.createDataFrame([(0, [1.0], 1), (0, [-1.0], 1), (7, [0.5], 1), (7, [0.25], 1)], VEC)
    got = sorted(map(tuple, top_k.top_k(df, df.filter("vec_id = 0"), 2).collect()))
    assert got == sorted([(0, 1, 7, 256 * 128), (0, 2, 7, 256 * 64), (0, 1, 7, -256 * 64), (0, 2, 7, -256 * 128)])


def test_few_candidates(spark):
    df = spark.createDataFrame([(0, [1.0], 1), (50, [0.5], 1)], VEC)
    assert sorted(map(tuple, top_k.top_k(df, df).collect())) == [(0, 1, 50, 256 * 128), (50, 1, 0, 256 * 128)]
    assert top_k.top_k(df.limit(0), df.limit(0)).count() == 0


def test_blocks_are_small_and_copied_for_few_parts(spark):
    """A block is one row that is sorted and shuffled once for each part of the queries: its bytes, and the parts, bound an executor's memory."""
    rng = np.random.default_rng(4)
    df = spark.createDataFrame([(i, [float(np.float32(x)) for x in rng.normal(0, 0.2, 8)], 1) for i in range(400)], VEC)
    block = top_k._packed(top_k._ready(df, "vec_id", "embedding").coalesce(1), 256, "block").first()
    assert len(block["values"]) + len(block["order"]) == 400 * 8 * 4 and len(block["ids"]) == 400 * 8
    assert top_k._parts(12_300, 19, 6) == 2 and top_k._parts(1_026, 2, 6) == 5 and top_k._parts(82_000, 100, 6) == 6 and top_k._parts(0, 1, 6) == 1
    values = np.array([[-32768.0, 32767.0], [0.0, 1.0]])
    assert [top_k.narrowest(values * x).dtype for x in (1, 2, 2.0**20)] == [np.int16, np.int32, np.float64]


def fill(sizes, weights, share):
    """Targets by sharing again and again."""
    target, left, free = {}, share * sum(sizes.values()), dict(sizes)
    while free:
        level = left / sum(weights[s] for s in free)
        full = [s for s in free if level * weights[s] > 2 * sizes[s]]
        if not full:
            return target | {s: level * weights[s] for s in free}
        for s in full:
            target[s] = 2.0 * free.pop(s)
            left -= target[s]
    return target


def test_targets_equal_repeated_sharing(spark):
    for seed in range(6):
        rng = random.Random(seed)
        sizes = {f"s{i:02d}": rng.choice((0, 1, 50, 1000, 20000)) * rng.randrange(1, 9) for i in range(rng.randrange(1, 14))}
        sizes[None] = 77
        order = sorted(sizes, key=lambda s: (s is None, s or ""))
        weights = {s: (5, 2, 1)[i % 3] for i, s in enumerate(order)}
        rows = spark.createDataFrame([(s, n) for s, n in sizes.items()], "source string, size long")
        got = {r["source"]: r["target"] for r in mixing.source_targets(rows).collect()}
        want = fill(sizes, weights, 1.5)
        assert all(abs(got[s] - want[s]) < 1e-6 * max(1, want[s]) for s in sizes), seed


def test_mix(spark):
    rng = random.Random(5)
    rows = [(i, "w " * rng.randrange(1, 200), "en", rng.choice("abcd"), i, 0.0, 1) for i in range(3000)]
    d = docs(spark, rows)
    report = {r["doc_id"]: r for r in mixing.mix_report(d).collect()}
    assert {r["doc_id"]: tuple(r) for r in mixing.mix_report(d.repartition(7)).collect()} == {i: tuple(r) for i, r in report.items()}
    taken, target = {}, {}
    for i, text, _, s, *_ in rows:
        r = report[i]
        assert r["size"] == len(text.split()) and r["taken"] in (0, r["size"], 2 * r["size"])
        taken[s], target[s] = taken.get(s, 0) + r["taken"], r["target"]
    assert all(abs(taken[s] / target[s] - 1) < 0.1 for s in target)
    copies = {r["doc_id"]: r["count"] for r in mixing.mix(d).groupBy("doc_id").count().collect()}
    assert {i: r["taken"] // r["size"] for i, r in report.items() if r["taken"]} == copies and mixing.mix(d).columns == d.columns


def test_mix_of_odd_rows(spark):
    got = mixing.mix_report(docs(spark)).collect()
    assert len(got) == docs(spark).count() and {r["size"] for r in got if r["doc_id"] in (1, 2, 3)} == {0} and all(r["taken"] <= 2 * r["size"] for r in got)
    assert mixing.mix_report(docs(spark, [])).count() == 0
