import random
from collections import Counter

import numpy as np
import pytest

from pathloom.llm import decontaminate, ngram_join
from pathloom.llm.words import Words, encoded, shingle_sets

from .cases import corpus, docs, edited, prose


def brute_classes(rows, k, num):
    """doc_id to (size, component, links) by comparing all pairs."""
    sets = []
    for i, text in rows:
        w = (text or "").encode().lower().split()
        sets.append((i, {tuple(w[j : j + k]) for j in range(len(w) - k + 1)} if len(w) >= k else {tuple(w)} if w else set()))
    label, links = {i: i for i, _ in sets}, Counter()
    ok = [(i, s) for i, s in sets if s and i is not None]
    edges = [(i, j) for a, (i, s) in enumerate(ok) for j, t in ok[:a] if 100 * len(s & t) >= num * len(s | t)]
    for i, j in edges:
        links[i] += 1
        links[j] += 1
    changed = True
    while changed:
        changed = False
        for i, j in edges:
            low = min(label[i], label[j])
            if label[i] != low or label[j] != low:
                label[i] = label[j] = low
                changed = True
    return {i: (len(s), label[i], links[i]) for i, s in sets}


def as_docs(spark, rows):
    return docs(spark, [(i, t, "en", "s", 0, 0.0, 0) for i, t in rows])


@pytest.mark.parametrize(("k", "num", "seed"), [(3, 90, 1), (5, 80, 2)])
def test_classes_against_all_pairs(spark, monkeypatch, k, num, seed):
    monkeypatch.setattr(ngram_join, "MEMBERS", 4)
    monkeypatch.setattr(ngram_join, "QUERIES", 3)
    rng = random.Random(seed)
    base = prose(rng, 120)
    chain = [base]
    for _ in range(6):
        chain.append(edited(rng, chain[-1], 1))
    rows = corpus(seed) + [(5000 - i, t) for i, t in enumerate(chain)] + [(1, ""), (2, None), (3, "one"), (4, "ONE"), (5, "two words"), (6, "two words"), (7, base + " " + base)]
    got = {r["doc_id"]: tuple(r)[1:] for r in ngram_join.jaccard_classes(as_docs(spark, rows).repartition(3), k, num).collect()}
    want = brute_classes(rows, k, num)
    assert got == want
    assert sum(c != i for i, (_, c, _) in want.items()) > 20
    plain = ngram_join.jaccard_classes(as_docs(spark, rows), k, num, count_links=False)
    assert plain.columns == ["doc_id", "n_shingles", "component_id"] and {r["doc_id"]: r["component_id"] for r in plain.collect()} == {i: c for i, (_, c, _) in want.items()}
    kept = ngram_join.one_of_each(as_docs(spark, rows), k, num)
    assert sorted(r["doc_id"] for r in kept.collect()) == sorted(i for i, (_, c, _) in want.items() if i == c) and kept.columns == as_docs(spark, rows).columns


@pytest.mark.parametrize(("size", "edits", "k", "num"), [(60, 3, 5, 80), (25, 2, 3, 90), (150, 12, 5, 80)])
def test_one_large_family(spark, monkeypatch, size, edits, k, num):
    monkeypatch.setattr(ngram_join, "MEMBERS", 8)
    monkeypatch.setattr(ngram_join, "QUERIES", 8)
    monkeypatch.setattr(ngram_join, "PIVOTS", 3)
    rng = random.Random(size)
    base = prose(rng, size)
    rows = [(i, edited(rng, base, rng.randrange(edits + 1))) for i in range(150)] + [(1000 + i, t) for i, t in corpus(size, 2, 3, 5)]
    want = brute_classes(rows, k, num)
    assert {r["doc_id"]: tuple(r)[1:] for r in ngram_join.jaccard_classes(as_docs(spark, rows), k, num).collect()} == want
    assert {r["doc_id"]: r["component_id"] for r in ngram_join.jaccard_classes(as_docs(spark, rows), k, num, count_links=False).collect()} == {i: c for i, (_, c, _) in want.items()}


def test_odd_rows(spark):
    d = docs(spark)
    got = ngram_join.jaccard_classes(d).collect()
    assert len(got) == d.count()
    by = {}
    for r in got:
        by.setdefault(r["doc_id"], []).append(tuple(r)[1:])
    assert by[None][0][1:] == (None, 0) and by[1] == by[2][:1] or by[1][0][0] == 0
    assert [x[1] for x in by[4] + by[5]] == [4, 4] and by[6] == [(1, 6, 1), (1, 6, 1)] and by[8][0][0] == 2
    kept = sorted((r["doc_id"] is not None, r["doc_id"] or 0) for r in ngram_join.one_of_each(d).collect())
    assert [i for some, i in kept if some] == [1, 2, 3, 4, 6, 7, 8, 9] and kept[0][0] is False
    assert ngram_join.jaccard_classes(docs(spark, [])).count() == 0 and ngram_join.one_of_each(docs(spark, [])).count() == 0


def test_rows_of_one_id_and_other_texts(spark):
    rows = [(1, "a b c d e f g"), (1, "t u v w x y z"), (2, "t u v w x y z")]
    got = sorted(tuple(r)[:3] for r in ngram_join.jaccard_classes(as_docs(spark, rows)).collect())
    assert got == [(1, 5, 1), (1, 5, 1), (2, 5, 1)]


def test_one_of_each_with_several_texts_of_an_id(spark):
    a, b, c, d, e, f = ("a1 a2 a3 a4 a5", "b1 b2 b3 b4 b5", "c1 c2 c3 c4 c5", "d1 d2 d3 d4 d5", "e1 e2 e3 e4 e5", "f1 f2 f3 f4 f5")
    rows = [(1, a), (1, b), (2, b), (3, c), (5, c), (5, d), (5, d), (7, ""), (7, e), (7, ""), (8, e), (9, None), (4, f), (4, f.upper()), (4, f + " ")]
    kept = [sorted(((r["doc_id"], r["text"]) for r in ngram_join.one_of_each(as_docs(spark, x)).collect()), key=repr) for x in (rows, rows[::-1])]
    assert kept[0] == kept[1] and len(kept[0]) == 9
    assert [r for r in kept[0] if r[0] != 4] == [(1, a), (1, b), (3, c), (5, d), (7, ""), (7, ""), (7, e), (9, None)]


def test_groups_against_all_pairs():
    rng = random.Random(2)
    sets = [np.unique(np.array([rng.randrange(40) for _ in range(30)], np.uint64)) for _ in range(50)]
    q, g = ngram_join.TokenGroup(sets[:20]).links(sets[20:], 60, 100)
    want = {(a, b) for a, s in enumerate(sets[20:]) for b, t in enumerate(sets[:20]) if 100 * len(np.intersect1d(s, t)) >= 60 * len(np.union1d(s, t))}
    assert set(zip(q.tolist(), g.tolist(), strict=True)) == want and want


def test_components(spark):
    edges = [(1, 2), (2, 3), (10, 11), (3, 9), (20, 20)] + [(100 + i, 101 + i) for i in range(40)] + [(500, i) for i in range(501, 540)]
    got = {r["node"]: r["component"] for r in ngram_join.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert all(got[i] == 1 for i in (1, 2, 3, 9)) and got[11] == 10 and all(got[100 + i] == 100 for i in range(41)) and all(got[i] == 500 for i in range(500, 540)) and 20 not in got
    assert ngram_join.components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_words_and_shingles():
    texts = ["A b\tc", "", None, "é\u00a0x ÉX", "a  b\nc d"]
    w = Words([encoded(t) for t in texts])
    assert w.counts.tolist() == [3, 0, 0, 2, 4]
    h = w.hashes()
    assert h[0] == h[5] and h[2] == h[7] and len(set(h.tolist())) == 6
    a, _, none, _, b = shingle_sets(texts, 3)
    assert len(none) == 0 and len(b) == 2 and a[0] in b
    assert Words([b"abcdef", b"abcxyz"]).hashes(first=3).tolist()[0] == Words([b"abcxyz"]).hashes(first=3).tolist()[0]


ITEMS = "item_id long, text string, doc_id long"


def brute_leaks(doc, item):
    """Best weighted similarity of item-sized windows, with weights all equal (items without shared shingles)."""
    w, v = decontaminate.words_of(doc).split(), decontaminate.words_of(item).split()
    k = min(5, len(v))
    grams = lambda x: Counter(tuple(x[i : i + k]) for i in range(len(x) - k + 1))
    own, best = grams(v), 0.0
    for i in range(len(w) - len(v) + 1):
        there = grams(w[i : i + len(v)])
        best = max(best, sum((own & there).values()) / sum((own | there).values()))
    return best


def test_leaks_against_all_windows(spark):
    rng = random.Random(4)
    items = [(i, prose(rng, rng.randrange(14, 60)), 0) for i in range(12)] + [(50, "three short words", 0), (51, None, 0), (52, "  ", 0), (53, "word", 0)]
    texts = []
    for i in range(40):
        t = prose(rng, rng.randrange(0, 150)).split(" ")
        if i % 2:
            item = items[rng.randrange(12)][1].split(" ")
            if i % 4 == 1:
                item = edited(rng, " ".join(item), rng.choice((0, 1, 2))).split(" ")
            at = rng.randrange(len(t) + 1)
            t[at:at] = [x.upper() + "," for x in item] if i % 3 == 0 else item
        texts.append((i, " ".join(t)))
    texts += [(90, "so, THREE short... words!"), (91, ""), (92, None)]
    got = {(r["doc_id"], r["item_id"]): r["similarity"] for r in decontaminate.contaminated(as_docs(spark, texts), spark.createDataFrame(items, ITEMS)).collect()}
    want = {(d, i): s for d, t in texts for i, x, _ in items if x and decontaminate.words_of(x).split() and (s := brute_leaks(t, x)) >= 0.8}
    assert set(got) == set(want) and len(want) > 10 and all(abs(got[p] - want[p]) < 1e-9 for p in want)
    clean = decontaminate.drop_contaminated(as_docs(spark, texts), spark.createDataFrame(items, ITEMS))
    assert sorted(r["doc_id"] for r in clean.collect()) == sorted({d for d, _ in texts} - {d for d, _ in want})


def test_documents_shorter_than_the_item():
    rng = random.Random(8)
    items = [(i, prose(rng, n)) for i, n in enumerate((59, 30, 12, 6, 5, 59))]
    short = [(i, " ".join(x.split(" ")[a : len(x.split(" ")) - b])) for i, x in items for a in range(6) for b in range(12)] + [(9, "")]
    found = [{} for _ in short]
    for at, best in decontaminate.Benchmark(items).search([t for _, t in short]):
        found[at] = {item: value for item, (value, start) in best.items()}
    grams = lambda t: Counter(tuple(t.split()[i : i + 5]) for i in range(len(t.split()) - 4))
    for (_, t), got in zip(short, found, strict=True):
        want = {}
        for item, x in items:
            both, either = grams(t) & grams(x), grams(t) | grams(x)
            if either and sum(both.values()) / sum(either.values()) >= 0.8:
                want[item] = sum(both.values()) / sum(either.values())
        assert set(got) == set(want) and all(abs(got[i] - want[i]) < 1e-9 for i in want), t
    assert found[4] and 0.92 < found[4][0] < 0.93  # the first 55 of 59 words


def test_blocks_of_items(spark, monkeypatch):
    rng = random.Random(6)
    items = [(i, prose(rng, 20), 0) for i in range(30)]
    d, b = as_docs(spark, [(i, prose(rng, 10) + " " + t) for i, t, _ in items] + [(99, prose(rng, 50))]), spark.createDataFrame(items, ITEMS)
    monkeypatch.setattr(decontaminate, "ITEMS", 7)
    assert sorted((r["doc_id"], r["item_id"]) for r in decontaminate.contaminated(d, b).collect()) == [(i, i) for i in range(30)]
    assert [r["doc_id"] for r in decontaminate.drop_contaminated(d, b).collect()] == [99]
    assert decontaminate.contaminated(docs(spark, []), b).count() == 0 and decontaminate.contaminated(d, b.limit(0)).count() == 0 and decontaminate.drop_contaminated(docs(spark), b).count() == docs(spark).count()


def test_results_do_not_depend_on_blocks(spark, monkeypatch):
    rng = random.Random(9)
    common = prose(rng, 24)  # a passage that a third of the items share, so weights differ
    items = [(i, (common + " " + prose(rng, 16)) if i % 3 == 0 else prose(rng, 40), 0) for i in range(30)]
    items += [(100, items[5][1], 0), (101, items[5][1], 0)]  # equal texts
    rows = [(i, prose(rng, 8) + " " + edited(rng, t, i % 5) + " " + prose(rng, 8)) for i, t, _ in items[:30]]
    rows += [(200 + i, prose(rng, 5) + " " + common + " " + prose(rng, 20)) for i in range(5)]
    d, b = as_docs(spark, rows), spark.createDataFrame(items, ITEMS)
    results = []
    for size in (20_000, 7):
        monkeypatch.setattr(decontaminate, "ITEMS", size)
        got = sorted((r["doc_id"], r["item_id"], round(r["similarity"], 9), r["start_word"]) for r in decontaminate.contaminated(d, b).collect())
        results.append(got)
        assert sorted(r["doc_id"] for r in decontaminate.drop_contaminated(d, b).collect()) == sorted({i for i, _ in rows} - {r[0] for r in got})
    assert results[0] == results[1] and {(5, 5), (5, 100), (5, 101)} <= {r[:2] for r in results[0]}


def test_recall_where_items_share_shingles():
    rng = random.Random(21)
    shared = [prose(rng, 25) for _ in range(4)]
    items = [(i, " ".join(rng.sample([shared[i % 4], prose(rng, 35)], 2))) for i in range(40)]
    bench = decontaminate.Benchmark(items)
    assert len(set(np.round(bench.weights(bench.shingles[0]), 6).tolist())) > 1
    right = found = 0
    for _ in range(12):
        texts = [" ".join([prose(rng, 10), edited(rng, t, rng.randrange(0, 4)), prose(rng, 10)]) for _, t in items]
        got = dict(bench.search(texts))
        for at, text in enumerate(texts):
            h = Words([decontaminate.words_of(text)]).hashes()
            grams = decontaminate.chained(h, 5)
            for item in range(len(items)):
                n = bench.sizes[item] - 4
                best = max(bench.alike(grams[i : i + n], item) for i in range(max(0, 10 - 3), 14)) if item == at else 0
                if best >= 0.8:
                    right += 1
                    found += item in got.get(at, {})
    assert right > 100 and found >= 0.9 * right, (right, found)


def test_long_repeated_texts(monkeypatch):
    monkeypatch.setattr(decontaminate, "_WINDOWS", 64)
    monkeypatch.setattr(decontaminate, "_EXPANDED", 50)
    rng = random.Random(3)
    items = [(i, prose(rng, 30)) for i in range(5)]
    text = " ".join([items[2][1]] * 40 + [prose(rng, 200), items[4][1]])
    found = dict(decontaminate.Benchmark(items).search([text, prose(rng, 60)]))
    assert set(found) == {0} and found[0][2] == (1.0, 0) and found[0][4] == (1.0, 40 * 30 + 200)


def test_index_gives_all_within_the_radius():
    rng = np.random.default_rng(5)
    known = rng.integers(0, 2**64, (60, 2), np.uint64)
    asked = known[rng.integers(0, 60, 200)].copy()
    for row in asked:
        for bit in rng.choice(128, rng.integers(0, 60), replace=False).tolist():
            row[bit // 64] ^= np.uint64(1 << (bit % 64))
    far = np.bitwise_count(asked[:, None] ^ known[None]).sum(2)
    a, b = decontaminate.HammingIndex(known).near(asked)
    assert set(zip(a.tolist(), b.tolist(), strict=True)) == {tuple(x) for x in np.argwhere(far <= decontaminate.RADIUS).tolist()}
