import random
import zlib

import numpy as np

from pathloom.llm import quality, toxicity
from pathloom.llm.linear import Ftrl

from .cases import docs, prose

LABELS = "doc_id long, quality int, toxic int, text string"


def labelled(spark, n=400, seed=1):
    rng, rows, labels = random.Random(seed), [], []
    for i in range(n):
        words = prose(rng, rng.randrange(20, 120)).split(" ")
        toxic, good = rng.random() < 0.3, rng.random() < 0.7
        if toxic:
            for _ in range(3):
                words.insert(rng.randrange(len(words)), rng.choice(("idiot", "zulokar" + rng.choice("abc"), "zulo" + rng.choice(("mi", "ra", "tek")))))
        if not good:
            words = [w + rng.choice(("!!", "***", "$$$")) for w in words] if rng.random() < 0.5 else [words[0]] * len(words)
        rows.append((i, " ".join(words), "en", "s", 0, 0.0, 0))
        labels.append((i, int(good), int(toxic), "x"))
    return docs(spark, rows), spark.createDataFrame(labels, LABELS), labels


def held(i):
    return zlib.crc32(str(i).encode()) % 5 == 0


def test_held_out_accuracy(spark):
    d, lab, labels = labelled(spark)
    for run, at in ((quality.quality_scores, 1), (toxicity.toxicity_scores, 2)):
        got = {r["doc_id"]: r for r in run(d, lab).collect()}
        own = [x for x in labels if held(x[0])]
        assert all(got[x[0]]["held_out"] for x in own) and sum(r["held_out"] for r in got.values()) == len(own)
        assert np.mean([got[x[0]]["predicted"] == x[at] for x in own]) > 0.9, run
        again = {r["doc_id"]: r["score"] for r in run(d.repartition(5), lab.repartition(3)).collect()}
        assert again == {i: r["score"] for i, r in got.items()}


def test_held_out_labels_and_other_columns_are_not_used(spark):
    d, lab, labels = labelled(spark, 150)
    turned = spark.createDataFrame([(i, 1 - q if held(i) else q, 1 - t if held(i) else t, x) for i, q, t, x in labels], LABELS)
    other = d.selectExpr("doc_id", "text", "'zz' AS lang", "cast(doc_id as string) AS source", "n_chars", "_score", "token")
    for run in (quality.quality_scores, toxicity.toxicity_scores):
        want = sorted(map(tuple, run(d, lab).collect()))
        assert sorted(map(tuple, run(d, turned).collect())) == want and sorted(map(tuple, run(other, lab).collect())) == want


def test_filters_keep_columns_and_order_of_scores(spark):
    d, lab, _ = labelled(spark, 200)
    score = {r["doc_id"]: r["predicted"] for r in toxicity.toxicity_scores(d, lab).collect()}
    kept = toxicity.drop_toxic(d, lab)
    assert kept.columns == d.columns and {r["doc_id"] for r in kept.collect()} == {i for i, p in score.items() if p == 0}
    score = {r["doc_id"]: r["predicted"] for r in quality.quality_scores(d, lab).collect()}
    assert {r["doc_id"] for r in quality.keep_good(d, lab).collect()} == {i for i, p in score.items() if p == 1}


def test_odd_rows(spark):
    lab = spark.createDataFrame([(4, 1, 1, ""), (6, 0, 0, ""), (6, None, None, ""), (None, 1, 1, ""), (77, 1, 1, "")], LABELS)
    for run in (quality.quality_scores, toxicity.toxicity_scores):
        for labels in (lab, lab.limit(0)):
            got = run(docs(spark), labels).collect()
            assert len(got) == docs(spark).count() and all(0 <= r["score"] <= 1 for r in got)
        assert all(r["score"] == 0.5 for r in got) and run(docs(spark, []), lab).count() == 0
    assert toxicity.drop_toxic(docs(spark), lab.limit(0)).count() == docs(spark).count()


TERMS = (("zed", "yot"), ("Moor", "moss"))


def test_swapping():
    assert toxicity.swapped("A zed, and YOT.", TERMS) == "A yot, and zed." and toxicity.swapped("nothing zedd", TERMS) is None and toxicity.swapped("zed", ()) is None


def test_neutral_mentions_are_not_marked():
    """Insults mostly mention one group: without the penalty its name is itself held toxic."""
    rng, texts, y = random.Random(3), [], []
    for i in range(600):
        toxic = i % 2
        words = prose(rng, 25).split(" ")
        words.insert(3, "zed" if (rng.random() < 0.9) == bool(toxic) else "yot")
        if toxic and rng.random() < 0.8:
            words.insert(7, "idiot")
        texts.append(" ".join(words))
        y.append(float(toxic))
    neutral = [" ".join([*prose(rng, 12).split(" "), "zed", *prose(rng, 12).split(" ")]) for _ in range(100)]
    rows = toxicity.twin_features(texts, TERMS)

    def marked(strength):
        w = toxicity.fit(rows, np.array(y), strength)
        score = lambda t: np.array([w[i].sum() for i, _ in toxicity.features(t)])
        return (score(neutral) >= 0).mean(), (score([t for t in texts if "idiot" in t]) >= 0).mean(), np.abs(score(["zed"]) - score(["yot"]))[0]

    plain, fair = marked(0.0), marked(20.0)
    assert plain[0] > 0.5 and fair[0] < plain[0] / 2 and fair[1] > 0.9 and fair[2] < plain[2] / 2


def test_penalised_learning_is_sparse():
    f = Ftrl(4, 0.1, 1.0, 1.0)
    for _ in range(200):
        for at, y in ((np.array([0, 1]), 1.0), (np.array([0, 2]), 0.0)):
            w = f.weights(at)
            f.step(at, np.full(2, 1 / (1 + np.exp(-w.sum())) - y), w)
    w = f.weights(slice(None))
    assert w[1] > 0.5 and w[2] < -0.5 and w[3] == 0


def test_features():
    (a, v), (b, _), (none, _) = quality.features(["xx xx xx", "Aa *** 12", None])
    assert len(a) == len(v) and (v[1:] <= 4.01).all() and none.tolist() == [0] and len(b) > 5
    x = toxicity.features(["Hello, hello! HELLO", "", None])
    assert len(x[0][0]) == 4 and x[1][0].tolist() == x[2][0].tolist() == [0]
