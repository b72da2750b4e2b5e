import random

import corpus_pipeline

from .cases import docs, prose


def test_stages(spark, tmp_path):
    """Planted toxic texts, copies and benchmark passages go; clean documents stay until the mix."""
    rng, rows, labels = random.Random(9), [], []
    kind = {}
    for i in range(300):
        text = prose(rng, rng.randrange(40, 90))
        toxic = i % 5 == 0
        if toxic:
            text = " ".join(w if j % 9 else "scumbag" for j, w in enumerate(text.split(" ")))
        rows.append((i, text, "en", "abc"[i % 3], len(text)))
        kind[i] = "toxic" if toxic else "clean"
        labels.append((i, 1, int(toxic)))
    passages = [prose(rng, 40) for _ in range(5)]
    for i in range(5):
        rows.append((400 + i, prose(rng, 20) + " " + passages[i] + " " + prose(rng, 10), "en", "a", 0))
        kind[400 + i] = "leak"
        rows.append((500 + i, rows[5 * i + 1][1] + " more", "en", "b", 0))
        kind[500 + i] = "copy"
        rows.append((600 + i, rows[5 * i + 2][1], "en", None, 0))
        kind[600 + i] = "copy"
    rows += [(700, None, None, None, None), (701, "", "en", "a", 0), (None, prose(rng, 30), "en", "a", 0)]
    columns = "doc_id long, text string, lang string, source string, n_chars long"
    spark.createDataFrame(rows, columns).write.parquet(f"file://{tmp_path}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"file://{tmp_path}/labels.parquet")
    spark.createDataFrame(list(enumerate(passages)), "item_id long, text string").write.parquet(f"file://{tmp_path}/benchmark.parquet")
    d = f"file://{tmp_path}"
    now, seen = spark.read.parquet(f"{d}/documents.parquet"), []
    for name, stage in corpus_pipeline.STAGES[:4]:
        out = stage(spark, now, d)
        assert out.columns == ["doc_id", "text", "lang", "source", "n_chars"]
        path = f"{d}/{name}"
        out.write.parquet(path)
        now = spark.read.parquet(path)
        seen.append({r["doc_id"] for r in now.collect()})
    ids = lambda k: {i for i, x in kind.items() if x == k}
    assert not seen[0] & ids("toxic") and seen[0] >= (set(kind) - ids("toxic")) | {700, 701, None}
    assert not seen[1] & ids("copy") and seen[1] >= ids("clean") | ids("leak") | {700, 701, None}
    assert not seen[2] & ids("leak") and seen[2] >= ids("clean") | {700, 701, None}
    words = spark.read.parquet(f"{d}/benchmark decontamination").selectExpr("sum(coalesce(size(filter(split(text, ' '), w -> w <> '')), 0)) AS n").first()["n"]
    mixed = now.selectExpr("sum(size(split(text, ' '))) AS n").first()["n"]
    assert abs(mixed / words - 1.5) < 0.15
    report = corpus_pipeline.STAGES[4][1](spark, now, d)
    assert report.count() == now.count() and report.columns[:4] == ["doc_id", "start", "n_tokens", "ids_crc32"]
    full = corpus_pipeline.run(spark, d)
    assert sorted(map(repr, full.collect())) == sorted(map(repr, report.collect()))


def test_empty_corpus(spark, tmp_path):
    for name, schema in (("documents", "doc_id long, text string, lang string, source string, n_chars long"), ("labels", "doc_id long, quality int, toxic int"), ("benchmark", "item_id long, text string")):
        spark.createDataFrame([], schema).write.parquet(f"file://{tmp_path}/{name}.parquet")
    assert corpus_pipeline.run(spark, f"file://{tmp_path}").count() == 0


def test_odd_rows_pass_the_stages(spark, tmp_path):
    rows = docs(spark).select("doc_id", "text", "lang", "source", "n_chars")
    rows.write.parquet(f"file://{tmp_path}/documents.parquet")
    spark.createDataFrame([(4, 1, 0)], "doc_id long, quality int, toxic int").write.parquet(f"file://{tmp_path}/labels.parquet")
    spark.createDataFrame([(1, None)], "item_id long, text string").write.parquet(f"file://{tmp_path}/benchmark.parquet")
    assert corpus_pipeline.run(spark, f"file://{tmp_path}").count() > 0
