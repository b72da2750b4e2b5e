import datetime as dt

from pathloom.operators import reach
from pathloom.sources.graph import EDGE
from pathloom.streaming import incremental, windows

from .graphs import HUB, dfa, ends, graph, pairs


def test_growing_answers(spark, tmp_path):
    a = dfa("(c|g)(d|e)*")
    q = incremental.GrowingQuery(spark, a, [10, 12], f"file://{tmp_path}/g")
    parts = [HUB[4:], HUB[:2] + HUB[5:6], HUB[2:4]]
    for i, rows in enumerate(parts):
        q.add(spark.createDataFrame(rows, EDGE), i)
    q.add(spark.createDataFrame(parts[2], EDGE), 2)  # a batch that runs again
    assert pairs(q.answers()) == pairs(reach.hybrid_reach(graph(spark, HUB), a, [10, 12]))


def test_edge_stream(spark, tmp_path):
    a = dfa("(c|g)(d|e)*")
    for i in range(3):
        spark.createDataFrame(HUB[i::3] + HUB[:1], EDGE).coalesce(1).write.parquet(f"file://{tmp_path}/in/{i}")
    q = incremental.GrowingQuery(spark, a, [10])
    s = spark.readStream.schema(EDGE).option("maxFilesPerTrigger", 1).parquet(f"file://{tmp_path}/in/*")
    run = s.writeStream.foreachBatch(q.add).option("checkpointLocation", f"{tmp_path}/c").trigger(availableNow=True).start()
    run.awaitTermination()
    assert ends(q.answers()) == [1, 2, 3, 9]


def events(spark, minutes):
    t0 = dt.datetime(2024, 1, 1)
    return spark.createDataFrame([(i, t0 + dt.timedelta(minutes=m), 1, "x", 1.0, "{}") for i, m in enumerate(minutes)], windows.EVENT)


def test_late_rows_are_left_out(spark, tmp_path):
    for i, minutes in enumerate(([5, 50, 65, 130], [10], [200])):
        events(spark, minutes).coalesce(1).write.mode("append").parquet(f"file://{tmp_path}/e")
        s = windows.event_stream(spark, f"file://{tmp_path}/e")
        run = windows.tumbling(s).writeStream.format("parquet").option("path", f"file://{tmp_path}/o").option("checkpointLocation", f"file://{tmp_path}/c").outputMode("append").trigger(availableNow=True).start()
        run.awaitTermination()
    rows = {r["begin"].hour: r["n_edges"] for r in spark.read.parquet(f"file://{tmp_path}/o").collect()}
    assert rows[0] == 2 and rows[1] == 1  # minute 10 came after the watermark had passed hour 0


def test_batch_windows(spark):
    e = windows.timed(events(spark, [5, 50, 65, 130, 140]))
    assert sorted(r["n_edges"] for r in windows.tumbling(e).collect()) == [1, 2, 2]
    assert sum(r["n_edges"] for r in windows.sliding(e).collect()) == 10
    assert sorted(r["n_edges"] for r in windows.sessions(e).collect()) == [1, 2, 2]


def test_repeats_and_degrees_in_streams(spark, tmp_path):
    t0 = dt.datetime(2024, 1, 1)
    rows = [("a", 1, 2, t0), ("a", 1, 2, t0), ("a", 1, 3, t0)]
    spark.createDataFrame(rows, "label string, src long, dst long, ts timestamp").coalesce(1).write.parquet(f"file://{tmp_path}/in")
    s = spark.readStream.schema("label string, src long, dst long, ts timestamp").parquet(f"file://{tmp_path}/in")
    run = incremental.first_arrivals(s).writeStream.format("memory").queryName("firsts").trigger(availableNow=True).option("checkpointLocation", f"file://{tmp_path}/c").start()
    run.awaitTermination()
    assert spark.table("firsts").count() == 2


def test_degrees_as_state(spark, tmp_path):
    """Distinct ends by source, kept in the state store; repeats change nothing."""
    for i, rows in enumerate(([("a", 1, 2), ("a", 1, 3), ("a", 2, 3)], [("a", 1, 2), ("a", 2, 4)])):
        spark.createDataFrame(rows, EDGE).coalesce(1).write.mode("append").parquet(f"file://{tmp_path}/in")
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        found = windows.out_degrees(incremental.edge_stream(spark, f"file://{tmp_path}/in"))
        rows = {}
        run = found.writeStream.foreachBatch(lambda df, _: rows.update((r["src"], r["n"]) for r in df.collect())).outputMode("update").option("checkpointLocation", f"file://{tmp_path}/c").trigger(availableNow=True).start()
        run.awaitTermination()
        assert rows == {1: 2, 2: 2}
    finally:
        spark.conf.unset("spark.sql.streaming.stateStore.providerClass")
