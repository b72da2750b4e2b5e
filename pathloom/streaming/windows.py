"""Windows over the stream of events: counts of acted edges, sessions, and degrees kept as state."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

EVENT = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def timed(events: DataFrame) -> DataFrame:
    """Events with ts as a point in time (UTC); watermarks need one."""
    return events.withColumn("ts", F.to_timestamp(F.to_utc_timestamp(F.col("ts").cast("timestamp"), "UTC")))


def event_stream(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    return timed(spark.readStream.schema(EVENT).option("maxFilesPerTrigger", files_per_batch).parquet(path))


def tumbling(events: DataFrame, width: str = "1 hour", delay: str = "10 minutes") -> DataFrame:
    """begin, n_edges, n_users of each window; rows later than the delay are left out of a stream."""
    w = events.withWatermark("ts", delay) if events.isStreaming else events
    users = F.approx_count_distinct("user_id") if events.isStreaming else F.countDistinct("user_id")
    return w.groupBy(F.window("ts", width)).agg(F.count("*").alias("n_edges"), users.alias("n_users")).select(F.col("window.start").alias("begin"), "n_edges", "n_users")


def sliding(events: DataFrame, width: str = "1 hour", step: str = "30 minutes", delay: str = "10 minutes") -> DataFrame:
    """begin, n_edges of overlapping windows."""
    w = events.withWatermark("ts", delay) if events.isStreaming else events
    return w.groupBy(F.window("ts", width, step)).agg(F.count("*").alias("n_edges")).select(F.col("window.start").alias("begin"), "n_edges")


def sessions(events: DataFrame, gap: str = "30 minutes", delay: str = "10 minutes") -> DataFrame:
    """user_id, begin, until, n_edges of each user's sessions."""
    w = events.withWatermark("ts", delay) if events.isStreaming else events
    found = w.groupBy("user_id", F.session_window("ts", gap).alias("s")).agg(F.count("*").alias("n_edges"))
    return found.select("user_id", F.col("s.start").alias("begin"), F.col("s.end").alias("until"), "n_edges")


class OutDegree(StatefulProcessor):
    """Distinct ends of each source vertex, kept as state; one row a batch for each source with new ends."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.ends = handle.getMapState("ends", "dst long", "seen int")
        self.count = handle.getValueState("count", "n long")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        n = self.count.get()[0] if self.count.exists() else 0
        before = n
        for part in rows:
            for dst in part["dst"].unique().tolist():
                if not self.ends.containsKey((dst,)):
                    self.ends.updateValue((dst,), (1,))
                    n += 1
        if n != before:
            self.count.update((n,))
            yield pd.DataFrame({"src": [key[0]], "n": [n]})

    def close(self) -> None:
        pass


def out_degrees(edges: DataFrame) -> DataFrame:
    """src, n as it grows, for a stream (label, src, dst)."""
    return edges.groupBy("src").transformWithStateInPandas(OutDegree(), "src long, n long", outputMode="Update", timeMode="None")
