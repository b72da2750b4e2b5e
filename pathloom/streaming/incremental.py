"""Answers of a registered query that grow as edges arrive."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.automaton import Automaton
from ..operators.levels import KEYS, TRIPLE, Plan, Seen
from ..sources.graph import EDGE, EdgeTable
from ..sources.store import new_path, written


class GrowingQuery:
    """Known (seed, q, v) pairs over an append-only edge table; each batch of edges extends the pairs from where the new edges touch them.

    State is two folders of Parquet, appended to batch by batch under the batch's number, so a batch that runs again replaces its own rows.
    """

    def __init__(self, spark: SparkSession, automaton: Automaton, seeds, folder: str | None = None):
        self.spark, self.automaton = spark, automaton
        self.folder = folder or new_path(spark, "growing")
        start = [(int(s), q, int(s), -1) for s in seeds for q in sorted(automaton.starts)]
        spark.createDataFrame(start, TRIPLE + ", batch long").write.partitionBy("batch").parquet(f"{self.folder}/pairs")

    def _read(self, name: str, schema: str, before: int | None = None) -> DataFrame:
        try:
            df = self.spark.read.schema(schema + ", batch long").parquet(f"{self.folder}/{name}")
        except Exception as e:
            if "PATH_NOT_FOUND" not in str(e):
                raise
            df = self.spark.createDataFrame([], schema + ", batch long")
        return df if before is None else df.filter(F.col("batch") < before)

    def _replace(self, df: DataFrame, name: str, batch: int) -> None:
        df.write.mode("overwrite").parquet(f"{self.folder}/{name}/batch={batch}")

    def add(self, edges: DataFrame, batch: int) -> None:
        """Take in a batch (label, src, dst); for foreachBatch."""
        old = self._read("edges", EDGE, batch).select("label", "src", "dst")
        fresh = written(edges.select("label", "src", "dst").distinct().join(old, ["label", "src", "dst"], "left_anti"), "fresh")
        self._replace(fresh, "edges", batch)
        labels = {x for x, _ in self.automaton.steps}
        whole = Plan(EdgeTable(self._read("edges", EDGE).filter(F.col("batch") <= batch).drop("batch"), labels, distinct=False), self.automaton)
        arrived = Plan(EdgeTable(fresh, labels, distinct=False), self.automaton)
        known = self._read("pairs", TRIPLE, batch).select(KEYS)
        grown = Seen()
        new, n = grown.new(arrived.step(known).join(known, KEYS, "left_anti"), "grown")
        first = new
        while n:
            new, n = grown.new(whole.step(new, n).join(known, KEYS, "left_anti"), "grown")
        self._replace(grown.df() if grown.size else first, "pairs", batch)

    def answers(self) -> DataFrame:
        """seed, v."""
        return self._read("pairs", TRIPLE).filter(F.col("q").isin(sorted(self.automaton.finals))).select("seed", "v").distinct()

    def run(self, stream: DataFrame, checkpoint: str):
        """Start a streaming query over a stream (label, src, dst)."""
        return stream.writeStream.foreachBatch(self.add).option("checkpointLocation", checkpoint).start()


def edge_stream(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    """Edges from Parquet files as they arrive in a folder."""
    return spark.readStream.schema(EDGE).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def first_arrivals(stream: DataFrame, delay: str = "10 minutes") -> DataFrame:
    """The stream (label, src, dst, ts) without repeats of an edge within the delay: edges are a set."""
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["label", "src", "dst"])
