"""Triple files and edge tables on disk: reading, dictionaries for vertex names, and layouts that queries read without moving edges."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .graph import EdgeTable, LabeledGraph, dictionary

#: subject, predicate, object of one line: names in angle brackets, blank nodes, or literals; other lines are comments.
_NT_LINE = r'^\s*(<[^>]*>|_:\S+)\s+(<[^>]*>)\s+(<[^>]*>|_:\S+|"(?:[^"\\]|\\.)*"\S*)\s*\.\s*$'


def read_delimited(spark: SparkSession, path: str, sep: str = "\t") -> DataFrame:
    """subject, predicate, object of a text file of three columns."""
    return spark.read.schema("subject string, predicate string, object string").option("sep", sep).csv(path)


def read_ntriples(spark: SparkSession, path: str) -> DataFrame:
    """subject, predicate, object without angle brackets; lines that are no triple are left out."""
    part = lambda i: F.regexp_replace(F.regexp_extract("value", _NT_LINE, i), "^<|>$", "")
    rows = spark.read.text(path).select(*(part(i).alias(n) for i, n in ((1, "subject"), (2, "predicate"), (3, "object"))))
    return rows.filter("predicate <> ''")


def numbered(triples: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Edges (label, src, dst) and the dictionary (value, key) of a table (subject, predicate, object)."""
    names = triples.select(F.col("subject").alias("value")).unionAll(triples.select("object"))
    known = dictionary(F.col("value"), names)
    edges = triples.join(known.select(F.col("value").alias("subject"), F.col("key").alias("src")), "subject").join(known.select(F.col("value").alias("object"), F.col("key").alias("dst")), "object")
    return edges.select(F.col("predicate").alias("label"), "src", "dst").distinct(), known


def save_by_label(graph: LabeledGraph, path: str, labels=None) -> None:
    """One folder for each label, rows sorted by src: scans read the labels of a query, and filters on src skip row groups."""
    graph.triples(labels).repartitionByRange("label", "src").sortWithinPartitions("label", "src").write.mode("overwrite").partitionBy("label").option("parquet.bloom.filter.enabled#src", "true").parquet(path)


def load_by_label(spark: SparkSession, path: str) -> EdgeTable:
    """A saved graph. Saved edges are distinct."""
    return EdgeTable(spark.read.schema("src long, dst long, label string").parquet(path), distinct=False)


class BucketedGraph(LabeledGraph):
    """A graph in two tables of one row an edge, bucketed and sorted by src and by dst. A traversal joins each step on the vertex alone, so
    only the frontier is shuffled, into the tables' buckets."""

    def __init__(self, spark: SparkSession, out_table: str, in_table: str, labels: Iterable[str]):
        self.spark, self.out_table, self.in_table, self._labels = spark, out_table, in_table, sorted(labels)

    def labels(self) -> list[str]:
        return self._labels

    def edges(self, label: str) -> DataFrame:
        return self.spark.table(self.out_table).filter(F.col("label") == label).select("src", "dst")

    def step_tables(self, steps: Iterable[tuple[str, int]]) -> list[tuple[tuple[str, int], DataFrame]]:
        """For each step its edges (src, dst) in the direction of the step, read from the copy that is bucketed by src."""
        turned = lambda label: self.spark.table(self.in_table).filter(F.col("label") == label).select(F.col("dst").alias("src"), F.col("src").alias("dst"))
        return [((label, inv), turned(label) if inv else self.edges(label)) for label, inv in steps]


def save_bucketed(graph: LabeledGraph, name: str, buckets: int, labels=None, folder: str | None = None) -> BucketedGraph:
    """Two tables, name_out and name_in, bucketed and sorted by src and by dst; in a folder if one is given, else in the warehouse."""
    rows = graph.triples(labels)
    for table, key in ((f"{name}_out", "src"), (f"{name}_in", "dst")):
        out = rows.repartition(buckets, key).write.mode("overwrite").format("parquet").bucketBy(buckets, key).sortBy(key)
        (out.option("path", f"{folder}/{table}") if folder else out).saveAsTable(table)
    return BucketedGraph(graph.spark, f"{name}_out", f"{name}_in", graph.labels() if labels is None else labels)
