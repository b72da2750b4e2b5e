"""Boolean matrices as relations: a DataFrame (row, col) of distinct pairs, one for each entry that is 1."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.store import forget, written
from .levels import Seen

PAIR = "row long, col long"


def zero(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([], PAIR)


def relation(df: DataFrame, row: str = "src", col: str = "dst") -> DataFrame:
    return df.select(F.col(row).cast("long").alias("row"), F.col(col).cast("long").alias("col")).filter("row is not null and col is not null").distinct()


def transpose(a: DataFrame) -> DataFrame:
    return a.select(F.col("col").alias("row"), F.col("row").alias("col"))


def union(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.unionByName(b).distinct()


def compose(a: DataFrame, b: DataFrame) -> DataFrame:
    """Boolean product: pairs (i, k) with some j in both. Duplicates are merged before they are shuffled."""
    left, right = a.select("row", F.col("col").alias("_mid")), b.select(F.col("row").alias("_mid"), "col")
    return left.join(right, "_mid").select("row", "col").distinct()


def mask(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.join(b, ["row", "col"], "left_semi")


def mask_not(a: DataFrame, b: DataFrame) -> DataFrame:
    """The entries of a that b lacks; the complement of b is never formed."""
    return a.join(b, ["row", "col"], "left_anti")


def complement(a: DataFrame, rows: DataFrame, cols: DataFrame) -> DataFrame:
    """All entries of rows (v) x cols (v) that a lacks; for small domains."""
    return mask_not(rows.select(F.col("v").alias("row")).crossJoin(cols.select(F.col("v").alias("col"))), a)


def rows_of(a: DataFrame, vertices: DataFrame) -> DataFrame:
    """The entries of a whose row is in vertices (v)."""
    return a.join(vertices.select(F.col("v").alias("row")), "row", "left_semi").select("row", "col")


def vec_mul(vertices: DataFrame, a: DataFrame) -> DataFrame:
    """Boolean vector times matrix: the columns (v) that the vertices (v) reach."""
    return rows_of(a, vertices).select(F.col("col").alias("v")).distinct()


def identity(vertices: DataFrame) -> DataFrame:
    return vertices.select(F.col("v").alias("row"), F.col("v").alias("col"))


def nnz(a: DataFrame) -> int:
    return a.count()


def is_empty(a: DataFrame) -> bool:
    return a.isEmpty()


def equal(a: DataFrame, b: DataFrame) -> bool:
    return mask_not(a, b).isEmpty() and mask_not(b, a).isEmpty()


def closure(a: DataFrame, reflexive: DataFrame | None = None, method: str = "semi_naive", start: DataFrame | None = None) -> DataFrame:
    """Transitive closure of a, with the identity on the vertices reflexive (v) if given.

    semi_naive extends what was new in the last round by one step, and takes as many rounds as the longest shortest path; squaring
    joins the result with itself and takes the logarithm of that. With start (v) only rows of those vertices are formed (semi-naive).
    """
    base = written(a, "closure-base")
    if method == "squaring":
        if start is not None:
            raise ValueError("squaring forms all rows")
        known, n = base, base.count()
        while True:
            more = written(union(known, compose(known, known)), "closure")
            if known is not base:
                forget(known)
            known, before, n = more, n, more.count()
            if n == before:
                break
    elif method == "semi_naive":
        found = Seen(["row", "col"])
        new, n = found.new(base if start is None else rows_of(base, start), "closure")
        known = new
        while n:
            new, n = found.new(compose(new, base), "closure")
        known = found.df() if found.size else known
    else:
        raise ValueError(method)
    return known if reflexive is None else union(known, identity(reflexive))
