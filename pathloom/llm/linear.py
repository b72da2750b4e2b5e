"""What the classifiers share: folds, the bounded sample of labelled texts, sparse online learning, scoring over all rows."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .store import lean, small_batches

#: A model learns from at most so many labelled rows, those of the smallest hash of the id. Models are bounded by their hash buckets.
SAMPLE, BUCKET_BITS = 12_000, 20
_ROWS = 128

#: A text's features: ascending bucket numbers and their values.
Sparse = tuple[np.ndarray, np.ndarray]


def held_out(doc_id: str = "doc_id") -> Column:
    """Rows that labels are never learnt from; false for a null id, which no label joins."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string")) % 5 == 0, F.lit(False))


def labelled_sample(docs: DataFrame, labels: DataFrame, target: str, bound: int = SAMPLE) -> DataFrame:
    """doc_id, text, y: at most bound labelled rows outside the held-out fold, those of the smallest hash. An id with several labels has the largest; rows
    that repeat an id and a text are one."""
    known = labels.filter(F.col("doc_id").isNotNull() & F.col(target).isNotNull()).groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max(target).cast("int").alias("y")).filter(~held_out())
    chosen = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(bound)  # a bounded number of rows, hence the broadcasts
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).join(F.broadcast(chosen), "doc_id")
    texts = texts.withColumn("_h", F.xxhash64("text"))
    few = texts.select("doc_id", "_h").distinct().orderBy(F.xxhash64("doc_id"), "doc_id", "_h").limit(bound)
    return texts.join(F.broadcast(few), ["doc_id", "_h"]).groupBy("doc_id", "_h").agg(F.first("text").alias("text"), F.first("y").alias("y")).select("doc_id", "text", "y")


class Ftrl:
    """Follow-the-regularised-leader with per-coordinate rates, an absolute and a squared penalty."""

    def __init__(self, buckets: int, rate: float, l1: float, l2: float, beta: float = 1.0):
        self.pull, self.squares = np.zeros(buckets), np.zeros(buckets)
        self.rate, self.l1, self.l2, self.beta = rate, l1, l2, beta

    def weights(self, at: np.ndarray | slice) -> np.ndarray:
        z = self.pull[at]
        return np.where(np.abs(z) <= self.l1, 0.0, -(z - np.sign(z) * self.l1) / ((self.beta + np.sqrt(self.squares[at])) / self.rate + self.l2))

    def step(self, at: np.ndarray, gradient: np.ndarray, weights: np.ndarray) -> None:
        squares = self.squares[at]
        more = squares + gradient * gradient
        self.pull[at] += gradient - (np.sqrt(more) - np.sqrt(squares)) / self.rate * weights
        self.squares[at] = more


def sigmoid(x: np.ndarray | float) -> np.ndarray | float:
    return 1 / (1 + np.exp(-np.clip(x, -35, 35)))


def model_of(sample: DataFrame, features: Callable[[list], list[tuple[Sparse, Sparse | None]]], fit: Callable[[list, np.ndarray], np.ndarray]) -> np.ndarray:
    """Weights by bucket. features gives each text's features and, or None, those of its twin. They are made where the texts are; one
    task learns from the bounded sample, in an order set by the ids. Features travel as 4-byte numbers and are read in place."""

    def featurise(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for at in range(0, len(batch), _ROWS):
                part = batch.iloc[at : at + _ROWS]
                found = features(part["text"].tolist())
                raw = lambda x, i, kind: None if x is None else x[i].astype(kind).tobytes()
                columns = {f"{name}{i}": [raw(f[j], i, kind) for f in found] for j, name in enumerate(("x", "twin")) for i, kind in enumerate((np.int32, np.float32))}
                yield pd.DataFrame({"doc_id": part["doc_id"].to_numpy(), "y": part["y"].to_numpy(), **columns})

    def learn(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        rows: list[tuple] = []
        for batch in batches:
            rows += zip(*(batch[c] for c in ("doc_id", "y", "x0", "x1", "twin0", "twin1")), strict=True)
        rows.sort(key=lambda r: r[:3])
        if rows:
            read = lambda at, value: None if at is None else (np.frombuffer(at, np.int32), np.frombuffer(value, np.float32))
            w = fit([(read(*r[2:4]), read(*r[4:])) for r in rows], np.array([r[1] for r in rows], float))
            at = np.flatnonzero(w)
            yield pd.DataFrame({"at": at.astype(np.int32), "w": w[at]})

    made = sample.mapInPandas(lean(featurise), "doc_id long, y int, x0 binary, x1 binary, twin0 binary, twin1 binary")
    rows = made.repartition(1).mapInPandas(lean(learn), "at int, w double").toPandas()
    out = np.zeros(1 << BUCKET_BITS, np.float32)
    out[rows["at"].to_numpy(int)] = rows["w"].to_numpy(np.float32)
    return out


def scored(docs: DataFrame, features: Callable[[list], list], weights: np.ndarray, keep: Callable[[np.ndarray], np.ndarray] | None = None) -> DataFrame:
    """docs with a column _score; with keep, only the rows whose scores it accepts (and no score), so that texts are moved nowhere."""
    small_batches(docs.sparkSession)
    columns = docs.columns
    at_text = columns.index("text")

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = []
            for at in range(0, batch.num_rows, _ROWS):
                found += [(weights[i] * v).sum() for i, v in features(batch.column(at_text).slice(at, _ROWS).to_pylist())]
            p = sigmoid(np.array(found, np.float64))
            if keep is not None:
                yield batch.filter(pa.array(keep(p)))
            else:
                yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(p)], [*columns, "_score"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema)
    return docs.mapInArrow(lean(score), schema if keep is not None else f"{schema}, _score double")
