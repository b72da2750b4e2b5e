"""Exact top-k inner products over an impact-ordered index, score at a time.

Vectors become integers, floor(scale x component) of the component as double. Data rows lie in blocks of at most CELLS components. The index of a block
is built once and stored with it. It keeps, for each dimension, segments: the rows whose component has the same quantised impact (component >> SHIFT),
each with its range of components. For a query a segment promises at most max(q * low, q * high) in its dimension; less the least that the dimension can
give, this is the segment's impact. Segments are processed by descending impact and add their promise to the rows they list. What a row can still
get from a dimension in which it was not met yet is at most the impact of the next segment. Processing stops
only on proof: when the rows whose bound reaches the k-th best exact score known in the block are at most FEW times k, those rows are
rescored exactly; rows under it can't be members. The known score comes from rescoring the leading rows, so the proof holds at any time.

A query set is paired with all data in blocks: every (data block, part of the queries) is one task's work, dealt by both numbers whatever its size in
bytes; then the block results are cut to k. A block is copied once for each part, so parts are as few as keep all cores busy, of QUERIES queries or more and
MOST at most, and blocks are stored in the narrowest whole numbers that hold them. Nothing that grows with the data lies in one task.

Defined results: vectors that are null, hold null or non-finite components, or are empty take no part, neither do rows without id. Any finite component
takes part: where sums of 64 bits might overflow, scores are whole numbers of any length, and a member's score beyond 64 bits raises OverflowError. Vectors
of another length than the query are no candidates. Equal scores go to the smaller id. Repeated ids are candidates each, but never their own query's;
repeated query rows get an answer each. Fewer than k candidates give fewer rows. Empty tables give an empty result. Other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

K, SCALE, EVERY = 5, 256, 50
CELLS, QUERIES, MOST, SHIFT, CHECK_EVERY, FEW = 1 << 21, 256, 1 << 14, 2, 128, 8
#: Tasks that the pairs of blocks are dealt to, at most.
MOST_TASKS = 1 << 12
#: Sums of products under this bound stay exact in 64 bits, with room for the counts beside them.
_SAFE = 2.0**45


def narrowest(values: np.ndarray) -> np.ndarray:
    """Whole numbers, given as doubles, in 2 or 4 bytes each where they fit."""
    low, high = values.min(initial=0.0), values.max(initial=0.0)
    for kind in (np.int16, np.int32):
        if np.iinfo(kind).min <= low and high <= np.iinfo(kind).max:
            return values.astype(kind)
    return values


def _places(n: int) -> type:
    """The numbers that the rows of a block are stored as."""
    return np.uint16 if n <= 1 << 16 else np.int32


class ImpactIndex:
    """Segments of one block of integer vectors (rows of whole numbers). order: row numbers by dimension and component, if known."""

    def __init__(self, ids: np.ndarray, rows: np.ndarray, order: np.ndarray | None = None):
        self.ids, self.whole = ids, rows
        self.largest = max(float(rows.max(initial=0)), -float(rows.min(initial=0)))
        self.narrow = self.largest < 2.0**53
        self.read = self.rescored = 0  # segments read and rows rescored by the last search
        if not self.narrow:
            return
        self.rows = rows if rows.dtype.kind == "i" else rows.astype(np.int64)
        self.order = self.sorted(rows) if order is None else order
        self.segments: list[np.ndarray] = []
        low, high, dim = [], [], []
        for d in range(rows.shape[1]):
            place = self.order[d].astype(np.int64)
            column = self.rows[place, d].astype(np.int64)
            cuts = np.flatnonzero(np.diff(column >> SHIFT)) + 1
            self.segments += np.split(place, cuts)
            begin = np.concatenate(([0], cuts))
            low.append(column[begin])
            high.append(column[np.append(cuts, len(column)) - 1])
            dim.append(np.full(len(begin), d))
        self.low, self.high, self.dim = np.concatenate(low), np.concatenate(high), np.concatenate(dim)

    @staticmethod
    def sorted(rows: np.ndarray) -> np.ndarray:
        return np.stack([np.argsort(column, kind="stable").astype(_places(len(rows))) for column in rows.T])

    def scores(self, may: np.ndarray, query: np.ndarray) -> np.ndarray:
        """Exact inner products: 64-bit numbers where they can't overflow, else whole numbers of any length."""
        if self.narrow and self.largest * float(np.abs(query).max()) * len(query) < 2.0**62:
            return self.rows[may].astype(np.int64) @ query.astype(np.int64)
        q = [int(x) for x in query.tolist()]
        return np.array([sum(int(a) * b for a, b in zip(row, q, strict=True)) for row in self.whole[may].tolist()], object)

    def search(self, query: np.ndarray, own: int, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Ids and scores of the block's best k for the query."""
        n, d = self.whole.shape
        self.read, floor, may = 0, None, np.arange(n)
        if self.narrow and self.largest * float(np.abs(query).max()) * d < _SAFE:
            floor, bound = self._bounds(query.astype(np.int64), own, k)
            may = np.flatnonzero(bound >= floor) if floor is not None else may
        may = may[self.ids[may] != own]
        self.rescored = len(may)
        score = self.scores(may, query)
        if len(may) > k and score.dtype == np.int64:
            keep = score >= np.partition(score, len(may) - k)[len(may) - k]
            may, score = may[keep], score[keep]
        best = sorted(range(len(may)), key=lambda i: (-int(score[i]), int(self.ids[may[i]])))[:k]
        return self.ids[may[best]], score[best]

    def _bounds(self, query: np.ndarray, own: int, k: int) -> tuple[int | None, np.ndarray]:
        """The k-th best score known, and what each row can reach, when processing stops."""
        n, d = self.rows.shape
        promise = np.maximum(self.low * query[self.dim], self.high * query[self.dim])
        least = np.full(d, np.iinfo(np.int64).max)
        np.minimum.at(least, self.dim, promise)
        base, impact = least.sum(), promise - least[self.dim]
        order = np.argsort(-impact, kind="stable")
        left = np.append(impact[order], 0)
        met = np.zeros(n, np.int64)  # impact x 2 ** 16 + number of dimensions met
        floor, bound = None, None
        for step, s in enumerate(order.tolist(), 1):
            met[self.segments[s]] += (int(impact[s]) << 16) + 1
            self.read = step
            if step % CHECK_EVERY and step < len(order):
                continue
            bound = (met >> 16) + left[step] * (d - (met & 0xFFFF)) + base
            if floor is None or step % (4 * CHECK_EVERY) == 0:
                lead = np.argpartition(-bound, min(n - 1, 4 * k))[: 4 * k + 1]
                known = np.sort((self.rows[lead].astype(np.int64) @ query)[self.ids[lead] != own])[::-1]
                if len(known) >= k:
                    floor = known[k - 1] if floor is None else max(floor, known[k - 1])
            if floor is not None and np.count_nonzero(bound >= floor) <= FEW * k:
                break
        return floor, bound


def _ready(vectors: DataFrame, id_col: str, vector_col: str) -> DataFrame:
    """vec_id, v (array of double) of the rows that take part."""
    fine = F.forall(vector_col, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x.cast("double")) < F.lit(float("inf"))))
    return vectors.filter(F.col(id_col).isNotNull() & (F.size(vector_col) > 0) & fine).select(F.col(id_col).cast("long").alias("vec_id"), F.transform(vector_col, lambda x: x.cast("double")).alias("v"))


def _packed(rows: DataFrame, scale: int, name: str, per_block: int | None = None) -> DataFrame:
    """name, dims, ids, values (whole numbers of the type kind) and, without per_block, the index's order, as bytes: at most per_block rows, or CELLS components, of equal length in each."""

    def pack(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        import uuid

        waiting: dict[int, list] = {}

        def out(d: int, got: list) -> pd.DataFrame:
            values = np.stack([v for _, v in got])
            values *= scale
            np.floor(values, values)
            if not np.isfinite(values).all():
                raise OverflowError("a scaled component is beyond doubles")
            values = narrowest(values)
            order = ImpactIndex.sorted(values).tobytes() if per_block is None else b""
            ids = np.array([i for i, _ in got], np.int64).tobytes()
            return pd.DataFrame({name: [uuid.uuid4().int & ((1 << 62) - 1)], "dims": [d], "kind": [values.dtype.str], "ids": [ids], "values": [values.tobytes()], "order": [order]})

        for batch in batches:
            for i, v in zip(batch["vec_id"].tolist(), batch["v"].tolist(), strict=True):
                got = waiting.setdefault(len(v), [])
                got.append((i, v))
                if len(got) >= (per_block or max(1, CELLS // len(v))):
                    yield out(len(v), waiting.pop(len(v)))
        for d, got in waiting.items():
            yield out(d, got)

    return rows.mapInPandas(pack, f"{name} long, dims int, kind string, ids binary, values binary, `order` binary")


def _parts(queries: int, blocks: int, cores: int) -> int:
    """Parts of the queries: enough to keep all cores busy and for MOST queries in each at most, but no more than leave QUERIES in each."""
    return max(1, -(-queries // MOST), min(-(-queries // QUERIES), -(-4 * cores // blocks)))


def top_k(vectors: DataFrame, queries: DataFrame, k: int = K, scale: int = SCALE, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score: for each row of queries the k best rows of vectors but those of its own id."""
    from .store import written

    ready, asking = _ready(vectors, id_col, vector_col), _ready(queries, id_col, vector_col)
    cells = ready.agg(F.sum(F.size("v"))).first()[0] or 0
    # Rows are dealt evenly to as many tasks as there are blocks, queries to as many as there are parts of them.
    data = written(_packed(ready.repartition(1 + cells // CELLS), scale, "block"), "impact-blocks")
    n_asked = asking.count()
    parts = _parts(n_asked, 1 + cells // CELLS, vectors.sparkSession.sparkContext.defaultParallelism)
    asked = written(_packed(asking.repartition(parts), scale, "part", 2 * (1 + n_asked // parts)), "impact-queries").drop("order")
    pairs = written(data.select("block", "dims").join(asked.select("part", "dims"), "dims").select("block", "part"), "impact-pairs")
    # A number of partitions that is given is not made smaller for want of bytes: the work lies in the pairs.
    n = max(1, min(2 * pairs.count(), MOST_TASKS))
    blocks = data.join(pairs, "block").repartition(n, "block", "part")
    asks = asked.join(pairs, "part").select("block", "part", F.col("kind").alias("query_kind"), F.col("ids").alias("query_ids"), F.col("values").alias("query_values")).repartition(n, "block", "part")

    def search(block: pd.DataFrame, asks: pd.DataFrame) -> pd.DataFrame:
        found = []
        for row in block.itertuples(index=False):
            shape = (-1, row.dims)
            ids = np.frombuffer(row.ids, np.int64)
            index = ImpactIndex(ids, np.frombuffer(row.values, row.kind).reshape(shape), np.frombuffer(row.order, _places(len(ids))).reshape(row.dims, -1))
            for part in asks.itertuples(index=False):
                for at, (q, v) in enumerate(zip(np.frombuffer(part.query_ids, np.int64).tolist(), np.frombuffer(part.query_values, part.query_kind).astype(np.float64).reshape(shape), strict=True)):
                    ids, score = index.search(v, q, k)
                    found += [(part.part, at, q, i, int(s)) for i, s in zip(ids.tolist(), score.tolist(), strict=True)]
        if any(abs(f[4]) >= 1 << 63 for f in found):
            raise OverflowError("a score is beyond 64 bits")
        return pd.DataFrame(found, columns=["part", "at", "query_id", "vec_id", "score"]).astype("int64")

    near = blocks.groupBy("block", "part").cogroup(asks.groupBy("block", "part")).applyInPandas(search, "part long, at long, query_id long, vec_id long, score long")
    place = F.row_number().over(Window.partitionBy("part", "at").orderBy(F.desc("score"), "vec_id"))
    return near.withColumn("rank", place).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
