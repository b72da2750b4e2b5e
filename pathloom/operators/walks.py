"""Long walks in few joins, where a state repeats one step that gives no vertex two successors: rings, chains, sequences.

There a task that holds all edges of the step follows each walk from vertex to vertex, for a part of the seeds. Where the edges or the parts are too many
for that, a walk of 2^k steps is one row of the k-th jump table, the join of the table before with itself, so the closure of a frontier takes the
logarithm of the longest walk in rounds. Walks from rows that the driver holds are followed there, if edges and walks are few enough. A traversal tries it for
states that HELD of its frontiers have held, and after LONG levels. What it adds are pairs that later levels would find one at a time; they are part
of the next frontier, so every pair is still extended by every step of its state that leads on.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Callable, Iterable, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.store import forget, written

#: Levels before a traversal looks for such states, and before the indexed method looks for those whose step has MANY edges or more.
LONG, EARLY, MANY = 16, 8, 1000
#: Frontiers that have held a state before the other methods look whether its step has MANY edges or more: the second shows that walks go on.
HELD = 2
#: Rows that walks followed on the driver return, at most.
WALKED = 200_000
#: Edges that one task follows, and rows that it returns, at most about so many. Seeds that share a task, and copies of the edges for tasks of other seeds.
FOLLOWED, SHARE, COPIES = 2_000_000, 64, 8


class Jumps:
    """Walks over edges (src, dst). Tables of walks of 1, 2, 4, ... steps are made as they are needed."""

    def __init__(self, edges: DataFrame | Callable[[], DataFrame]):
        self._edges, self._tables, self._single, self.size = edges, [], None, 0
        self._near = None

    @property
    def edges(self) -> DataFrame:
        if not isinstance(self._edges, DataFrame):
            self._edges = self._edges()
        return self._edges.select("src", "dst")

    def bring(self, least: int = 0) -> None:
        """Take the edges to the driver, two numbers each, if they are at least so many and at most FOLLOWED."""
        if self._near is None and self._single is None:
            self.size = self.size or self.edges.count()
            if least <= self.size <= FOLLOWED:
                held = self.edges.toArrow()
                self.take(held["src"].to_numpy(), held["dst"].to_numpy())

    def take(self, src: np.ndarray, dst: np.ndarray) -> None:
        """Hold these edges on the driver; one that comes more than once counts once."""
        order = np.lexsort((dst, src))
        src, dst = src[order], dst[order]
        if len(src):
            first = np.concatenate([[True], (src[1:] != src[:-1]) | (dst[1:] != dst[:-1])])
            src, dst = src[first], dst[first]
        self.size, self._single = len(src), not bool((src[1:] == src[:-1]).any())
        self._near = (src, dst, placed(src, dst) if self._single else None)

    def ends(self, sources: Iterable[int], most: int) -> list[tuple[int, int]] | None:
        """The edges from these vertices, if the driver holds the edges and these are at most so many."""
        if self._near is None:
            return None
        src, dst, _ = self._near
        asked = np.fromiter(sources, np.int64)
        low, high = np.searchsorted(src, asked, "left"), np.searchsorted(src, asked, "right")
        if int((high - low).sum()) > most:
            return None
        some = np.flatnonzero(high > low).tolist()
        return [(int(asked[i]), w) for i in some for w in dst[low[i] : high[i]].tolist()]

    @property
    def near(self) -> bool:
        return self._near is not None

    def single(self) -> bool:
        """Whether no vertex has two successors, so that no table is larger than the edges."""
        if self._single is None:
            most, size = self.edges.groupBy("src").agg(F.count("*").alias("n")).agg(F.max("n"), F.sum("n")).first()
            self._single, self.size = (most or 0) <= 1, size or 0
        return self._single

    def table(self, k: int) -> DataFrame:
        while len(self._tables) <= k:
            if self._tables:
                last = self._tables[-1]
                longer = last.join(last.select(F.col("src").alias("dst"), F.col("dst").alias("_end")), "dst").select("src", F.col("_end").alias("dst"))
            else:
                longer = self.edges
            self._tables.append(written(longer, "jumps"))
        return self._tables[k]

    def closure(self, rows: DataFrame | set[tuple[int, int]], carry: Sequence[str]) -> tuple[DataFrame | set[tuple[int, int]] | None, int]:
        """The rows (carry, v), and those of all vertices that walks from v reach, and their number. Driver rows (one carried column) give driver rows,
        or None if the driver cannot hold the edges or what they give."""
        if isinstance(rows, set):
            out = self.driven(rows)
            return out, len(out or ())
        rows = rows.select(*carry, "v")
        seeds = rows.select(*carry).distinct().count()
        parts = -(-seeds // max(1, min(SHARE, FOLLOWED // max(1, self.size)))) if self.single() else 0
        if parts and self.size <= FOLLOWED and (parts - 1) * self.size <= COPIES * FOLLOWED:
            more = written(self.followed(rows, carry, parts), "walked")
            return more, more.count()
        found, k = written(rows.distinct(), "walked"), 0
        n = found.count()
        while n:
            jumped = found.join(self.table(k).withColumnRenamed("src", "v"), "v").select(*carry, F.col("dst").alias("v"))
            more = written(found.unionByName(jumped).distinct(), "walked")
            forget(found)
            before, found, n, k = n, more, more.count(), k + 1
            if n == before:
                break
        return found, n

    def driven(self, rows: set[tuple[int, int]]) -> set[tuple[int, int]] | None:
        """The same on the driver."""
        if self._near is None:
            return None
        src, dst, after = self._near
        own, out, n = defaultdict(list), set(rows), 0
        for key, v in rows:
            own[key].append(v)
        for key, starts in own.items():
            seen, taken = bytearray(len(src)), []
            for i in placed(src, np.asarray(starts, np.int64)).tolist():
                while i >= 0 and not seen[i]:
                    seen[i] = 1
                    taken.append(i)
                    i = int(after[i])
                if n + len(taken) > WALKED:
                    return None
            n += len(taken)
            out.update((key, v) for v in dst[np.asarray(taken, np.int64)].tolist())
        return out

    def followed(self, rows: DataFrame, carry: Sequence[str], parts: int) -> DataFrame:
        """The same by tasks that each hold all edges and a part of the rows; all rows of one carry are in one part."""
        names = list(carry)

        def follow(rows, edges):
            import numpy as np
            import pandas as pd

            order = np.argsort(edges["src"].to_numpy())
            src, dst = edges["src"].to_numpy()[order], edges["dst"].to_numpy()[order]

            def place(v):
                at = np.minimum(np.searchsorted(src, v), max(0, len(src) - 1))
                return np.where(src[at] == v, at, -1) if len(src) else np.full(len(v), -1)

            after, out = place(dst).tolist(), []
            for key, own in rows.groupby(names, sort=False):
                starts, seen, taken = own["v"].to_numpy(), bytearray(len(src)), []
                for i in place(starts).tolist():
                    while i >= 0 and not seen[i]:
                        seen[i] = 1
                        taken.append(i)
                        i = after[i]
                reached = np.unique(np.concatenate([starts, dst[np.asarray(taken, np.int64)]]))
                out.append(pd.DataFrame({**dict(zip(names, key, strict=True)), "v": reached}))
            return pd.concat(out) if out else pd.DataFrame({c: np.array([], np.int64) for c in [*names, "v"]})

        dealt = rows.withColumn("_part", F.pmod(F.xxhash64(*names), F.lit(parts)).cast("int"))
        edges = self.edges.withColumn("_part", F.explode(F.sequence(F.lit(0), F.lit(parts - 1))))
        return dealt.groupBy("_part").cogroup(edges.groupBy("_part")).applyInPandas(follow, rows.schema)


def placed(src: np.ndarray, v: np.ndarray) -> np.ndarray:
    """Where each v stands in src, which is sorted; -1 for those that do not."""
    if not len(src):
        return np.full(len(v), -1)
    at = np.minimum(np.searchsorted(src, v), len(src) - 1)
    return np.where(src[at] == v, at, -1)


class Loops:
    """Jumps by state, for states with one step that leads back to them. edges: src, dst of a label, turned round if inverted."""

    def __init__(self, delta: Iterable[tuple[int, str, int, int]], edges: Callable[[str, int], DataFrame], brought: Callable[[str, int], pa.Table | None] = lambda *_: None):
        steps = defaultdict(set)
        for q, label, inv, q2 in delta:
            if q == q2:
                steps[q].add((label, inv))
        self.steps = {q: next(iter(own)) for q, own in steps.items() if len(own) == 1}
        self._edges, self._brought, self._made, self._held = edges, brought, {}, defaultdict(int)
        self._asked: set[tuple[str, int]] = set()

    def made(self, step: tuple[str, int]) -> Jumps:
        if step not in self._made:
            self._made[step] = Jumps(lambda: self._edges(*step))
        return self._made[step]

    def at_hand(self, step: tuple[str, int]) -> Jumps | None:
        """The edges of a step that a state repeats, if the graph brings them to the driver at once, by which they need not be kept and counted before."""
        if step not in self.steps.values():
            return None
        if step not in self._asked:
            self._asked.add(step)
            held = self._brought(*step)
            if held is not None:
                a, b = ("dst", "src") if step[1] else ("src", "dst")
                self.made(step).take(held[a].to_numpy(), held[b].to_numpy())
        own = self._made.get(step)
        return own if own is not None and own.near else None

    def ready(self, states: Iterable[int]) -> set[int]:
        """Of these states, those whose step the driver holds, so that nothing is gained by waiting."""
        return {q for q in set(states) & set(self.steps) if self.at_hand(self.steps[q]) is not None}

    def lasting(self, states: Iterable[int], level: int, long: int = LONG, near: bool = False) -> tuple[set[int], int]:
        """Of the states that the frontier of a level holds, those to look at, and the least number of edges of their step. near: a frontier of driver rows."""
        states = set(states) & set(self.steps)
        for q in states:
            self._held[q] += 1
        if level >= long:
            return states, 0
        return {q for q in states if self._held[q] >= HELD} | (self.ready(states) if near else set()), MANY

    def of(self, states: Iterable[int], least: int = 0, near: bool = False) -> dict[int, Jumps]:
        """Those of the given states whose step gives no vertex two successors and has at least so many edges. A step's edges are looked at when a
        frontier first holds its state. near: on the driver, if they are few enough."""
        out = {}
        for q in sorted(set(states) & set(self.steps)):
            jumps = self.made(self.steps[q])
            if near:
                if self.at_hand(self.steps[q]) is None:
                    jumps.bring(least)
                if jumps.size < least and not jumps.near:
                    continue
            if jumps.single() and (jumps.size >= least or (near and jumps.near)):
                out[q] = jumps
        return out

    def within(self, rows: DataFrame, least: int = 0) -> dict[int, Jumps]:
        """The same of the states in a table."""
        return self.of((r[0] for r in rows.select("q").distinct().collect()), least) if self.steps else {}


def driven(rows: set[tuple[int, int, int]], loops: dict[int, Jumps]) -> set[tuple[int, int, int]] | None:
    """The same as walked() for driver rows; None if the driver cannot hold the edges or what they give."""
    out = set()
    for q, jumps in loops.items():
        found, n = jumps.closure({(s, v) for s, p, v in rows if p == q}, ["seed"])
        if found is None or len(out) + n > WALKED:
            return None
        out.update((s, q, v) for s, v in found)
    return out


def walked(rows: DataFrame, loops: dict[int, Jumps]) -> DataFrame | None:
    """seed, q, v: the rows of states with loops and all that their walks reach, or None if no row has such a state."""
    out = None
    for q, jumps in loops.items():
        found, n = jumps.closure(rows.filter(F.col("q") == q), ["seed"])
        if n:
            found = found.select("seed", F.lit(q).alias("q"), "v")
            out = found if out is None else out.unionAll(found)
    return out
