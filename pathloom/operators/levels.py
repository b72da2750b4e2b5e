"""One level of a traversal: advance (seed, state, vertex) by one step in automaton and graph together.

Two regimes. While all rows fit a fixed bound on the driver, a level is one scan with the frontier's vertices as literals, which
partition and row group statistics prune. Beyond it a level is a join plan, and its rows are written to the shared folder.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterable, Iterator, Sequence
from dataclasses import dataclass, field
from functools import reduce

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.automaton import Automaton
from ..sources.graph import LabeledGraph
from ..sources.store import forget, written
from .walks import FOLLOWED, Loops

TRIPLE = "seed long, q int, v long"
KEYS = ["seed", "q", "v"]
#: Bounds of the literal regime: vertices in a frontier, rows known, rows fetched in one level.
LITERAL_CAP, KNOWN_CAP, FETCH_CAP = 1000, 50_000, 50_000
#: A frontier of at most so many rows is broadcast to the edges, which are then not shuffled, however many of them one vertex has.
BROADCAST_ROWS = 200_000
#: Written tables of known pairs before older ones are merged.
MOST_PIECES = 8


@dataclass
class Level:
    """What one level did."""

    level: int
    frontier: int
    new: int
    known: int
    regime: str


@dataclass
class Plan:
    """A query bound to a graph: transitions over labels that the graph has, and how levels are run."""

    graph: LabeledGraph
    automaton: Automaton
    order: str = "automaton_first"
    literal_cap: int = LITERAL_CAP
    trace: list[Level] = field(default_factory=list)
    #: What the driver has fetched: ends by (label, inv, vertex), and the vertices asked for by step.
    ends: dict[tuple[str, int, int], list[int]] = field(default_factory=lambda: defaultdict(list))
    asked: dict[tuple[str, int], set[int]] = field(default_factory=lambda: defaultdict(set))

    def __post_init__(self):
        have = set(self.graph.labels())
        self.delta = sorted(t for t in self.automaton.delta if t[1] in have)
        self.steps = sorted({(label, inv) for _, label, inv, _ in self.delta})
        self.loops = Loops(self.delta, lambda label, inv: self.graph.hops([(label, inv)]), lambda label, inv: self.graph.brought(label, FOLLOWED))
        self.moves: dict[int, list[tuple[str, int, int]]] = defaultdict(list)
        for q, label, inv, q2 in self.delta:
            self.moves[q].append((label, inv, q2))

    @property
    def spark(self):
        return self.graph.spark

    def delta_df(self) -> DataFrame:
        return F.broadcast(self.spark.createDataFrame(self.delta, "q int, label string, inv int, q2 int"))

    def edge_tables(self) -> list[DataFrame]:
        """The edges of the query's steps."""
        return [self.graph.hops(self.steps)]

    def edges_from(self, states: Iterable[int] | None = None) -> DataFrame:
        """The edges of the steps that the given states take, for one level; some may come more than once."""
        return self.graph.passed(sorted({t[1:3] for t in self.delta if states is None or t[0] in states}))

    def ahead(self) -> None:
        """Begin to bring what driver rows will need: steps that states repeat, and names."""
        self.graph.ahead({label for label, _ in self.steps}, {label for label, _ in self.loops.steps.values()}, FOLLOWED)

    def leads(self, states: Iterable[int], closed: Iterable[int]) -> bool:
        """Whether these states have a step that could give new pairs, where those of closed states that repeat them do not."""
        return any(m[2] != q or q not in closed for q in states for m in self.moves.get(q, ()))

    def fetch(self, wanted: dict[tuple[str, int], set[int]], many: bool = False) -> dict[tuple[str, int, int], list[int]] | None:
        """Ends of the wanted edges on the driver, or None if they are more than FETCH_CAP. many: the vertices go to the edges as a table. Vertices that were asked
        for before are not looked up again."""
        out, rows, new = None, [], False
        for (label, inv), sources in sorted(wanted.items()):
            sources = sources - self.asked[label, inv]
            if not sources:
                continue
            new, held = True, self.loops.at_hand((label, inv))
            if held is not None:
                near = held.ends(sorted(sources), FETCH_CAP)
                if near is None:
                    return None
                rows += ((label, inv, v, w) for v, w in near)
                continue
            if many:
                found = self.graph.passed([(label, inv)]).join(F.broadcast(self.spark.createDataFrame(pa.table({"src": pa.array(sorted(sources), pa.int64())}))), "src")
            else:
                found = self.graph.looked_up(label, inv, sources)
            found = found.select("label", "inv", "src", "dst")
            out = found if out is None else out.unionAll(found)
        if not new:
            return self.ends
        if out is not None:
            found = out.limit(FETCH_CAP + 1).toArrow()  # all parts at a time, where collect() takes one after the other
            rows += zip(*(c.to_pylist() for c in found.columns), strict=True)
        if len(rows) > FETCH_CAP:
            return None
        if len(self.ends) > FETCH_CAP:  # each of them has one row at least, and the wanted ones that go are looked up again
            self.ends.clear()
            self.asked.clear()
            return self.fetch(wanted, many)
        for step, sources in wanted.items():
            self.asked[step] |= sources
        for label, inv, v, w in rows:
            self.ends[label, inv, v].append(w)
        return self.ends

    def literal_step(self, frontier: set[tuple[int, int, int]], closed: Iterable[int] = ()) -> set[tuple[int, int, int]] | None:
        """Successors of driver rows, or None if they don't fit. closed: states whose known rows are closed, since the driver followed their walks; the
        step that repeats them gives nothing new, and their rows may be more than go into literals."""
        moves = {q: [m for m in own if m[2] != q] if q in closed else own for q, own in self.moves.items()}
        wanted: dict[tuple[str, int], set[int]] = defaultdict(set)
        for _, q, v in frontier:
            for label, inv in self.steps if self.order == "graph_first" else {m[:2] for m in moves.get(q, ())}:
                wanted[label, inv].add(v)
        many = sum(map(len, wanted.values())) > self.literal_cap * max(1, len(self.steps))
        if many and not closed:
            return None
        ends = self.fetch(wanted, many)
        if ends is None:
            return None
        out: set[tuple[int, int, int]] = set()
        for seed, q, v in frontier:
            for label, inv, q2 in moves.get(q, ()):
                out.update((seed, q2, w) for w in ends.get((label, inv, v), ()))
                if len(out) > KNOWN_CAP:
                    return None
        return out

    def step(self, frontier: DataFrame, size: int | None = None, states: Iterable[int] | None = None) -> DataFrame:
        """Distinct successors of a table (seed, q, v) of the given size, which holds no others than the given states. The sum over labels comes before
        the one duplicate removal."""
        out = None
        small = size is not None and size <= BROADCAST_ROWS
        for found in self.moved_by_step(frontier) if hasattr(self.graph, "step_tables") and not small else self.moved(frontier, small, states):
            out = found if out is None else out.unionAll(found)
        if out is None:
            return self.rows([])
        return out.distinct()

    def moved(self, frontier: DataFrame, small: bool = False, states: Iterable[int] | None = None) -> Iterator[DataFrame]:
        delta = self.delta_df()
        sent = F.broadcast if small else lambda df: df
        edges = self.edges_from(states).withColumnRenamed("src", "v")
        if self.order == "automaton_first":
            found = sent(frontier.join(delta, "q").select("seed", "q2", "label", "inv", "v")).join(edges, ["v", "label", "inv"])
        elif self.order == "graph_first":
            found = sent(frontier).join(edges, "v").select("seed", "q", "label", "inv", "dst").join(delta, ["q", "label", "inv"])
        else:
            raise ValueError(self.order)
        yield found.select("seed", F.col("q2").alias("q"), F.col("dst").alias("v"))

    def moved_by_step(self, frontier: DataFrame) -> Iterator[DataFrame]:
        """The same for tables that are bucketed by vertex: one join on the vertex alone for each step of the query."""
        for (label, inv), edges in self.graph.step_tables(self.steps):
            rules = self.spark.createDataFrame([(q, q2) for q, x, i, q2 in self.delta if (x, i) == (label, inv)], "q int, q2 int")
            ready = frontier.join(F.broadcast(rules), "q").select("seed", "q2", "v")
            yield ready.join(edges.withColumnRenamed("src", "v"), "v").select("seed", F.col("q2").alias("q"), F.col("dst").alias("v"))

    def rows(self, rows: Iterable[tuple[int, int, int]]) -> DataFrame:
        rows = sorted(rows)
        if len(rows) <= LITERAL_CAP:
            return self.spark.createDataFrame(rows, TRIPLE)
        kinds = pa.int64(), pa.int32(), pa.int64()
        return self.spark.createDataFrame(pa.table([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names=KEYS))

    def start(self, seeds) -> set[tuple[int, int, int]] | DataFrame:
        """(seed, q, v) for seeds given as numbers or as a table with one column; driver rows if they are few."""
        if not isinstance(seeds, DataFrame):
            found = {(int(s), q, int(s)) for s in seeds for q in self.automaton.starts}
            return found if len(found) <= self.literal_cap else self.rows(found)
        seeds = seeds.select(F.col(seeds.columns[0]).cast("long").alias("seed")).filter("seed is not null").distinct()
        states = F.array(*map(F.lit, sorted(self.automaton.starts))).cast("array<int>")
        few = [r[0] for r in seeds.limit(self.literal_cap + 1).collect()] if self.literal_cap else []
        if few and len(few) * max(1, len(self.automaton.starts)) <= self.literal_cap:
            return {(s, q, s) for s in few for q in self.automaton.starts}
        return seeds.select("seed", F.explode(states).alias("q"), F.col("seed").alias("v"))


def local(spark, pairs: Iterable[tuple[int, int]]) -> DataFrame:
    """seed, v of driver rows, as a part of the plan."""
    seed, v = zip(*sorted(pairs), strict=True) if pairs else ((), ())
    return spark.createDataFrame(pa.table({"seed": pa.array(seed, pa.int64()), "v": pa.array(v, pa.int64())}))


class Seen:
    """Rows that a loop has found: written tables of which the newest is what the next level extends.

    A level compares its rows with all of them in one join. Older tables are merged as they grow in number, by sizes, so a row is rewritten
    a logarithmic number of times; tables that were merged are deleted unless they are kept for the loop's result. The newest never is.
    """

    def __init__(self, keys: Sequence[str] = KEYS, keep: bool = False):
        self.keys, self.keep = list(keys), keep
        self.size = 0
        self._pieces: list[tuple[DataFrame, int, bool]] = []  # table, rows, whether the loop gave it

    def add(self, piece: DataFrame, count: int | None = None) -> int:
        """Take in rows that are not in the tables yet; their number."""
        count = piece.count() if count is None else count
        if count:
            self._pieces.append((piece, count, True))
            self.size += count
            if len(self._pieces) > MOST_PIECES:
                self._merge()
        return count

    def _merge(self) -> None:
        newest = self._pieces.pop()
        take, total = 1, self._pieces[-1][1]
        while take < len(self._pieces) and (take < MOST_PIECES // 2 or self._pieces[-take - 1][1] <= 2 * total):
            take += 1
            total += self._pieces[-take][1]
        old, self._pieces = self._pieces[-take:], self._pieces[:-take]
        merged = written(reduce(DataFrame.unionAll, (t.select(self.keys) for t, _, _ in old)), "known")
        forget(*(t for t, _, given in old if not (given and self.keep) and t.inputFiles()))
        self._pieces += [(merged, total, False), newest]

    def df(self) -> DataFrame:
        return reduce(DataFrame.unionAll, (t.select(self.keys) for t, _, _ in self._pieces))

    def without(self, found: DataFrame) -> DataFrame:
        """The rows of found that are new."""
        return found.join(self.df(), self.keys, "left_anti") if self._pieces else found

    def new(self, found: DataFrame, name: str) -> tuple[DataFrame, int]:
        """The rows of found that are new, written and taken in, and their number."""
        piece = written(self.without(found), name)
        return piece, self.add(piece)


class Known:
    """Pairs found so far: driver rows, or written tables."""

    def __init__(self, plan: Plan, first, keep: bool = False):
        self.plan, self.size = plan, 0
        self.rows: set | None = set() if isinstance(first, set) else None
        self.tables = Seen(keep=keep)
        self.add(first)

    def add(self, new, count: int | None = None) -> None:
        if self.rows is not None:
            self.rows |= new
            self.size = len(self.rows)
        else:
            self.size += self.tables.add(new, count)

    def spread(self) -> None:
        """Leave the literal regime."""
        if self.rows is not None:
            self.tables.add(written(self.plan.rows(self.rows), "known"), len(self.rows))
            self.rows = None

    def without(self, found: DataFrame) -> DataFrame:
        return self.tables.without(found)

    def df(self) -> DataFrame:
        if self.rows is not None:
            return self.plan.rows(self.rows)
        return self.tables.df() if self.size else self.plan.rows([])
