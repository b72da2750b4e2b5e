"""The traversals: frontier, saturation, hybrid, reversed, traced and bounded forms."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.automaton import Automaton
from ..sources.graph import LabeledGraph
from ..sources.store import written
from .levels import KNOWN_CAP, LITERAL_CAP, Known, Level, Plan, local
from .walks import LONG, driven, walked

THRESHOLD = 100


@dataclass
class Found:
    """All (seed, q, v) pairs reached, and how."""

    plan: Plan
    known: Known
    by_level: list | None = None

    def pairs(self) -> DataFrame:
        return self.known.df()

    def answers(self) -> DataFrame:
        return accepting(self, self.plan.automaton.finals)


def accepting(found: Found, finals) -> DataFrame:
    """seed, v of the pairs in a final state."""
    if found.known.rows is not None:
        return local(found.plan.spark, {(s, v) for s, q, v in found.known.rows if q in finals})
    return found.known.df().filter(F.col("q").isin(sorted(finals))).select("seed", "v").distinct()


class _Stop(Exception):
    pass


def traverse(
    graph: LabeledGraph, automaton: Automaton, seeds, method: str = "hybrid", threshold: float = THRESHOLD, order: str = "automaton_first", seed_visited: bool = True,
    max_levels: int | None = None, literal_cap: int = LITERAL_CAP, keep_levels: bool = False, walks: bool = True,
) -> Found:
    """Run a method to its end, or for max_levels levels.

    frontier: each level extends only what was new in the last one. saturation: each level extends all pairs known, until nothing
    changes. hybrid: saturation until threshold pairs are known, then frontier from the pairs new in the last level.
    States that repeat a step of single successors are closed at once after LONG levels (if the step has MANY edges, when HELD frontiers have held them), unless levels
    are kept or bounded or walks=False.
    seed_visited=False leaves the seeds themselves out of the known pairs until a step reaches them again, so zero-length answers go missing.
    """
    if method not in ("frontier", "saturation", "hybrid"):
        raise ValueError(method)
    plan = Plan(graph, automaton, order, literal_cap)
    first = plan.start(seeds)
    first = first if isinstance(first, set) else written(first, "frontier")
    known = Known(plan, first, keep_levels)
    new, n_new = first, known.size
    if not seed_visited:
        known = Known(plan, set() if isinstance(first, set) else first.filter("false"), keep_levels)
    levels = [(0, first)] if keep_levels else None
    level, closed, states = 0, set(), None
    walks = walks and not keep_levels and max_levels is None
    if walks and seed_visited and isinstance(first, set) and first:
        plan.ahead()
        new, n_new, closed = _closed(plan, known, first, n_new, 0, set(automaton.starts))
    while n_new and (max_levels is None or level < max_levels):
        level += 1
        all_pairs = seed_visited and (method == "saturation" or (method == "hybrid" and known.size < threshold))
        source, size = (known.rows if all_pairs else new) if known.rows is not None else (known.df() if all_pairs else new), known.size if all_pairs else n_new
        found = plan.literal_step(source, closed) if known.rows is not None and isinstance(source, set) else None
        fresh = found - known.rows if found is not None else None
        if fresh is not None and (not fresh or len(known.rows) + len(fresh) <= KNOWN_CAP):
            new = fresh
            n_new = len(new)
            known.add(new)
            regime = "literal"
        else:
            if known.rows is not None:
                source = plan.rows(source)
                known.spread()
            new = written(known.without(plan.step(source, size, None if all_pairs else states)), "frontier")
            counts = {r["q"]: r["count"] for r in new.groupBy("q").count().collect()}
            n_new = sum(counts.values())
            known.add(new, n_new)
            regime = "join"
        states = {q for _, q, _ in new} if isinstance(new, set) else set(counts)
        closed = closed - states
        plan.trace.append(Level(level, size, n_new, known.size, regime))
        if levels is not None and n_new:
            levels.append((level, new))
        if walks and n_new:
            new, n_new, followed = _closed(plan, known, new, n_new, level, states)
            closed |= followed
    return Found(plan, known, levels)


def _closed(plan: Plan, known: Known, new: set | DataFrame, n_new: int, level: int, states: set[int]) -> tuple[set | DataFrame, int, set[int]]:
    """The frontier, and the pairs that walks from it reach in its states, which become known; their number; the states, if the driver followed them."""
    near = isinstance(new, set)
    looked, least = plan.loops.lasting(states, level, LONG, near) if level else (plan.loops.ready(states) if near else set(), 0)
    loops = plan.loops.of(looked, least, near) if looked else {}
    if not loops:
        return new, n_new, set()
    if isinstance(new, set):
        far = driven(new, loops)
        if far is not None:
            far -= known.rows
            known.add(far)
            if far:
                plan.trace.append(Level(level, 0, len(far), known.size, "walk"))
            alive = {q for q in states if plan.leads((q,), loops)}
            both = new | far if alive == states else {r for rows in (new, far) for r in rows if r[1] in alive}
            if known.size > KNOWN_CAP and both:  # else all is found
                known.spread()
                return written(plan.rows(both), "frontier"), len(both), set()
            return both, len(both), set(loops)
        known.spread()
        new = plan.rows(new)
    far = walked(new, loops)
    if far is None:
        return new, n_new, set()
    fresh = written(known.without(far), "frontier")
    n = fresh.count()
    if not n:
        return new, n_new, set()
    both = written(new.unionByName(fresh), "frontier")  # a table of its own, since the known pairs may merge those of the two
    known.add(fresh, n)
    plan.trace.append(Level(level, 0, n, known.size, "walk"))
    return both, n_new + n, set()


def frontier_reach(graph, automaton, seeds, **how) -> DataFrame:
    return traverse(graph, automaton, seeds, "frontier", **how).answers()


def saturate_reach(graph, automaton, seeds, **how) -> DataFrame:
    return traverse(graph, automaton, seeds, "saturation", **how).answers()


def hybrid_reach(graph, automaton, seeds, threshold: float = THRESHOLD, **how) -> DataFrame:
    return traverse(graph, automaton, seeds, "hybrid", threshold, **how).answers()


def reverse_reach(graph, automaton, targets, method: str = "hybrid", **how) -> DataFrame:
    """seed (a target), v (a vertex with a path to it): the reversed automaton from the targets."""
    return traverse(graph, automaton.reverse(), targets, method, **how).answers()


def reach_pairs(graph, automaton, seeds, method: str = "frontier", **how) -> DataFrame:
    return traverse(graph, automaton, seeds, method, **how).pairs()


def trace_reach(graph, automaton, seeds, method: str = "frontier", **how) -> DataFrame:
    """level, seed, q, v: each pair with the level that found it."""
    found = traverse(graph, automaton, seeds, method, keep_levels=True, **how)
    out = None
    for level, rows in found.by_level:
        df = found.plan.rows(rows) if isinstance(rows, set) else rows
        df = df.select(F.lit(level).alias("level"), "seed", "q", "v")
        out = df if out is None else out.unionAll(df)
    return out


def level_counts(graph, automaton, seeds, method: str = "frontier", **how) -> list[Level]:
    """What each level did: sizes of what was extended, found and known, and the regime."""
    return traverse(graph, automaton, seeds, method, walks=False, **how).plan.trace
