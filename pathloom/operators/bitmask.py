"""Traversals over packed rows: all states of a vertex, or many seeds of a pair, in one 64-bit number."""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Callable, Iterable
from functools import reduce

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.automaton import Automaton
from ..sources.graph import LabeledGraph
from ..sources.store import forget, written
from .levels import BROADCAST_ROWS, KNOWN_CAP, LITERAL_CAP, Plan, local
from .reach import traverse
from .walks import LONG, driven

STATES, SEEDS = 63, 63


def _states(plan: Plan, mask: int) -> list[int]:
    return [q for q in range(plan.automaton.n) if mask >> q & 1]


def _literal(plan: Plan, masks: dict[tuple[int, int], int]) -> tuple[dict, dict, bool] | None:
    """The same on the driver while it fits, or None: known masks by (seed, v), those that are still to be extended because walks go on from them or give many,
    and whether these walks have been followed."""
    known, new, level = dict(masks), dict(masks), 0
    while new:
        states = _states(plan, reduce(int.__or__, new.values()))
        looked, least = plan.loops.lasting(states, level, LONG, True) if level else (plan.loops.ready(states), 0)
        loops = plan.loops.of(looked, least, True) if looked else {}
        if loops:
            far = driven({(seed, q, v) for (seed, v), mask in new.items() for q in loops if mask >> q & 1}, loops)
            if far is None:
                return known, new, False
            for seed, q, v in far:
                if not known.get((seed, v), 0) >> q & 1:
                    known[seed, v] = known.get((seed, v), 0) | 1 << q
                    new[seed, v] = new.get((seed, v), 0) | 1 << q
            if not plan.leads(states, loops):
                return known, {}, False
            if len(known) > KNOWN_CAP:
                return known, new, True
        level += 1
        wanted = defaultdict(set)
        moves: dict[tuple[str, int], list[tuple[int, int]]] = defaultdict(list)
        for q, label, inv, q2 in plan.delta:
            if q != q2 or q not in loops:  # walks that were followed give nothing new
                moves[label, inv].append((q, q2))
        for (_, v), mask in new.items():
            for step, pairs in moves.items():
                if any(mask >> q & 1 for q, _ in pairs):
                    wanted[step].add(v)
        many = sum(map(len, wanted.values())) > plan.literal_cap
        ends = plan.fetch(wanted, many) if loops or not many else None
        if ends is None:
            return (known, new, True) if loops else None
        found: dict[tuple[int, int], int] = defaultdict(int)
        for (seed, v), mask in new.items():
            for (label, inv), pairs in moves.items():
                to = reduce(lambda m, p: m | (1 << p[1] if mask >> p[0] & 1 else 0), pairs, 0)
                if to:
                    for w in ends.get((label, inv, v), ()):
                        found[seed, w] |= to
        new = {k: m & ~known.get(k, 0) for k, m in found.items() if m & ~known.get(k, 0)}
        for k, m in new.items():
            known[k] = known.get(k, 0) | m
        if new and len(known) > KNOWN_CAP:
            return None
    return known, {}, False


def _rows(plan: Plan, masks: dict[tuple[int, int], int]) -> DataFrame:
    columns = zip(*((*k, m) for k, m in sorted(masks.items())), strict=True)
    return plan.spark.createDataFrame(pa.table([pa.array(c, pa.int64()) for c in columns], names=["seed", "v", "mask"]))


def _walked(plan: Plan, known: DataFrame, new: DataFrame, states: Iterable[int], least: int) -> tuple[DataFrame, DataFrame, DataFrame | None]:
    """known and new with all that walks in the given states reach, and the table of both; None for it if there are no such walks."""
    found = None
    for q, jumps in plan.loops.of(states, least).items():
        far, n = jumps.closure(new.filter(F.col("mask").bitwiseAND(F.lit(1 << q)) != 0), ["seed"])
        if n:
            far = far.withColumn("far", F.lit(1 << q).cast("long"))
            found = far if found is None else found.unionAll(far)
    if found is None:
        return known, new, None
    found = found.groupBy("seed", "v").agg(F.bit_or("far").alias("far"))
    whole = known.withColumnRenamed("mask", "old").join(new.withColumnRenamed("mask", "new"), ["seed", "v"], "left").join(found, ["seed", "v"], "full_outer")
    both = written(whole.select("seed", "v", *(F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in ("old", "new", "far"))), "masks")
    more = F.col("far").bitwiseAND(F.bitwise_not("old")).bitwiseOR(F.col("new"))
    return both.select("seed", "v", F.col("old").bitwiseOR(F.col("far")).alias("mask")), both.select("seed", "v", more.alias("mask")).filter("mask <> 0"), both


def _moved(plan: Plan):
    """For each step the states after it, computed from the mask column."""
    out = []
    for label, inv in plan.steps:
        parts = [F.when(F.col("mask").bitwiseAND(F.lit(1 << q)) != 0, F.lit(1 << q2)).otherwise(F.lit(0)) for q, x, i, q2 in plan.delta if (x, i) == (label, inv)]
        out.append(F.struct(F.lit(label).alias("label"), F.lit(inv).alias("inv"), reduce(lambda a, b: a.bitwiseOR(b), parts).cast("long").alias("mask")))
    return F.filter(F.array(*out), lambda m: m["mask"] != 0)


def bitmask_reach(graph: LabeledGraph, automaton: Automaton, seeds, literal_cap: int = LITERAL_CAP) -> DataFrame:
    """seed, v. One row for each (seed, vertex) holds its states as bits, so a level shuffles a row where pairs would be many."""
    if automaton.n > STATES:
        return traverse(graph, automaton, seeds, "frontier", literal_cap=literal_cap).answers()
    plan = Plan(graph, automaton, literal_cap=literal_cap)
    final = sum(1 << q for q in automaton.finals)
    first = plan.start(seeds)
    if isinstance(first, set):
        masks: dict[tuple[int, int], int] = defaultdict(int)
        for seed, q, v in first:
            masks[seed, v] |= 1 << q
        plan.ahead()
        done = _literal(plan, masks)
        if done is not None and not done[1]:
            return local(plan.spark, [k for k, m in done[0].items() if m & final])
        first = plan.rows(first)
    else:
        done = None
    if done is not None:
        known, new = (written(_rows(plan, x), "masks") for x in done[:2])
        tables, n, level, held = [], len(done[1]), 0 if done[2] else LONG, reduce(int.__or__, done[1].values())
    else:
        bit = F.expr("shiftleft(1L, q)")
        new = written(first.groupBy("seed", "v").agg(F.bit_or(bit).alias("mask")), "masks")
        known, tables, n, level, held = new, [], new.count(), 0, reduce(int.__or__, (1 << q for q in automaton.starts), 0)
    while plan.steps and n:
        looked, least = plan.loops.lasting(_states(plan, held), level, LONG) if level else ((), 0)
        if looked:
            known, new, both = _walked(plan, known, new, looked, least)
            if both is not None:
                forget(*tables)
                tables, n = [both], new.count()
        level += 1
        sent = F.broadcast if n <= BROADCAST_ROWS else lambda df: df
        moved, edges = sent(new.select("seed", "v", F.inline(_moved(plan)))), plan.edges_from(_states(plan, held))
        parts = moved.join(edges.withColumnRenamed("src", "v"), ["v", "label", "inv"]).select("seed", F.col("dst").alias("v"), "mask")
        found = parts.groupBy("seed", "v").agg(F.bit_or("mask").alias("found"))
        both = written(known.join(found, ["seed", "v"], "full_outer").select("seed", "v", F.coalesce("mask", F.lit(0)).alias("old"), F.coalesce("found", F.lit(0)).alias("found")), "masks")
        known = both.select("seed", "v", F.col("old").bitwiseOR(F.col("found")).alias("mask"))
        new = both.select("seed", "v", F.col("found").bitwiseAND(F.bitwise_not("old")).alias("mask")).filter("mask <> 0")
        n, held = new.agg(F.count("*"), F.coalesce(F.bit_or("mask"), F.lit(0))).first()
        forget(*tables)
        tables = [both]
    return known.filter(F.col("mask").bitwiseAND(F.lit(final)) != 0).select("seed", "v")


def numbered_blocks(seeds: DataFrame) -> DataFrame:
    """seed, block, bit: the distinct seeds, numbered on from range to range, so no task sees all of them and every block but the last is full."""
    ready = seeds.select(F.col(seeds.columns[0]).cast("long").alias("seed")).filter("seed is not null").distinct()
    parted = written(ready.withColumn("_part", F.spark_partition_id()), "seeds")
    sizes = parted.groupBy("_part").agg(F.count("*").alias("_n"))
    before = Window.partitionBy(F.lit(0)).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sizes.select("_part", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_before"))
    place = F.col("_before") + F.row_number().over(Window.partitionBy("_part").orderBy("seed")) - 1
    placed = parted.join(F.broadcast(offsets), "_part").select("seed", place.alias("_at"))
    return placed.select("seed", F.floor(F.col("_at") / SEEDS).alias("block"), (F.col("_at") % SEEDS).cast("int").alias("bit"))


def packed_levels(known: DataFrame, new: DataFrame, step: Callable[[DataFrame], DataFrame], keys: list[str]) -> DataFrame:
    """keys, mask: known with the bits that repeated steps reach from new (tables of keys and mask). A level extends only bits that the one before found first."""
    tables, n = [], new.count()
    while n:
        found = step(new).groupBy(keys).agg(F.bit_or("mask").alias("found"))
        both = written(known.join(found, keys, "full_outer").select(*keys, F.coalesce("mask", F.lit(0)).alias("old"), F.coalesce("found", F.lit(0)).alias("found")), "packed")
        known = both.select(*keys, F.col("old").bitwiseOR(F.col("found")).alias("mask"))
        new = both.select(*keys, F.col("found").bitwiseAND(F.bitwise_not("old")).alias("mask")).filter("mask <> 0")
        n = new.count()
        forget(*tables)
        tables = [both]
    return known.filter("mask <> 0")


def seed_blocks_reach(graph: LabeledGraph, automaton: Automaton, seeds: DataFrame) -> DataFrame:
    """seed, v for many seeds: blocks of up to 63 seeds share rows (block, q, v), with one bit for each seed.

    A level extends only the bits that were new in the last one, as the frontier method does for each seed.
    """
    plan = Plan(graph, automaton)
    placed = written(numbered_blocks(seeds), "seeds")
    states = F.array(*map(F.lit, sorted(automaton.starts))).cast("array<int>")
    keys = ["block", "q", "v"]
    new = written(placed.select("block", F.explode(states).alias("q"), F.col("seed").alias("v"), F.expr("shiftleft(1L, bit)").alias("mask")), "blocks")
    known, tables, delta, n = new, [], plan.delta_df(), new.count()
    while plan.steps and n:
        sent = F.broadcast if n <= BROADCAST_ROWS else lambda df: df
        ready = sent(new.join(delta, "q").select("block", "q2", "label", "inv", "v", "mask"))
        parts = [ready.join(e.withColumnRenamed("src", "v"), ["v", "label", "inv"]).select("block", F.col("q2").alias("q"), F.col("dst").alias("v"), "mask") for e in plan.edge_tables()]
        found = reduce(DataFrame.unionAll, parts).groupBy(keys).agg(F.bit_or("mask").alias("found"))
        both = written(known.join(found, keys, "full_outer").select(*keys, F.coalesce("mask", F.lit(0)).alias("old"), F.coalesce("found", F.lit(0)).alias("found")), "blocks")
        known = both.select(*keys, F.col("old").bitwiseOR(F.col("found")).alias("mask"))
        new = both.select(*keys, F.col("found").bitwiseAND(F.bitwise_not("old")).alias("mask")).filter("mask <> 0")
        n = new.count()
        forget(*tables)
        tables = [both]
    done = known.filter(F.col("q").isin(sorted(automaton.finals))).groupBy("block", "v").agg(F.bit_or("mask").alias("mask"))
    return done.join(placed, "block").filter(F.expr("shiftright(mask, bit) & 1 = 1")).select("seed", "v")


def batch_reach(graph: LabeledGraph, automaton: Automaton, seeds: DataFrame, method: str = "hybrid", **how) -> DataFrame:
    """seed, v for a table of seeds: blocks of seeds if there are more than one block's, else a traversal by the given method."""
    if len(seeds.select(seeds.columns[0]).distinct().limit(SEEDS + 1).collect()) > SEEDS:
        return seed_blocks_reach(graph, automaton, seeds)
    return traverse(graph, automaton, seeds, method, **how).answers()
