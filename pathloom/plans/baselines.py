"""Comparison methods: an indexed product traversal, a pattern language without path algebra, recursive SQL, and brute force."""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterable
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.automaton import Automaton
from ..functions.cypher import NotExpressible, hop, is_cypher_expressible
from ..functions.expr import Alt, Concat, Empty, Expr, Label, Opt, Plus, Star
from ..functions.vertices import kind_of
from ..operators.bitmask import SEEDS, numbered_blocks, packed_levels
from ..operators.levels import Seen
from ..operators.walks import EARLY, LONG, MANY, Loops, walked
from ..sources.graph import LabeledGraph
from ..sources.store import written


def _seeded(spark: SparkSession, seeds: Iterable[int] | DataFrame) -> DataFrame:
    """seed of a list of numbers or of a table with one column."""
    if isinstance(seeds, DataFrame):
        return seeds.select(F.col(seeds.columns[0]).cast("long").alias("seed")).filter("seed is not null").distinct()
    return spark.createDataFrame([(int(s),) for s in dict.fromkeys(seeds)], "seed long")


#: Ranges of vertices that are looked up in one level at most; beyond them a level reads the whole copy.
SPANS = 64


def _copies(graph: LabeledGraph, directions: Iterable[int], labels: Iterable[str] | None) -> DataFrame:
    """label, inv, v, dst: the copies of all edges for the given directions. Each is written once, ordered by vertex in each of its parts."""
    copies, name = graph.__dict__.setdefault("_by_vertex", {}), None if labels is None else tuple(sorted(labels))
    for inv in directions:
        if (name, inv) not in copies:
            v, dst = ("dst", "src") if inv else ("src", "dst")
            turned = graph.triples(labels, once=True).select("label", F.lit(inv).alias("inv"), F.col(v).alias("v"), F.col(dst).alias("dst"))
            copies[name, inv] = written(turned.sortWithinPartitions("v"), "by-vertex", lasting=True)
    found = [copies[name, inv] for inv in directions]
    return reduce(DataFrame.unionAll, found) if found else graph.spark.createDataFrame([], "label string, inv int, v long, dst long")


def _looked_up(both: DataFrame, new: DataFrame) -> DataFrame:
    """The part of the copies in the ranges of vertices that new holds, by kind of vertex: files say which ranges they have."""
    spans = new.groupBy(kind_of("v").alias("kind")).agg(F.min("v"), F.max("v")).limit(SPANS + 1).collect()
    if not 0 < len(spans) <= SPANS:
        return both
    return both.filter(reduce(Column.__or__, (F.col("v").between(low, high) for _, low, high in spans)))


def indexed_reach(graph: LabeledGraph, automaton: Automaton, seeds: Iterable[int] | DataFrame, labels: Iterable[str] | None = None) -> DataFrame:
    """seed, v. One copy of all edges for each direction that the expression walks, found by vertex alone; labels are compared after the join with the edges."""
    spark = graph.spark
    both = _copies(graph, sorted({inv for _, _, inv, _ in automaton.delta}), labels)
    delta = F.broadcast(automaton.to_df(spark))
    states = F.array(*map(F.lit, sorted(automaton.starts))).cast("array<int>")
    asked = _seeded(spark, seeds)
    if asked.limit(SEEDS + 1).count() > SEEDS:
        return _indexed_blocks(both, delta, states, automaton, asked)
    start = asked.select("seed", F.explode(states).alias("q"), F.col("seed").alias("v"))
    known, level = Seen(), 0
    loops = Loops(automaton.delta, lambda label, inv: both.filter((F.col("label") == label) & (F.col("inv") == inv)).select(F.col("v").alias("src"), "dst"))
    new, n = known.new(start, "indexed")
    while n:
        far = walked(new, loops.within(new, 0 if level >= LONG else MANY)) if level >= min(LONG, EARLY) else None
        if far is not None:
            fresh = written(known.without(far), "indexed")
            new = written(new.unionByName(fresh), "indexed")
            known.add(fresh)
        level += 1
        found = new.join(_looked_up(both, new), "v").join(delta, ["q", "label", "inv"]).select("seed", F.col("q2").alias("q"), F.col("dst").alias("v")).distinct()
        new, n = known.new(found, "indexed")
    return (known.df() if known.size else new).filter(F.col("q").isin(sorted(automaton.finals))).select("seed", "v").distinct()


def _indexed_blocks(both: DataFrame, delta: DataFrame, states: Column, automaton: Automaton, seeds: DataFrame) -> DataFrame:
    """The same for many seeds: the seeds of a block share rows (block, q, v), with one bit for each, so an edge is found once for all of them."""
    placed, keys = written(numbered_blocks(seeds), "seeds"), ["block", "q", "v"]
    start = written(placed.select("block", F.explode(states).alias("q"), F.col("seed").alias("v"), F.expr("shiftleft(1L, bit)").alias("mask")), "indexed")

    def step(new: DataFrame) -> DataFrame:
        return new.join(_looked_up(both, new), "v").join(delta, ["q", "label", "inv"]).select("block", F.col("q2").alias("q"), F.col("dst").alias("v"), "mask")

    done = packed_levels(start, start, step, keys).filter(F.col("q").isin(sorted(automaton.finals))).groupBy("block", "v").agg(F.bit_or("mask").alias("mask"))
    return done.join(placed, "block").filter(F.expr("shiftright(mask, bit) & 1 = 1")).select("seed", "v")


def subset_reach(graph: LabeledGraph, expr: Expr, seeds: Iterable[int] | DataFrame) -> DataFrame:
    """seed, v by a chain of single hops and repeated hops; NotExpressible for what the pattern language lacks."""
    if not is_cypher_expressible(expr):
        raise NotExpressible(str(expr))

    def one(rows: DataFrame, labels: tuple[str, ...], inv: int) -> DataFrame:
        edges = graph.hops([(x, inv) for x in labels]).select(F.col("src").alias("v"), "dst")
        return rows.join(edges, "v").select("seed", F.col("dst").alias("v")).distinct()

    def run(e: Expr, rows: DataFrame) -> DataFrame:
        simple = hop(e.body if isinstance(e, (Star, Plus, Opt)) else e)
        if isinstance(e, Empty):
            return rows
        if isinstance(e, (Label, Alt)) and simple:
            return one(rows, *simple)
        if isinstance(e, Concat):
            return reduce(lambda r, p: run(p, r), e.parts, rows)
        if isinstance(e, Alt):
            return reduce(DataFrame.unionByName, (run(p, rows) for p in e.parts)).distinct()
        if isinstance(e, Opt):
            return rows.unionByName(one(rows, *simple)).distinct()
        known = Seen(["seed", "v"])
        new, n = known.new(one(rows, *simple), "hops")
        first = new
        while n:
            new, n = known.new(one(new, *simple), "hops")
        out = known.df() if known.size else first
        return out.unionByName(rows).distinct() if isinstance(e, Star) else out

    return run(expr, _seeded(graph.spark, seeds).select("seed", F.col("seed").alias("v")))


def recursive_sql(automaton: Automaton, seed: int, levels: int, edges: str = "hop") -> str:
    """A recursive query over a view (label, inv, src, dst). Spark's recursion keeps duplicates, so the depth is a part of the query: walks of
    more steps are not its answers. It may raise over Spark's limit of rows in a recursion, but never cuts answers short."""
    rules = ", ".join(f"({q}, '{label}', {inv}, {q2})" for q, label, inv, q2 in automaton.rows()) or "(0, '', 0, 0)"
    starts = ", ".join(f"({q})" for q in sorted(automaton.starts))
    finals = ", ".join(map(str, sorted(automaton.finals))) or "-1"
    return f"""
        WITH RECURSIVE
          rule(q, label, inv, q2) AS (SELECT * FROM VALUES {rules}),
          walk(q, v, depth) MAX RECURSION LEVEL {levels + 2} AS (
            SELECT col1, CAST({seed} AS BIGINT), 0 FROM VALUES {starts}
            UNION ALL
            SELECT rule.q2, e.dst, depth + 1 FROM walk JOIN rule ON rule.q = walk.q JOIN {edges} e ON e.label = rule.label AND e.inv = rule.inv AND e.src = walk.v
            WHERE depth < {levels})
        SELECT DISTINCT v FROM walk WHERE q IN ({finals})"""


def recursive_sql_reach(spark: SparkSession, graph: LabeledGraph, automaton: Automaton, seed: int, max_levels: int) -> DataFrame:
    """v by recursive SQL up to max_levels steps; for acyclic or short queries, since walks are not merged."""
    view = f"hop_{abs(hash((seed, max_levels, automaton)))}"
    graph.hops(automaton.steps).createOrReplaceTempView(view)
    return spark.sql(recursive_sql(automaton, seed, max_levels, view))


def brute_reach(edges: Iterable[tuple[str, int, int]], automaton: Automaton, seed: int) -> set[int]:
    """Reference: a queue over (state, vertex)."""
    out = defaultdict(set)
    for label, a, b in edges:
        out[label, 0, a].add(b)
        out[label, 1, b].add(a)
    moves = automaton.moves()
    todo = [(q, seed) for q in automaton.starts]
    seen = set(todo)
    while todo:
        q, v = todo.pop()
        for label, inv, q2 in moves.get(q, ()):
            for w in out[label, inv, v]:
                if (q2, w) not in seen:
                    seen.add((q2, w))
                    todo.append((q2, w))
    return {v for q, v in seen if q in automaton.finals}


def brute_words(edges: Iterable[tuple[str, int, int]], expr_accepts, steps: Iterable[tuple[str, int]], seed: int, longest: int) -> set[int]:
    """Reference of the reference: all walks up to a length, each word tested."""
    out = defaultdict(set)
    for label, a, b in edges:
        out[label, 0, a].add(b)
        out[label, 1, b].add(a)
    walks, found = {((), seed)}, set()
    for _ in range(longest + 1):
        found |= {v for w, v in walks if expr_accepts(w)}
        walks = {((*w, s), x) for w, v in walks for s in steps for x in out[(*s, v)]}
    return found
