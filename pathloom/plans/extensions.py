"""Beyond the base methods: rare-label start, push and pull, lengths, witnesses, counts, simple paths, and a choice of method by cost."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.automaton import Automaton, compile_expr
from ..functions.expr import Concat, Empty, Expr, Label, concat
from ..operators.levels import KEYS, Plan, Seen
from ..operators.reach import hybrid_reach, trace_reach, traverse
from ..sources.graph import LabeledGraph
from ..sources.store import written
from .exalg import estimate, exalg_reach


def rare_split(graph: LabeledGraph, expr: Expr) -> tuple[Expr, Label, Expr] | None:
    """Prefix, rarest label among the factors every word must pass, suffix; None without such a factor."""
    parts = expr.parts if isinstance(expr, Concat) else (expr,)
    places = [i for i, p in enumerate(parts) if isinstance(p, Label)]
    if not places:
        return None
    stats = graph.stats(sorted({p.name for p in parts if isinstance(p, Label)}))
    i = min(places, key=lambda i: (stats[parts[i].name][0], i))
    return concat(*parts[:i]), parts[i], concat(*parts[i + 1 :])


def rare_label_reach(graph: LabeledGraph, expr: Expr, seeds) -> DataFrame:
    """seed, v: from the edges of the rarest mandatory label backward to the seeds and forward to the ends."""
    split = rare_split(graph, expr)
    if split is None:
        return hybrid_reach(graph, compile_expr(expr), seeds)
    before, label, after = split
    edges = written(graph.hops([(label.name, label.inv)]).select("src", "dst"), "rare")
    asked = seeds.select(F.col(seeds.columns[0]).alias("seed")) if isinstance(seeds, DataFrame) else graph.spark.createDataFrame([(s,) for s in seeds], "seed long")
    if isinstance(before, Empty):
        back = asked.join(edges.select(F.col("src").alias("seed")).distinct(), "seed", "left_semi").select("seed", F.col("seed").alias("src"))
    else:
        back = hybrid_reach(graph, compile_expr(before).reverse(), edges.select("src").distinct()).select(F.col("seed").alias("src"), F.col("v").alias("seed")).join(asked, "seed", "left_semi")
    middle = written(back.join(edges, "src").select("seed", "dst").distinct(), "rare")
    if isinstance(after, Empty):
        return middle.select("seed", F.col("dst").alias("v"))
    ahead = hybrid_reach(graph, compile_expr(after), middle.select("dst").distinct()).select(F.col("seed").alias("dst"), "v")
    return middle.join(ahead, "dst").select("seed", "v").distinct()


def push_pull_reach(graph: LabeledGraph, automaton: Automaton, seed: int, pull_ratio: float = 0.1) -> DataFrame:
    """v. A level pushes the frontier into the edges, or, when the frontier has more than a part of all sources, pulls: edges whose end is
    known are dropped first and the frontier is only tested for membership."""
    plan = Plan(graph, automaton, literal_cap=0)
    edges = reduce(DataFrame.unionAll, plan.edge_tables())
    sources = sum(n[1] for n in graph.stats([x for x, _ in plan.steps]).values())
    known = Seen()
    new, size = known.new(plan.rows((seed, q, seed) for q in automaton.starts), "pushed")
    while size:
        if size < pull_ratio * sources:
            found = plan.step(new, size)
        else:
            ends = edges.join(plan.delta_df(), ["label", "inv"]).select(F.col("q2").alias("q"), F.col("dst").alias("v"), F.col("q").alias("_q"), "src")
            ends = ends.join(known.df().select("q", "v"), ["q", "v"], "left_anti")
            found = ends.join(new.select(F.col("q").alias("_q"), F.col("v").alias("src")), ["_q", "src"], "left_semi").select(F.lit(seed).cast("long").alias("seed"), "q", "v").distinct()
        new, size = known.new(found, "pushed")
    return (known.df() if known.size else new).filter(F.col("q").isin(sorted(automaton.finals))).select("v").distinct()


def distance_reach(graph: LabeledGraph, automaton: Automaton, seeds) -> DataFrame:
    """seed, v, dist: length of the shortest accepted path."""
    found = trace_reach(graph, automaton, seeds).filter(F.col("q").isin(sorted(automaton.finals)))
    return found.groupBy("seed", "v").agg(F.min("level").cast("long").alias("dist"))


def _levels_with(graph: LabeledGraph, automaton: Automaton, seeds, first, carried) -> list[DataFrame]:
    """Levels of the frontier method with further columns: first gives them for the start, carried aggregates them over a pair's steps."""
    plan = Plan(graph, automaton, literal_cap=0)
    start = plan.start(seeds)
    start = plan.rows(start) if isinstance(start, set) else start
    known = Seen(keep=True)
    new, n = known.new(start.select("*", *first), "level")
    levels, delta = [new], plan.delta_df()
    while n:
        parts = [new.join(delta, "q").join(e.withColumnRenamed("src", "v"), ["v", "label", "inv"]) for e in plan.edge_tables()]
        found = reduce(DataFrame.unionAll, parts).groupBy("seed", F.col("q2"), "dst").agg(*carried).withColumnRenamed("q2", "q").withColumnRenamed("dst", "v")
        new, n = known.new(found, "level")
        levels.append(new)
    return levels


def count_shortest(graph: LabeledGraph, automaton: Automaton, seeds) -> DataFrame:
    """seed, v, dist, n: number of shortest accepted runs. With a deterministic automaton these are shortest labelled paths."""
    levels = _levels_with(graph, automaton, seeds, [F.lit(1).cast("long").alias("n")], [F.sum("n").alias("n")])
    rows = reduce(DataFrame.unionByName, (x.withColumn("dist", F.lit(i).cast("long")) for i, x in enumerate(levels)))
    final = rows.filter(F.col("q").isin(sorted(automaton.finals))).groupBy("seed", "v", "dist").agg(F.sum("n").alias("n"))
    best = final.groupBy("seed", "v").agg(F.min_by(F.struct("dist", "n"), "dist").alias("b"))
    return best.select("seed", "v", "b.dist", "b.n")


def witness_reach(graph: LabeledGraph, automaton: Automaton, seeds) -> DataFrame:
    """seed, v, path: for each answer one shortest path as an array of (label, inv, v) steps. The least parent is kept for each pair."""
    parent = F.struct(F.col("q").alias("pq"), F.col("v").alias("pv"), "label", "inv")
    none = F.lit(None).cast("struct<pq:int,pv:long,label:string,inv:int>").alias("parent")
    levels = _levels_with(graph, automaton, seeds, [none], [F.min(parent).alias("parent")])
    step = "array<struct<label:string,inv:int,v:long>>"
    out = None
    finals = F.col("q").isin(sorted(automaton.finals))
    walking = None
    for i in range(len(levels) - 1, -1, -1):
        ends = levels[i].filter(finals).select("seed", F.col("v").alias("end"), F.lit(i).alias("dist"), "q", "v", F.array().cast(step).alias("path"))
        here = ends if walking is None else ends.unionByName(walking)
        if i == 0:
            out = here.select("seed", F.col("end").alias("v"), "dist", "path")
            break
        joined = here.join(levels[i], KEYS)
        grown = F.concat(F.array(F.struct(F.col("parent.label").alias("label"), F.col("parent.inv").alias("inv"), F.col("v"))), F.col("path"))
        walking = written(joined.select("seed", "end", "dist", F.col("parent.pq").alias("q"), F.col("parent.pv").alias("v"), grown.alias("path")), "walk")
    return out.groupBy("seed", "v").agg(F.min_by("path", F.struct("dist", F.col("path").cast("string"))).alias("path"))


def simple_paths(graph: LabeledGraph, automaton: Automaton, seeds, max_len: int) -> DataFrame:
    """seed, v, path (vertices): all accepted paths of at most max_len edges that visit no vertex twice."""
    plan = Plan(graph, automaton, literal_cap=0)
    start = plan.start(seeds)
    now = (plan.rows(start) if isinstance(start, set) else start).withColumn("path", F.array("v"))
    out, delta = [now], plan.delta_df()
    for _ in range(max_len):
        parts = [now.join(delta, "q").join(e.withColumnRenamed("src", "v"), ["v", "label", "inv"]) for e in plan.edge_tables()]
        found = reduce(DataFrame.unionAll, parts).filter(~F.array_contains("path", F.col("dst")))
        now = written(found.select("seed", F.col("q2").alias("q"), F.col("dst").alias("v"), F.concat("path", F.array("dst")).alias("path")).distinct(), "simple")
        if now.isEmpty():
            break
        out.append(now)
    return reduce(DataFrame.unionByName, out).filter(F.col("q").isin(sorted(automaton.finals))).select("seed", "v", "path").distinct()


def choose(graph: LabeledGraph, expr: Expr) -> str:
    """rare_label if a mandatory label is far rarer than what comes before it, exalg if the whole relation is small, else hybrid."""
    stats = graph.stats(sorted({x for x, _ in expr.steps()}))
    whole = estimate(expr, stats).n
    split = rare_split(graph, expr)
    if split and not isinstance(split[0], Empty):
        n = stats[split[1].name][0]
        others = [stats[x][0] for x, _ in split[0].steps()]
        if others and n * 20 < max(others):
            return "rare_label"
    return "exalg" if whole < 1000 and not expr.nullable() else "hybrid"


def auto_reach(graph: LabeledGraph, expr: Expr, seed: int, method: str | None = None) -> DataFrame:
    """v by the method that choose() names."""
    method = method or choose(graph, expr)
    if method == "rare_label":
        return rare_label_reach(graph, expr, [seed]).select("v")
    if method == "exalg":
        return exalg_reach(graph, expr, source=seed, eager=False)
    return traverse(graph, compile_expr(expr), [seed]).answers().select("v")
