"""Path queries with fixed ends, and their SQL and table-function surfaces."""

from __future__ import annotations

import re
import time
from collections.abc import Callable, Iterable
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from ..functions.automaton import compile_expr
from ..functions.expr import Expr, ParseError, parse_pattern
from ..operators.reach import THRESHOLD, traverse
from ..sources.graph import LabeledGraph
from ..sources.store import scratch


@dataclass(frozen=True)
class PathQuery:
    """An expression with beginnings and ends: None (all vertices), numbers, or a table with one column."""

    expr: Expr
    sources: object = None
    finals: object = None

    @classmethod
    def from_source(cls, text: str | Expr, v: int) -> PathQuery:
        return cls(parse_pattern(text) if isinstance(text, str) else text, [v], None)

    @classmethod
    def to_target(cls, text: str | Expr, v: int) -> PathQuery:
        return cls(parse_pattern(text) if isinstance(text, str) else text, None, [v])


def _table(graph: LabeledGraph, ends) -> DataFrame:
    if isinstance(ends, DataFrame):
        return ends.select(F.col(ends.columns[0]).cast("long").alias("v")).distinct()
    return graph.spark.createDataFrame([(int(v),) for v in dict.fromkeys(ends)], "v long")


def evaluate(graph: LabeledGraph, query: PathQuery, method: str = "hybrid", threshold: float = THRESHOLD, minimize: bool = True, **how) -> DataFrame:
    """seed, v: beginnings and ends of paths that spell a word of the expression.

    With ends fixed on one side only the traversal starts there; with both, on the side of fewer vertices, and the other one filters.
    """
    automaton = compile_expr(query.expr, minimize)
    run = lambda a, seeds: traverse(graph, a, seeds, method, threshold, **how).answers()
    backward = query.sources is None and query.finals is not None
    if query.sources is not None and query.finals is not None and not isinstance(query.finals, DataFrame):
        backward = isinstance(query.sources, DataFrame) or len(query.finals) < len(query.sources)
    if backward:
        found = run(automaton.reverse(), query.finals).select(F.col("v").alias("seed"), F.col("seed").alias("v"))
        return found if query.sources is None else found.join(_table(graph, query.sources).withColumnRenamed("v", "seed"), "seed", "left_semi")
    seeds = graph.vertices([x for x, _ in query.expr.steps()]) if query.sources is None else query.sources
    found = run(automaton, seeds)
    return found if query.finals is None else found.join(_table(graph, query.finals), "v", "left_semi").select("seed", "v")


_STATEMENT = re.compile(r"\s*PATHS\s+(?P<expr>.+?)(?:\s+FROM\s+(?P<source>\d+))?(?:\s+TO\s+(?P<target>\d+))?(?:\s+AS\s+(?P<view>\w+))?\s*;?\s*", re.IGNORECASE | re.DOTALL)


def rpq_sql(graph: LabeledGraph, statement: str) -> DataFrame:
    """``PATHS <expression> [FROM <vertex>] [TO <vertex>] [AS <view>]``: the answers, and a temporary view of them."""
    m = _STATEMENT.fullmatch(statement)
    if not m:
        raise ParseError(f"no PATHS statement: {statement!r}")
    ends = {k: [int(m[k])] if m[k] else None for k in ("source", "target")}
    found = evaluate(graph, PathQuery(parse_pattern(m["expr"]), ends["source"], ends["target"]))
    if m["view"]:
        found.createOrReplaceTempView(m["view"])
    return found


def register_functions(spark: SparkSession) -> None:
    """vid(kind, key), path_query(expression) and path_accepts(expression, words) for SQL."""
    from ..functions.vertices import ROOM

    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION vid(kind BIGINT, key BIGINT) RETURNS BIGINT RETURN kind * {ROOM} + key")
    spark.udtf.register("path_query", PathAutomaton)


@udtf(returnType="q: int, label: string, inv: int, q2: int, is_start: boolean, is_final: boolean")
class PathAutomaton:
    """Transitions of an expression's minimal automaton; is_start is about q, is_final about q2."""

    def eval(self, text: str):
        a = compile_expr(parse_pattern(text))
        for q, label, inv, q2 in a.rows():
            yield q, label, inv, q2, q in a.starts, q2 in a.finals


def accepts_udf(text: str):
    """A vectorised function: does a word (labels joined by blanks, ^ for inverted) belong to the expression?"""
    automaton = compile_expr(parse_pattern(text))

    @F.pandas_udf("boolean")
    def accepts(words: pd.Series) -> pd.Series:
        return words.map(lambda w: None if w is None else automaton.accepts([(x.lstrip("^"), int(x.startswith("^"))) for x in w.split()]))

    return accepts


@dataclass
class Outcome:
    """status: ok, timeout or error; ms of the run; number of answers."""

    status: str
    ms: float
    n: int | None


def run_with_limit(spark: SparkSession, work: Callable[[], DataFrame], seconds: float = 60, name: str = "query") -> Outcome:
    """Compute all columns of all answers of work in a job group of its own, and count them.

    From the limit on every job of the group is cancelled, those that start later too, so a run between two jobs ends at its next one. A run
    that takes longer than the limit is a timeout however it ends. Tables written on the way are deleted.
    """
    import threading
    import uuid

    group, done = f"{name}-{uuid.uuid4().hex}", threading.Event()

    def guard() -> None:
        if not done.wait(seconds):
            while not done.wait(0.05):
                spark.sparkContext.cancelJobGroup(group)

    began, status, n = time.perf_counter(), "ok", None
    spark.sparkContext.setJobGroup(group, name, True)
    watch = threading.Thread(target=guard, daemon=True)
    watch.start()
    try:
        with scratch(spark):
            found = work()
            n = found.agg(F.count("*"), F.bit_xor(F.xxhash64(*found.columns))).first()[0]
    except Exception:
        status = "error"
    finally:
        done.set()
        watch.join()
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
        spark.sparkContext.setLocalProperty("spark.job.interruptOnCancel", None)
    took = time.perf_counter() - began
    if took >= seconds:
        status, n = "timeout", None
    return Outcome(status, took * 1000, n)


def time_methods(spark: SparkSession, runs: dict[str, Callable[[], DataFrame]], seconds: float = 60, warm: int = 1, times: int = 3) -> dict[str, Outcome]:
    """Each method's median outcome after warm-up runs, one at a time."""
    out = {}
    for name, work in runs.items():
        for _ in range(warm):
            run_with_limit(spark, work, seconds, name)
        found = sorted((run_with_limit(spark, work, seconds, name) for _ in range(times)), key=lambda o: o.ms)
        out[name] = found[len(found) // 2]
    return out


def timings(spark: SparkSession, runs: Iterable[tuple[str, str, str, Callable[[], DataFrame]]], seconds: float = 60, warm: int = 0) -> DataFrame:
    """system, query, grp, ms, status (as in measures.TIMING) of runs (system, query, group, work), one after the other, each after warm runs."""
    from .measures import TIMING

    rows = []
    for system, query, grp, work in runs:
        for _ in range(warm):
            run_with_limit(spark, work, seconds, query)
        found = run_with_limit(spark, work, seconds, query)
        rows.append((system, query, grp, found.ms, found.status))
    return spark.createDataFrame(rows, TIMING)


def clean_workload(graph: LabeledGraph, queries: Iterable[tuple[str, str, int | None, int | None]]) -> DataFrame:
    """name, kept, reason for queries (name, expression, source, target): those without a fixed end, with an unknown end vertex, or of which no label is in the graph, go."""
    rows = [(name, parse_pattern(text), s if s is not None else t) for name, text, s, t in queries]
    have = set(graph.labels())
    ends = sorted({v for _, _, v in rows if v is not None})
    known = set()
    if ends:
        found = graph.vertices(sorted({x for _, e, _ in rows for x, _ in e.steps() if x in have})).filter(F.col("v").isin(ends))
        known = {r[0] for r in found.collect()}

    def reason(e: Expr, v: int | None) -> str | None:
        if v is None:
            return "no fixed end"
        if v not in known:
            return "missing vertex"
        return None if any(x in have for x, _ in e.steps()) else "missing label"

    judged = [(name, reason(e, v)) for name, e, v in rows]
    return graph.spark.createDataFrame([(n, r is None, r or "") for n, r in judged], "query string, kept boolean, reason string")


def drop_trivial(answers: DataFrame, nullable: bool) -> DataFrame:
    """Answers (seed, v) without the seeds whose one answer is the seed itself, for an expression that has the empty word."""
    if not nullable:
        return answers
    own = answers.groupBy("seed").agg(F.count("*").alias("_n"), F.max(F.col("seed") == F.col("v")).alias("_own"))
    return answers.join(own.filter((F.col("_n") == 1) & F.col("_own")), "seed", "left_anti")
