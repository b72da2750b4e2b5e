"""The expression-algebra evaluator: one relation for each node of the expression, restricted at the fixed end, products reordered by size.

A node is evaluated whole, or seeded at its left or right end by a set of vertices. With eager=True a compound node that does not
touch the fixed end is formed whole before it is multiplied, which is the evaluator's known weakness; eager=False seeds through.
The seeds are the first factor of a chain of products, so the cheapest order of the chain is found with them in it: mostly from the fixed end on, but
factors far from it are multiplied first where that is estimated to be cheaper.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.expr import Alt, Concat, Empty, Expr, Label, Opt, Plus, Star
from ..operators import relation as rel
from ..operators.bitmask import SEEDS, numbered_blocks, packed_levels
from ..operators.levels import Seen
from ..operators.walks import LONG, Jumps
from ..sources.graph import LabeledGraph
from ..sources.store import written

CLOSURE_GUESS = 8


@dataclass(frozen=True)
class Size:
    """Estimated entries, distinct rows and distinct columns of a relation."""

    n: float
    rows: float
    cols: float


def estimate(e: Expr, stats: dict[str, tuple[int, int, int]]) -> Size:
    if isinstance(e, Empty):
        return Size(1, 1, 1)
    if isinstance(e, Label):
        n, src, dst = stats.get(e.name, (0, 0, 0))
        return Size(n, dst, src) if e.inv else Size(n, src, dst)
    if isinstance(e, Alt):
        parts = [estimate(p, stats) for p in e.parts]
        return Size(*(sum(getattr(p, f) for p in parts) for f in ("n", "rows", "cols")))
    if isinstance(e, Concat):
        out = estimate(e.parts[0], stats)
        for p in e.parts[1:]:
            out = product_size(out, estimate(p, stats))
        return out
    body = estimate(e.body, stats)
    if isinstance(e, Opt):
        return body
    return Size(min(body.rows * body.cols, body.n * CLOSURE_GUESS), body.rows, body.cols)


def product_size(a: Size, b: Size) -> Size:
    n = min(a.n * b.n / max(a.cols, b.rows, 1), a.rows * b.cols)
    return Size(n, min(a.rows, n), min(b.cols, n))


def product_order(sizes: list[Size]) -> tuple[float, list]:
    """Cost and bracketing (nested pairs of places) of the cheapest order of a chain of products, by the sum of intermediate sizes."""
    k = len(sizes)
    best: dict[tuple[int, int], tuple[float, Size, object]] = {(i, i): (0.0, s, i) for i, s in enumerate(sizes)}
    for span in range(1, k):
        for i in range(k - span):
            j = i + span
            options = []
            for m in range(i, j):
                ca, sa, pa = best[i, m]
                cb, sb, pb = best[m + 1, j]
                size = product_size(sa, sb)
                options.append((ca + cb + size.n, m, size, [pa, pb]))
            cost, _, size, plan = min(options, key=lambda o: o[:2])
            best[i, j] = (cost, size, plan)
    return best[0, k - 1][0], best[0, k - 1][2]


class Algebra:
    """Evaluates expressions over one graph."""

    def __init__(self, graph: LabeledGraph, reorder: bool = True, eager: bool = True, kernel: str = "packed"):
        if kernel not in ("packed", "shared"):
            raise ValueError(kernel)
        self.graph, self.reorder, self.eager, self.kernel = graph, reorder, eager, kernel
        self.formed: list[str] = []
        self.orders: list = []
        self.seeds = 1
        self._packed: dict[Label, DataFrame] = {}

    @property
    def spark(self):
        return self.graph.spark

    def stats(self, e: Expr) -> dict[str, tuple[int, int, int]]:
        return self.graph.stats(sorted({label for label, _ in e.steps()}))

    def leaf(self, e: Label) -> DataFrame:
        if e.name not in set(self.graph.labels()):
            return rel.zero(self.spark)
        a, b = ("dst", "src") if e.inv else ("src", "dst")
        return self.graph.edges(e.name).select(F.col(a).alias("row"), F.col(b).alias("col"))

    def packed(self, e: Label) -> DataFrame:
        """row, cols: the label's matrix with one row for each vertex."""
        if e not in self._packed:
            self._packed[e] = self.leaf(e).groupBy("row").agg(F.collect_list("col").alias("cols"))
        return self._packed[e]

    def vertices(self) -> DataFrame:
        return self.graph.vertices()

    def times(self, a: DataFrame, e: Expr) -> DataFrame:
        """a times the relation of e, which is formed whole unless it is a label."""
        if self.kernel == "packed" and isinstance(e, Label):
            return a.join(self.packed(e).withColumnRenamed("row", "_mid"), a["col"] == F.col("_mid")).select("row", F.explode("cols").alias("col")).distinct()
        return rel.compose(a, self.whole(e))

    def whole(self, e: Expr) -> DataFrame:
        """The relation of e over all vertices; of nullable repetitions with the identity on all vertices."""
        if isinstance(e, Label):
            return self.leaf(e)
        self.formed.append(str(e))
        if isinstance(e, Empty):
            return rel.identity(self.vertices())
        if isinstance(e, Alt):
            out = self.whole(e.parts[0])
            for p in e.parts[1:]:
                out = out.unionByName(self.whole(p))
            return out.distinct()
        if isinstance(e, Concat):
            if not self.reorder:
                out = self.whole(e.parts[0])
                for p in e.parts[1:]:
                    out = self.times(out, p)
                return out

            def build(plan) -> DataFrame:
                return self.whole(e.parts[plan]) if isinstance(plan, int) else rel.compose(build(plan[0]), build(plan[1]))

            stats = self.stats(e)
            return build(product_order([estimate(p, stats) for p in e.parts])[1])
        if isinstance(e, Opt):
            return rel.union(self.whole(e.body), rel.identity(self.vertices()))
        return rel.closure(self.whole(e.body), self.vertices() if isinstance(e, Star) else None)

    def seeded(self, e: Expr, pairs: DataFrame) -> DataFrame:
        """(row, col) with pairs (row, mid) extended by e: the fixed end's vertices travel through e from the left."""
        if isinstance(e, Empty):
            return pairs
        if isinstance(e, Label):
            return self.times(pairs, e)
        if isinstance(e, Alt):
            out = self.seeded(e.parts[0], pairs)
            for p in e.parts[1:]:
                out = out.unionByName(self.seeded(p, pairs))
            return out.distinct()
        if isinstance(e, Concat):
            return self.chain(e, pairs)
        if isinstance(e, Opt):
            return rel.union(pairs, self.seeded(e.body, pairs))
        # A repetition at the fixed end: levels from the seeds with the body's relation, which is formed whole if it is compound and eager.
        step = (lambda x: self.times(x, e.body)) if isinstance(e.body, Label) or self.eager else (lambda x: self.seeded(e.body, x))
        if not isinstance(e.body, Label) and self.eager:
            body = written(self.whole(e.body), "body")
            step = lambda x: rel.compose(x, body)
        base = written(pairs, "seeds")
        if not isinstance(e.body, Label) and self.eager and self.seeds > SEEDS:
            out = self.repeated(base, body)
            return rel.union(out, base) if isinstance(e, Star) else out
        found = Seen(["row", "col"])
        new, n = found.new(step(base), "seeded")
        first, level, jumps = new, 1, None
        while n:
            if level == LONG and isinstance(e.body, Label):
                jumps = Jumps(self.leaf(e.body).select(F.col("row").alias("src"), F.col("col").alias("dst")))
            if level == LONG and jumps is not None and jumps.single():  # all that is left of the walks in one closure
                far, _ = jumps.closure(new.select("row", F.col("col").alias("v")), ["row"])
                new, n = found.new(far.withColumnRenamed("v", "col"), "seeded")
            level += 1
            new, n = found.new(step(new), "seeded")
        out = found.df() if found.size else first
        return rel.union(out, base) if isinstance(e, Star) else out

    def repeated(self, base: DataFrame, body: DataFrame) -> DataFrame:
        """base times body once or more. Many rows of base share an entry of the product, with one bit for each, so an entry of body is met once for all of them."""
        placed = written(numbered_blocks(base.select("row")), "seeds")
        new = base.join(placed, base["row"] == placed["seed"]).groupBy("block", "col").agg(F.bit_or(F.expr("shiftleft(1L, bit)")).alias("mask"))
        new = written(new, "seeds")
        none = new.select("block", "col", F.lit(0).cast("long").alias("mask"))
        inner = body.select(F.col("row").alias("_mid"), F.col("col").alias("_to"))
        found = packed_levels(none, new, lambda x: x.join(inner, x["col"] == F.col("_mid")).select("block", F.col("_to").alias("col"), "mask"), ["block", "col"])
        return found.join(placed, "block").filter(F.expr("shiftright(mask, bit) & 1 = 1")).select(F.col("seed").alias("row"), "col")

    def chain(self, e: Concat, pairs: DataFrame) -> DataFrame:
        """pairs times the factors of e, in the cheapest order of the products of seeds and factors, or one factor after the other."""
        order: object = 0
        for i in range(1, len(e.parts) + 1):
            order = [order, i]
        if self.reorder:
            stats = self.stats(e)
            order = product_order([Size(self.seeds, self.seeds, self.seeds), *(estimate(p, stats) for p in e.parts)])[1]
        self.orders.append(order)

        def whole(plan) -> DataFrame:
            return self.whole(e.parts[plan - 1]) if isinstance(plan, int) else rel.compose(whole(plan[0]), whole(plan[1]))

        def build(plan) -> DataFrame:
            """The product of a part of the chain that begins with the seeds."""
            if plan == 0:
                return pairs
            left = build(plan[0])
            if not isinstance(plan[1], int):
                return rel.compose(left, whole(plan[1]))
            p = e.parts[plan[1] - 1]
            return self.seeded(p, left) if plan[1] == 1 or isinstance(p, Label) or not self.eager else self.away(p, left)

        return build(order)

    def away(self, e: Expr, pairs: DataFrame) -> DataFrame:
        """pairs times a compound e that does not touch the fixed end: e is formed whole; the identity of e? and e* is added to the product."""
        if isinstance(e, (Star, Opt)):
            inner = Plus(e.body) if isinstance(e, Star) else e.body
            return rel.union(pairs, rel.compose(pairs, self.whole(inner)))
        return rel.compose(pairs, self.whole(e))


def exalg_pairs(graph: LabeledGraph, expr: Expr, seeds: DataFrame, end: str = "source", reorder: bool = True, restrict: bool = True, eager: bool = True, kernel: str = "packed", algebra: list | None = None, n: int | None = None) -> DataFrame:
    """seed, v: for each seed (a table with one column, of n rows) the ends of paths from it, or with end="target" the beginnings of paths to it.

    Targets are sources of the inverse expression. algebra, if given, receives the evaluator.
    """
    e = expr if end == "source" else expr.inverse()
    work = Algebra(graph, reorder, eager, kernel)
    if algebra is not None:
        algebra.append(work)
    seed = seeds.select(F.col(seeds.columns[0]).cast("long").alias("row")).filter("row is not null").distinct().withColumn("col", F.col("row"))
    if n is None:
        seed = written(seed, "seeds")
        n = seed.count()
    work.seeds = max(1, n)
    found = work.seeded(e, seed) if restrict else rel.rows_of(work.whole(e), seed.select(F.col("row").alias("v")))
    found = rel.union(found, seed) if e.nullable() else found  # seeds that the graph lacks have their zero-length path too
    return found.select(F.col("row").alias("seed"), F.col("col").alias("v")).distinct()


def exalg_reach(
    graph: LabeledGraph, expr: Expr, source: int | None = None, target: int | None = None, reorder: bool = True, restrict: bool = True, eager: bool = True, kernel: str = "packed", algebra: list | None = None
) -> DataFrame:
    """v: ends of paths from source, or beginnings of paths to target; with both, target itself if a path joins them."""
    if source is None and target is None:
        raise ValueError("no fixed end")
    start, end = (source, "source") if source is not None else (target, "target")
    seed = graph.spark.createDataFrame([(start,)], "v long")
    out = exalg_pairs(graph, expr, seed, end, reorder, restrict, eager, kernel, algebra, 1).select("v")
    return out.filter(F.col("v") == target) if source is not None and target is not None else out
