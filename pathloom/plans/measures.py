"""Cost measures of timed queries, sizes of layouts, and the split into simple and complex queries.

Timings are tables (system, query, grp, ms, status); the method measured against is named.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources.graph import HOP, LabeledGraph, dictionary
from ..sources.store import stored_size, written

TIMING = "system string, query string, grp string, ms double, status string"


def summarize(times: DataFrame) -> DataFrame:
    """system, grp, n, total_ms, mean_ms, median_ms over the runs that ended well; medians are exact."""
    done = times.filter("status = 'ok'")
    return done.groupBy("system", "grp").agg(F.count("*").alias("n"), F.sum("ms").alias("total_ms"), F.avg("ms").alias("mean_ms"), F.percentile("ms", F.lit(0.5)).alias("median_ms"))


def relative_speedup(times: DataFrame, ours: str) -> DataFrame:
    """system, grp, mean_speedup, median_speedup (ours / other), times_slower_mean, times_slower_median (other / ours)."""
    s = summarize(times)
    base = s.filter(F.col("system") == ours).select("grp", F.col("mean_ms").alias("_mean"), F.col("median_ms").alias("_median"))
    both = s.join(base, "grp")
    return both.select(
        "system", "grp", (F.col("_mean") / F.col("mean_ms")).alias("mean_speedup"), (F.col("_median") / F.col("median_ms")).alias("median_speedup"),
        (F.col("mean_ms") / F.col("_mean")).alias("times_slower_mean"), (F.col("median_ms") / F.col("_median")).alias("times_slower_median"),
    )


def status_counts(times: DataFrame) -> DataFrame:
    return times.groupBy("system", "status").agg(F.count("*").alias("n"))


def distribution(times: DataFrame, at=(0.0, 0.25, 0.5, 0.75, 0.9, 1.0)) -> DataFrame:
    """system, grp, mean_ms and the given percentiles of ms."""
    done = times.filter("status = 'ok'")
    return done.groupBy("system", "grp").agg(F.avg("ms").alias("mean_ms"), *(F.percentile("ms", F.lit(p)).alias(f"p{round(100 * p)}") for p in at))


def classify(expressible: DataFrame, times: DataFrame) -> DataFrame:
    """query, grp: simple if every system can state it (query, expressible) and none failed on it, else complex."""
    failed = times.filter("status <> 'ok'").select("query").distinct().withColumn("_failed", F.lit(True))
    simple = F.col("expressible") & F.col("_failed").isNull()
    return expressible.join(failed, "query", "left").select("query", F.when(simple, "simple").otherwise("complex").alias("grp"))


def per_pattern(times: DataFrame) -> DataFrame:
    """query, system, total_ms: sums over the seeds of a pattern."""
    return times.filter("status = 'ok'").groupBy("query", "system").agg(F.sum("ms").alias("total_ms"))


def graph_stats(graph: LabeledGraph, labels=None) -> DataFrame:
    """n_edges, n_vertices, n_labels."""
    e = graph.triples(labels)
    ends = e.select(F.explode(F.array("src", "dst")).alias("v")).agg(F.countDistinct("v").alias("n_vertices"))
    return e.agg(F.count("*").alias("n_edges"), F.countDistinct("label").alias("n_labels")).crossJoin(ends).select("n_edges", "n_vertices", "n_labels")


def bytes_per_triple(total_bytes: Column, edges: Column) -> Column:
    return total_bytes / edges


# Layouts of the edges of a graph.


def adjacency_out(graph: LabeledGraph, labels=None) -> DataFrame:
    """label, src, dsts (sorted): a compressed row for each source."""
    return graph.triples(labels).groupBy("label", "src").agg(F.sort_array(F.collect_set("dst")).alias("dsts"))


def adjacency_in(graph: LabeledGraph, labels=None) -> DataFrame:
    return graph.triples(labels).groupBy("label", "dst").agg(F.sort_array(F.collect_set("src")).alias("srcs"))


def unpacked(adjacency: DataFrame) -> DataFrame:
    return adjacency.select("label", "src", F.explode("dsts").alias("dst"))


def quadtree(matrix: DataFrame, levels: int) -> DataFrame:
    """level, i, j, bits of a 2^levels square matrix (row, col from 0): for each node with entries below it, which of its 4 children have some.

    The tree is stored top down, 4 bits a node, so its size is 4 times the rows here.
    """
    out = None
    for level in range(levels):
        down = levels - level
        child = lambda c: F.shiftright(c, down - 1)
        bit = F.call_function("shiftleft", F.lit(1), ((child(F.col("row")) % 2) * 2 + child(F.col("col")) % 2).cast("int"))
        nodes = matrix.groupBy(F.shiftright("row", down).alias("i"), F.shiftright("col", down).alias("j")).agg(F.bit_or(bit).alias("bits")).select(F.lit(level).alias("level"), "i", "j", "bits")
        out = nodes if out is None else out.unionAll(nodes)
    return out


def quadtree_decode(tree: DataFrame, levels: int) -> DataFrame:
    """row, col of the entries, from the top down."""
    spark = tree.sparkSession
    now = spark.createDataFrame([(0, 0)], "i long, j long")
    for level in range(levels):
        here = tree.filter(F.col("level") == level).select("i", "j", "bits")
        split = now.join(here, ["i", "j"]).select("i", "j", "bits", F.explode(F.array(*(F.lit(k) for k in range(4)))).alias("k"))
        now = split.filter(F.expr("shiftright(bits, k) & 1 = 1")).select((F.col("i") * 2 + F.floor(F.col("k") / 2)).alias("i"), (F.col("j") * 2 + F.col("k") % 2).alias("j"))
    return now.select(F.col("i").alias("row"), F.col("j").alias("col"))


def layout_bytes(graph: LabeledGraph, layout: str, labels=None) -> DataFrame:
    """label, bytes of a layout with 8-byte numbers: pairs, adjacency_out, adjacency_in, both."""
    s = graph.label_stats(labels)
    size = {
        "pairs": F.col("n") * 16,
        "adjacency_out": (F.col("n_src") + 1) * 8 + F.col("n_src") * 8 + F.col("n") * 8,
        "adjacency_in": (F.col("n_dst") + 1) * 8 + F.col("n_dst") * 8 + F.col("n") * 8,
        "both": (F.col("n_src") + F.col("n_dst") + 2) * 8 + (F.col("n_src") + F.col("n_dst")) * 8 + F.col("n") * 16,
    }[layout]
    return s.select("label", size.cast("long").alias("bytes"))


def footprint(graph: LabeledGraph, layout: str = "both", labels=None) -> DataFrame:
    """n_edges, bytes, bytes_per_triple of the whole graph in a layout."""
    sizes = layout_bytes(graph, layout, labels).agg(F.sum("bytes").alias("bytes"))
    edges = graph.label_stats(labels).agg(F.sum("n").alias("n_edges"))
    return edges.crossJoin(sizes).select("n_edges", "bytes", bytes_per_triple(F.col("bytes"), F.col("n_edges")).alias("bytes_per_triple"))


LAYOUTS = ("pairs", "rows", "columns", "both", "quadtree")


class LaidOut(LabeledGraph):
    """A graph whose edges are stored in a layout and read from it by any evaluator.

    pairs: one copy of (src, dst). rows: a compressed row for each source, which inverted steps unpack and turn round; columns: the reverse. both: rows
    for forward and columns for inverted steps, so that each direction reads the copy keyed by the vertex it comes from. quadtree: a bitmap tree over
    the label's vertices, numbered densely, decoded from the top down. A label is laid out at its first use.
    """

    def __init__(self, graph: LabeledGraph, layout: str = "both"):
        if layout not in LAYOUTS:
            raise ValueError(layout)
        self.graph, self.layout, self.spark, self._laid = graph, layout, graph.spark, {}

    def labels(self) -> list[str]:
        return self.graph.labels()

    def _stored(self, label: str, kind: str) -> DataFrame:
        if (label, kind) not in self._laid:
            make = {"pairs": lambda: self.graph.triples([label]), "rows": lambda: adjacency_out(self.graph, [label]), "columns": lambda: adjacency_in(self.graph, [label])}[kind]
            self._laid[label, kind] = written(make(), f"layout-{kind}", lasting=True)
        return self._laid[label, kind]

    def _tree(self, label: str) -> tuple[DataFrame, DataFrame, int]:
        """The tree of a label, its vertices (v, key from 1), and the number of levels."""
        if (label, "quadtree") not in self._laid:
            e = self.graph.edges(label)
            numbers = written(dictionary(F.col("v"), e.select(F.col("src").alias("v")).unionAll(e.select(F.col("dst").alias("v"))), "v"), "numbers", lasting=True)
            levels = max(1, int(numbers.count()).bit_length())
            a, b = numbers.select(F.col("v").alias("src"), F.col("key").alias("row")), numbers.select(F.col("v").alias("dst"), F.col("key").alias("col"))
            self._laid[label, "quadtree"] = (written(quadtree(written(e.join(a, "src").join(b, "dst").select("row", "col"), "matrix"), levels), "quadtree", lasting=True), numbers, levels)
        return self._laid[label, "quadtree"]

    def _read(self, label: str, inv: int) -> DataFrame:
        """src, dst of a label for a step that goes along it (0) or against it (1)."""
        kind = {"both": "columns" if inv else "rows"}.get(self.layout, self.layout)
        if kind == "quadtree":
            tree, numbers, levels = self._tree(label)
            a, b = numbers.select(F.col("v").alias("src"), F.col("key").alias("row")), numbers.select(F.col("v").alias("dst"), F.col("key").alias("col"))
            return quadtree_decode(tree, levels).join(a, "row").join(b, "col").select("src", "dst")
        stored = self._stored(label, kind)
        if kind == "pairs":
            return stored.select("src", "dst")
        return stored.select("src", F.explode("dsts").alias("dst")) if kind == "rows" else stored.select(F.explode("srcs").alias("src"), "dst")

    def edges(self, label: str) -> DataFrame:
        return self._read(label, 0)

    def hops(self, steps) -> DataFrame:
        have, out = set(self.labels()), None
        for label, inv in sorted(steps):
            if label in have:
                a, b = ("dst", "src") if inv else ("src", "dst")
                df = self._read(label, inv).select(F.lit(label).alias("label"), F.lit(inv).alias("inv"), F.col(a).alias("src"), F.col(b).alias("dst"))
                out = df if out is None else out.unionAll(df)
        return self.spark.createDataFrame([], HOP) if out is None else out

    def stored_bytes(self, labels) -> dict[str, int]:
        """Bytes on disk of each label's stored tables, as the file system reports them."""
        out = {}
        for label in labels:
            self._read(label, 0), self._read(label, 1)
            tables = [t for (x, kind), t in self._laid.items() if x == label for t in (t[:2] if kind == "quadtree" else (t,))]
            out[label] = sum(stored_size(t) for t in tables)
        return out


def plan_counters(spark, work: Callable[[], object]) -> dict[str, int]:
    """What the Spark queries that work runs did: rows made by joins, rows shuffled, rows scanned, and the number of queries."""
    store = spark._jsparkSession.sharedState().statusStore()
    before = {store.executionsList().apply(i).executionId() for i in range(store.executionsList().size())}
    work()
    spark._jsc.sc().listenerBus().waitUntilEmpty()
    out, all_ = {"join_rows": 0, "shuffled_rows": 0, "scanned_rows": 0, "queries": 0}, store.executionsList()
    for i in range(all_.size()):
        number = all_.apply(i).executionId()
        if number in before:
            continue
        out["queries"] += 1
        values, nodes = store.executionMetrics(number), store.planGraph(number).allNodes()
        for j in range(nodes.size()):
            node = nodes.apply(j)
            for name, wanted, key in (("Join", "number of output rows", "join_rows"), ("Exchange", "shuffle records written", "shuffled_rows"), ("Scan", "number of output rows", "scanned_rows")):
                if name not in node.name():
                    continue
                metrics = node.metrics()
                for m in range(metrics.size()):
                    if metrics.apply(m).name() == wanted and values.contains(metrics.apply(m).accumulatorId()):
                        out[key] += int(str(values.apply(metrics.apply(m).accumulatorId())).replace(",", "").split()[0])
    return out
