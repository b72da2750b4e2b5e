"""Edge-labelled graphs: one table (label, src, dst) of distinct triples, addressed by label.

GivenTables derives the labels of the given tables on demand; EdgeTable wraps any such table, for example one saved by sources.triples.
"""

from __future__ import annotations

from collections import Counter, defaultdict
from collections.abc import Callable, Iterable, Sequence
from concurrent.futures import ThreadPoolExecutor
from contextlib import suppress
from functools import reduce
from threading import Lock

import pyarrow as pa
from pyspark import InheritableThread, inheritable_thread_target
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.vertices import KINDS, ROOM, vid
from .store import stored_size

EDGE = "label string, src long, dst long"
HOP = "label string, inv int, src long, dst long"
#: Neighbours of a vector in the label near.
NEAREST = 3
#: Scans of a plain label's table before the label is derived, which costs about as much as so many.
PASSES = 4
#: Names of a kind that are numbered on the driver, at most, and the bytes of the longest of them.
FEW, LONGEST = 100, 1000
#: Bytes of the table of a sequence that goes to the driver without its edges being kept and counted before.
BROUGHT = 32 << 20
#: Labels that are planned at a time.
PLANNED = 6


class LabeledGraph:
    """Edges by label. Subclasses give edges(label); what they give is distinct and free of nulls."""

    spark: SparkSession

    def labels(self) -> list[str]:
        raise NotImplementedError

    def edges(self, label: str) -> DataFrame:
        """src, dst of one label."""
        raise NotImplementedError

    def once(self, label: str) -> DataFrame:
        """The same for a single pass over them, after which nothing need be kept."""
        return self.edges(label)

    def planned(self, labels: Sequence[str]) -> list[DataFrame]:
        """once() of some labels."""
        return [self.once(x) for x in labels]

    def triples(self, labels: Iterable[str] | None = None, once: bool = False) -> DataFrame:
        """label, src, dst of the given labels (default: all). once: for a single pass."""
        names = sorted(self.labels() if labels is None else set(labels) & set(self.labels()))
        found = [df.select(F.lit(x).alias("label"), "src", "dst") for x, df in zip(names, self.planned(names) if once else map(self.edges, names), strict=True)]
        out = found[0] if found else self.spark.createDataFrame([], EDGE)
        for df in found[1:]:
            out = out.unionAll(df)
        return out

    def hops(self, steps: Iterable[tuple[str, int]]) -> DataFrame:
        """label, inv, src, dst: the edges of each step, turned round for inverted labels. Labels that the graph lacks give nothing."""
        have, out = set(self.labels()), None
        for label, inv in sorted(steps):
            if label in have:
                a, b = ("dst", "src") if inv else ("src", "dst")
                df = self.edges(label).select(F.lit(label).alias("label"), F.lit(inv).alias("inv"), F.col(a).alias("src"), F.col(b).alias("dst"))
                out = df if out is None else out.unionAll(df)
        return self.spark.createDataFrame([], HOP) if out is None else out

    def passed(self, steps: Iterable[tuple[str, int]]) -> DataFrame:
        """hops() for a join or a filter whose result is made distinct: an edge may come more than once."""
        return self.hops(steps)

    def looked_up(self, label: str, inv: int, sources: Iterable[int]) -> DataFrame:
        """passed() of one step from the given vertices."""
        return self.passed([(label, inv)]).filter(f"src IN ({', '.join(f'{v}L' for v in sorted(sources))})")  # one call, where isin() makes one for each vertex

    def brought(self, label: str, most: int) -> pa.Table | None:
        """src, dst of a label on the driver, or None: only of labels for which that costs no more than to keep them, and of at most so many rows. An edge may
        come more than once."""
        return None

    def ahead(self, labels: Iterable[str], repeated: Iterable[str], most: int) -> None:
        """Begin what looked_up() of these labels, and brought() of those that a state repeats, take, in threads of their own."""

    def label_stats(self, labels: Iterable[str] | None = None) -> DataFrame:
        """label, n, n_src, n_dst: edges, and distinct ends, of each label."""
        return self.triples(labels).groupBy("label").agg(F.count("*").alias("n"), F.countDistinct("src").alias("n_src"), F.countDistinct("dst").alias("n_dst"))

    def stats(self, labels: Iterable[str]) -> dict[str, tuple[int, int, int]]:
        """The same on the driver for the labels of one query; kept, since graphs do not change."""
        known = self.__dict__.setdefault("_stats", {})
        missing = {x for x in labels if x in set(self.labels())} - set(known)
        if missing:
            known.update((r[0], (r[1], r[2], r[3])) for r in self.label_stats(missing).collect())
        return {x: known.get(x, (0, 0, 0)) for x in labels}

    def vertices(self, labels: Iterable[str] | None = None) -> DataFrame:
        e = self.triples(labels)
        return e.select(F.col("src").alias("v")).unionAll(e.select("dst")).distinct()


class EdgeTable(LabeledGraph):
    """A graph in one table (label, src, dst); a table partitioned by label is read one folder a label."""

    def __init__(self, table: DataFrame, labels: Iterable[str] | None = None, distinct: bool = True):
        self.spark = table.sparkSession
        self.table = table.filter("label is not null and src is not null and dst is not null").select("label", F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"))
        self.table = self.table.distinct() if distinct else self.table
        self._labels = sorted(labels) if labels is not None else None

    def labels(self) -> list[str]:
        if self._labels is None:
            self._labels = sorted(r[0] for r in self.table.select("label").distinct().collect())
        return self._labels

    def edges(self, label: str) -> DataFrame:
        return self.table.filter(F.col("label") == label).select("src", "dst")


def dictionary(values: Column, table: DataFrame, name: str = "value") -> DataFrame:
    """name, key: the distinct non-null values, numbered from 1 in their binary order.

    Values are sorted by ranges; each range counts on from the ranges before it, so no task sees all values.
    """
    from .store import forget, written

    sorted_ = written(table.select(values.alias(name)).filter(F.col(name).isNotNull()).distinct().repartitionByRange(name).withColumn("_part", F.spark_partition_id()), "dictionary", lasting=True)
    n, before = 0, F.when(F.col("_part").isNull(), 0)
    for part, size in sorted(map(tuple, sorted_.groupBy("_part").count().collect())):
        before = before.when(F.col("_part") == part, F.lit(n))
        n += size
    place = F.row_number().over(Window.partitionBy("_part").orderBy(name))
    numbered = written(sorted_.select(name, (before.cast("long") + place).alias("key")), "dictionary", lasting=True)
    forget(sorted_)
    return numbered


class GivenTables(LabeledGraph):
    """The 29 labels of the given tables. Edges of a label are derived at first use, then kept in memory and on disk as Spark sees fit."""

    def __init__(self, spark: SparkSession, sf_dir: str, keep: bool = True):
        self.spark, self.sf_dir, self.keep, self._kept, self._read = spark, sf_dir, keep, {}, Counter()
        self._schemas, self._names, self._near, self._locks = {}, {}, {}, defaultdict(Lock)

    def table(self, name: str) -> DataFrame:
        path = f"{self.sf_dir}/{name}.parquet"
        if name not in self._schemas:
            df = self.spark.read.parquet(path)
            self._schemas[name] = df.schema
            return df
        return self.spark.read.schema(self._schemas[name]).parquet(path)

    def labels(self) -> list[str]:
        return sorted(_RULES)

    def edges(self, label: str) -> DataFrame:
        if label not in self._kept:
            df = self.once(label)
            self._kept[label] = df.persist() if self.keep else df
        return self._kept[label]

    def once(self, label: str) -> DataFrame:
        if label in self._kept:
            return self._kept[label]
        return self.rows(label).distinct()

    def rows(self, label: str, where: str | None = None) -> DataFrame:
        """src, dst of a label as the given tables have them, so an edge may come more than once. where: a condition on the table of a label that is scanned."""
        found = _RULES[label](self, where) if where else _RULES[label](self)
        return found.filter("src is not null and dst is not null").select("src", "dst")

    def scanned(self, label: str, maybe: bool = False) -> bool:
        """Whether a label is two columns of one table, be it with a few names to be numbered, and is not to be kept yet. maybe: before the names are counted."""
        if not self.keep or label in self._kept or self._read[label] >= PASSES:
            return False
        return label in _PLAIN or (label in _CALLED and (maybe or self.few(_CALLED[label]) is not None))

    def passed(self, steps: Iterable[tuple[str, int]], where: str | None = None) -> DataFrame:
        """The first PASSES times that a label of two columns of one table is asked for, its rows as they stand there; then the label is derived and kept."""
        out = None
        for label, inv in sorted(set(steps)):
            if self.scanned(label):
                self._read[label] += 1
                a, b = ("dst", "src") if inv else ("src", "dst")
                df = self.rows(label, where).select(F.lit(label).alias("label"), F.lit(inv).alias("inv"), F.col(a).alias("src"), F.col(b).alias("dst"))
            else:
                df = self.hops([(label, inv)])
            out = df if out is None else out.unionAll(df)
        return self.hops([]) if out is None else out

    def looked_up(self, label: str, inv: int, sources: Iterable[int]) -> DataFrame:
        """The same with a condition on the table's own keys, by which files are read in part."""
        end, sources = _KEYS.get(label, (None, None))[inv], sorted(sources)
        where = end(self, sources) if end and sources and self.scanned(label) else None
        return self.passed([(label, inv)], where).filter(f"src IN ({', '.join(f'{v}L' for v in sources)})")

    def brought(self, label: str, most: int) -> pa.Table | None:
        """Labels from a row to the next, if their table is small; they stay on the driver for later queries."""
        if label not in _SEQUENCES or label in self._kept or not self.keep:
            return None
        with self._locks[label]:
            if label not in self._near:
                held = self.rows(label).limit(most + 1).toArrow() if stored_size(self.table(_SEQUENCES[label])) <= BROUGHT else None
                self._near[label] = held if held is not None and held.num_rows <= most else None
            return self._near[label]

    def ahead(self, labels: Iterable[str], repeated: Iterable[str], most: int) -> None:
        """Sequences and the numbers of names: small jobs, which can run beside the scans of the first levels."""
        for label in sorted(labels):
            if label in _SEQUENCES and label in repeated:
                task, args = self.brought, (label, most)
            elif label in _CALLED and self.scanned(label, True):
                task, args = self.few, (_CALLED[label],)
            else:
                continue

            def begin(task=task, args=args):
                with suppress(Exception):  # the traversal meets it when it needs the result
                    task(*args)

            InheritableThread(target=begin, session=self.spark, daemon=True).start()

    def planned(self, labels: Sequence[str]) -> list[DataFrame]:
        """The same at a time: names of vertices are numbered by small jobs of their own, which leave most cores idle one after the other."""
        with ThreadPoolExecutor(PLANNED) as pool:
            return [x.result() for x in [pool.submit(inheritable_thread_target(self.spark)(self.once), label) for label in labels]]

    def close(self) -> None:
        """Give up the edges kept in memory and on disk; a label asked for again is derived again."""
        for df in self._kept.values():
            df.unpersist()
        self._kept.clear()
        for own in (self._read, self._schemas, self._names, self._near):
            own.clear()
        _GRAPHS.pop((self.spark.sparkContext.applicationId, id(self.spark._jsparkSession), self.sf_dir), None)

    def dictionary(self, kind: str) -> DataFrame:
        """value, key of a kind of vertices that is named by text."""
        if kind not in self._kept:
            column, table = _NAMED[kind]
            self._kept[kind] = dictionary(column(), self.hrefs() if kind == "href" else self.table(table))
        return self._kept[kind]

    def few(self, kind: str) -> list[bytes] | None:
        """The names of a kind in their binary order, if they are at most FEW."""
        with self._locks[kind]:
            if kind not in self._names:
                column, table = _NAMED[kind]
                names = (self.hrefs() if kind == "href" else self.table(table)).select(column().alias("value")).filter("value is not null").distinct()
                found = names.select(F.octet_length("value").alias("n"), F.substring(F.col("value").cast("binary"), 1, LONGEST).alias("name")).limit(FEW + 1).toArrow()
                short = found.num_rows <= FEW and all(n <= LONGEST for n in found["n"].to_pylist())
                self._names[kind] = sorted(found["name"].to_pylist()) if short else None
            return self._names[kind]

    def hrefs(self) -> DataFrame:
        """page_id, value: the distinct paths that a page links."""
        return self.table("pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit(r'<a href="(/[^"]*)"'), F.lit(1))).alias("value")).distinct()

    def named(self, rows: DataFrame, kind: str) -> DataFrame:
        """rows (src, value) with dst, the vertex of the value."""
        few = self.few(kind)
        if few:
            place = F.array_position(F.array(*(F.lit(name).cast("string") for name in few)), F.col("value"))
            return rows.filter("value is not null").select("src", vid(kind, place).alias("dst"))
        return rows.join(self.dictionary(kind), "value").select("src", vid(kind, "key").alias("dst"))


def page_host(url: str = "url") -> Column:
    return F.nullif(F.regexp_extract(url, r"://([^/?#]*)", 1), F.lit(""))


#: Kinds of vertices that are named by text: where their names come from.
_NAMED = {
    "event_type": (lambda: F.col("event_type"), "events"), "href": (lambda: F.col("value"), "pages"), "source": (lambda: F.col("source"), "documents"),
    "lang": (lambda: F.col("lang"), "documents"), "brand": (lambda: F.col("p_brand"), "part"), "part_type": (lambda: F.col("p_type"), "part"),
    "segment": (lambda: F.col("c_mktsegment"), "customer"), "priority": (lambda: F.col("o_orderpriority"), "orders"), "host": (lambda: page_host(), "pages"),
}


def _item() -> Column:
    return vid("item", F.col("l_orderkey") * 8 + F.col("l_linenumber"))


def _pair(table: str, src: Callable[[], Column], dst: Callable[[], Column], where: str | None = None) -> Callable[[GivenTables], DataFrame]:
    def rule(g: GivenTables, more: str | None = None) -> DataFrame:
        rows = g.table(table)
        for condition in filter(None, (where, more)):
            rows = rows.filter(condition)
        return rows.select(src().alias("src"), dst().alias("dst"))

    return rule


def _name(table: str, src: Callable[[], Column], kind: str) -> Callable[[GivenTables], DataFrame]:
    def rule(g: GivenTables, more: str | None = None) -> DataFrame:
        rows = g.table(table)
        return g.named((rows.filter(more) if more else rows).select(src().alias("src"), _NAMED[kind][0]().alias("value")), kind)

    return rule


def _next(table: str, kind: str, key: str, within: str, *order: str) -> Callable[[GivenTables], DataFrame]:
    """From each row of a group to the next in the given order."""

    def rule(g: GivenTables) -> DataFrame:
        after = F.lead(key).over(Window.partitionBy(within).orderBy(*order))
        return g.table(table).filter(F.col(within).isNotNull()).select(vid(kind, key).alias("src"), vid(kind, after).alias("dst"))

    return rule


def _ring(rows: DataFrame, group: str, key: str, kind: str, alone: bool) -> DataFrame:
    """From each row of a group to the next by key, from the last to the first."""
    w = Window.partitionBy(group)
    after = F.coalesce(F.lead(key).over(w.orderBy(key)), F.min(key).over(w))
    out = rows.select(F.col(key), after.alias("_after"), F.count("*").over(w).alias("_n"))
    return (out if alone else out.filter("_n > 1")).select(vid(kind, key).alias("src"), vid(kind, "_after").alias("dst"))


def _located(g: GivenTables) -> DataFrame:
    """Item to its supplier's nation, supplier to nation, order to its customer's nation."""
    supplier, customer = g.table("supplier"), g.table("customer")
    nation = vid("nation", "s_nationkey").alias("dst")
    items = g.table("lineitem").join(supplier, F.col("l_suppkey") == F.col("s_suppkey")).select(_item().alias("src"), nation)
    orders = g.table("orders").join(customer, F.col("o_custkey") == F.col("c_custkey")).select(vid("order", "o_orderkey").alias("src"), vid("nation", "c_nationkey").alias("dst"))
    return items.unionAll(supplier.select(vid("supplier", "s_suppkey").alias("src"), nation)).unionAll(orders)


def _reply(g: GivenTables) -> DataFrame:
    number = F.col("conv_id") * 1000 + F.col("turn")
    after = F.lead("_n").over(Window.partitionBy("conv_id").orderBy("turn"))
    return g.table("conversations").withColumn("_n", number).select(vid("turn", "_n").alias("src"), vid("turn", after).alias("dst"))


def _is_customer(g: GivenTables) -> DataFrame:
    users = g.table("events").select(F.col("user_id").alias("k")).distinct()
    return users.join(g.table("customer"), F.col("k") == F.col("c_custkey"), "left_semi").select(vid("user", "k").alias("src"), vid("customer", "k").alias("dst"))


#: Items that are looked for in each document at once.
QUOTED = 50_000


def _quotes(g: GivenTables) -> DataFrame:
    """Documents that contain an item's text: items go to all tasks, at most about QUOTED at a time, so any number of them is compared.

    An item's words between its first and its last space are words of every document that contains it, so an item is compared with the
    documents that hold the longest of them; items with less than two spaces are compared with all documents.
    """
    items, docs = g.table("benchmark").select("item_id", F.col("text").alias("_quoted")), g.table("documents").select("doc_id", "text")
    words = F.split("_quoted", " ")
    inner = F.transform(F.slice(words, 2, F.greatest(F.size(words) - 2, F.lit(0))), lambda w: F.struct(F.length(w).alias("n"), w.alias("w")))
    items = items.withColumn("_key", F.array_max(inner)["w"])
    n = 1 + items.count() // QUOTED
    parts = [items.filter(F.pmod(F.xxhash64("item_id"), F.lit(n)) == i) for i in range(n)] if n > 1 else [items]
    found = []
    for part in parts:
        keys = part.agg(F.collect_set("_key").alias("_keys"))
        held = docs.join(F.broadcast(keys)).withColumn("_key", F.explode(F.array_intersect(F.split("text", " "), "_keys"))).select("doc_id", "text", "_key")
        for rows in (held.join(F.broadcast(part), "_key"), docs.join(F.broadcast(part.filter("_key is null").drop("_key")))):
            found.append(rows.filter(F.contains("text", "_quoted")).select(vid("doc", "doc_id").alias("src"), vid("bench_item", "item_id").alias("dst")))
    return reduce(DataFrame.unionAll, found)


def _near(g: GivenTables, k: int = NEAREST) -> DataFrame:
    """Each vector to its k nearest by cosine of doubles, rounded to 6 digits, ties by id. Every vector against all, in blocks."""
    import numpy as np

    rows = g.table("embeddings").filter("vec_id is not null and embedding is not null").select("vec_id", "embedding")
    blocks = 1 + rows.count() // 4000
    data = rows.select("vec_id", "embedding", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int").alias("block"))
    asked = data.select(F.col("block").alias("part"), "vec_id", "embedding")
    both = asked.withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).withColumn("asks", F.lit(True))
    held = data.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).withColumn("asks", F.lit(False))

    def nearest(key, rows):
        import pandas as pd

        unit = np.stack([np.asarray(x, np.float64) for x in rows["embedding"]])
        unit /= np.maximum(np.linalg.norm(unit, axis=1, keepdims=True), 1e-300)
        asks, ids = rows["asks"].to_numpy(bool), rows["vec_id"].to_numpy()
        if asks.all() or not asks.any():
            return pd.DataFrame({"q": [], "v": [], "s": []})
        like = np.round(unit[asks] @ unit[~asks].T, 6)
        out = []
        own, ranked = ids[~asks], np.where(np.isnan(like), -np.inf, like)
        least = np.partition(ranked, max(0, len(own) - k - 1), axis=1)[:, max(0, len(own) - k - 1)]  # only rows as near as this are sorted
        for q, row, near, low in zip(ids[asks], like, ranked, least, strict=True):
            some = np.flatnonzero(near >= low)
            best = [i for i in some[np.lexsort((own[some], -near[some]))][: k + 1] if own[i] != q][:k]
            out += [(q, own[i], row[i]) for i in best]
        return pd.DataFrame(out, columns=["q", "v", "s"])

    dealt = held.unionByName(both).repartition(min(blocks * blocks, 1000), "block", "part")  # a pair of blocks is work, whatever its bytes
    found = dealt.groupBy("block", "part").applyInPandas(nearest, "q long, v long, s double")
    place = F.row_number().over(Window.partitionBy("q").orderBy(F.desc("s"), "v"))
    return found.withColumn("_place", place).filter(F.col("_place") <= k).select(vid("vector", "q").alias("src"), vid("vector", "v").alias("dst"))


def _v(kind: str, key: str) -> Callable[[], Column]:
    return lambda: vid(kind, key)


_RULES: dict[str, Callable[[GivenTables], DataFrame]] = {
    "bulk_supply": _pair("lineitem", _v("supplier", "l_suppkey"), _v("part", "l_partkey"), "l_quantity >= 46"),
    "sourced_from": _pair("lineitem", _v("part", "l_partkey"), _v("supplier", "l_suppkey"), "l_quantity < 46"),
    "located": _located,
    "adjacent": lambda g: _ring(g.table("nation"), "n_regionkey", "n_nationkey", "nation", True),
    "within": _pair("nation", _v("nation", "n_nationkey"), _v("region", "n_regionkey")),
    "ordered_by": _pair("orders", _v("order", "o_orderkey"), _v("customer", "o_custkey")),
    "resident_of": _pair("customer", _v("customer", "c_custkey"), _v("nation", "c_nationkey")),
    "placed": _pair("orders", _v("customer", "o_custkey"), _v("order", "o_orderkey")),
    "has_item": _pair("lineitem", _v("order", "l_orderkey"), _item),
    "of_part": _pair("lineitem", _item, _v("part", "l_partkey")),
    "made_by": _name("part", _v("part", "p_partkey"), "brand"),
    "of_type": _name("part", _v("part", "p_partkey"), "part_type"),
    "succ_part": _next("part", "part", "p_partkey", "p_brand", "p_partkey"),
    "follows": _next("orders", "order", "o_orderkey", "o_custkey", "o_orderdate", "o_orderkey"),
    "in_segment": _name("customer", _v("customer", "c_custkey"), "segment"),
    "has_priority": _name("orders", _v("order", "o_orderkey"), "priority"),
    "acted": _pair("events", _v("user", "user_id"), _v("event", "event_id")),
    "then": _next("events", "event", "event_id", "user_id", "ts", "event_id"),
    "event_kind": _name("events", _v("event", "event_id"), "event_type"),
    "is_customer": _is_customer,
    "reply": _reply,
    "links": lambda g: g.named(g.hrefs().select(vid("page", "page_id").alias("src"), "value"), "href"),
    "on_host": _name("pages", _v("page", "page_id"), "host"),
    "from_source": _name("documents", _v("doc", "doc_id"), "source"),
    "in_lang": _name("documents", _v("doc", "doc_id"), "lang"),
    "same_text": lambda g: _ring(g.table("documents").filter("text is not null").select("doc_id", F.md5("text").alias("digest")), "digest", "doc_id", "doc", False),
    "quotes": _quotes,
    "near": _near,
    "in_class": _pair("embeddings", _v("vector", "vec_id"), _v("vector_class", "label")),
}
#: Labels that are two columns of one table.
_PLAIN = {"bulk_supply", "sourced_from", "ordered_by", "resident_of", "placed", "has_item", "of_part", "acted", "in_class"}
#: Labels whose end is a name that stands in a column: the kind that it names.
_CALLED = {"made_by": "brand", "of_type": "part_type", "in_segment": "segment", "has_priority": "priority", "event_kind": "event_type", "from_source": "source", "in_lang": "lang", "on_host": "host"}
#: Labels that lead from a row of a table to the next.
_SEQUENCES = {"succ_part": "part", "follows": "orders", "then": "events", "reply": "conversations"}


def _key(kind: str, column: str) -> Callable[[GivenTables, list[int]], str]:
    """The condition that vertices of a kind set on the column of their keys."""
    least = KINDS[kind] * ROOM - (1 << 63)  # vertices below it have no key of 64 bits
    return lambda g, sources: f"{column} IN ({', '.join(f'{v - KINDS[kind] * ROOM}L' for v in sources if v >= least) or 'NULL'})"


def _item_key(g: GivenTables, sources: list[int]) -> str | None:
    """The orders whose items can have these numbers, whatever 32 bits the number of a line is."""
    if g.table("lineitem").schema["l_linenumber"].dataType.simpleString() not in ("tinyint", "smallint", "int"):
        return None
    low, high = (v - KINDS["item"] * ROOM for v in (sources[0], sources[-1]))
    return f"l_orderkey BETWEEN {(low - (1 << 31)) // 8}L AND {(high + (1 << 31)) // 8 + 1}L"


#: What vertices at the start and at the end of a label say of its table.
_KEYS = {
    "bulk_supply": (_key("supplier", "l_suppkey"), _key("part", "l_partkey")), "sourced_from": (_key("part", "l_partkey"), _key("supplier", "l_suppkey")),
    "ordered_by": (_key("order", "o_orderkey"), _key("customer", "o_custkey")), "placed": (_key("customer", "o_custkey"), _key("order", "o_orderkey")),
    "resident_of": (_key("customer", "c_custkey"), _key("nation", "c_nationkey")), "has_item": (_key("order", "l_orderkey"), _item_key), "of_part": (_item_key, _key("part", "l_partkey")),
    "acted": (_key("user", "user_id"), _key("event", "event_id")), "made_by": (_key("part", "p_partkey"), None), "of_type": (_key("part", "p_partkey"), None),
    "in_segment": (_key("customer", "c_custkey"), None), "has_priority": (_key("order", "o_orderkey"), None), "event_kind": (_key("event", "event_id"), None),
}
_GRAPHS: dict[tuple, GivenTables] = {}


def given_graph(spark: SparkSession, sf_dir: str) -> GivenTables:
    """The graph of a folder of tables, one for each Spark application and folder."""
    key = (spark.sparkContext.applicationId, id(spark._jsparkSession), sf_dir)
    if key not in _GRAPHS:
        _GRAPHS[key] = GivenTables(spark, sf_dir)
    return _GRAPHS[key]
