"""N-gram Jaccard join over a token-group matrix, and the classes of linked documents.

Documents are sets of hashed k-word shingles; two link when intersection / union >= num / den, compared in integers.

1. One pass finds tokens that are frequent somewhere (a fixed-size table of counts by hash cell). It orders tokens: rare first, then
   by hash. Any order gives the same links; this one keeps frequent tokens out of the prefixes.
2. A second pass gives each document its size, a digest of its set and its prefix. A set of n tokens shares ceil(t n) or more with any set that it
   links with, and ceil(2 t n / (1 + t)) or more with one that is not smaller. Less these overlaps, and k = SHARED more, the first n tokens are
   its prefix and its head; of two linked sets the head of the smaller one and the prefix of the other have k tokens in common (fewer if an
   overlap is under k). Documents of equal digests are one class from here on.
3. Tokens that stand in the head of one class and the prefix of another are live, classes without k of them have no links. The others are dealt to
   groups of similar sets: those that elect the same of their live tokens, the one that most classes hold. So the holders of a token, of a family of
   near copies or of a passage that many documents share, lie in few groups. Groups are split into slices of at most MEMBERS classes and TOKENS tokens.
4. Links within the slices are found first. Some members of a split group, the pivots, stand in each of its slices and tie them together. What is
   linked by then is a component: a family of near copies, however large, is one.
5. The token-group matrix holds, for each token, the components and the slices of classes not linked yet that hold it in a head, with their range of
   sizes. A class meets those other than its own of which the sizes allow a link and k tokens agree. So a family meets itself no more.
6. In a task for a group's slice and at most QUERIES of the classes that meet it, the union of the members' whole sets bounds the overlap of each
   query with every member; only queries with a bound of t n or more open the group, and get exact overlaps with all members.
   A task returns a spanning forest of its links, not the pairs.
7. Classes are joined to components by large and small stars over written tables. A node is the smallest doc_id of a class and its digest, so a
   component's least node names its smallest doc_id.

If links are to be counted, all pairs must be seen: step 4 then comes with step 6, and classes meet all groups but their own.

Sets are told apart by 64-bit token hashes (128 bits and the size for whole sets), so a result is exact but for hash collisions.
Defined results: a null text, or one without words, has size 0 and links with nothing; a text of fewer than k words is one shingle of all
its words. Rows without doc_id link with nothing and have component null. Repeated rows count each. Rows of the same id and other
texts are documents of their own that carry the same id. Long texts are hashed whole. Empty tables give empty results. Columns other
than doc_id and text are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, LongType, StructField, StructType

from .store import forget, lean, release, small_batches, written
from .words import mix, shingle_sets

WORDS, NUM, DEN = 3, 90, 100
MEMBERS, QUERIES, TOKENS, SHARED, PIVOTS = 1024, 512, 1_000_000, 5, 32
#: Up to so many rows that describe groups, or name the classes to look up, are broadcast; beyond it they are joined.
BROADCAST_GROUPS = 200_000
_CELL_BITS = 22
_ROWS, _EXPANDED = 128, 500_000


def frequent_cells(docs: DataFrame, k: int) -> np.ndarray:
    """Levels (by the logarithm) of the counts of the hash cells that stand out in some partition, else 0. The size is fixed, whatever the input."""
    cells = 1 << _CELL_BITS

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, waiting, held = np.zeros(cells, np.int32), [], 0
        for batch in batches:
            for at in range(0, batch.num_rows, _ROWS):
                for s in shingle_sets(batch.column(0).slice(at, _ROWS).to_pylist(), k):
                    waiting.append((s >> np.uint64(64 - _CELL_BITS)).astype(np.int32))
                    held += len(s)
                    if held > cells // 4:
                        np.add.at(total, np.concatenate(waiting), 1)
                        waiting, held = [], 0
        if waiting:
            np.add.at(total, np.concatenate(waiting), 1)
        mean = total.mean()
        found = np.flatnonzero(total > mean + 2.5 * np.sqrt(mean) + 1)
        yield pa.RecordBatch.from_arrays([pa.array(found, pa.int32()), pa.array(total[found], pa.int64())], ["cell", "n"])

    level = F.round(32 * F.log2(F.sum("n"))).cast("short")
    rows = docs.select("text").mapInArrow(lean(count), "cell int, n long").groupBy("cell").agg(level.alias("level")).toArrow()
    out = np.zeros(cells, np.int16)
    out[rows["cell"].to_numpy()] = rows["level"].to_numpy()
    return out


def digests(s: np.ndarray) -> tuple[int, int]:
    """Two signed 64-bit digests of a set of hashes."""
    n = np.uint64(len(s))
    with np.errstate(over="ignore"):
        both = np.array([mix(s).sum(dtype=np.uint64) + n, np.bitwise_xor.reduce(mix(s + np.uint64(0x5851F42D4C957F2D))) ^ n], np.uint64)
    return tuple(mix(both).view(np.int64).tolist())


def set_features(docs: DataFrame, k: int, num: int, den: int) -> DataFrame:
    """doc_id, n, d1, d2, prefix of each row."""
    cells = frequent_cells(docs, k)

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, _ROWS):
                part = batch.slice(at, _ROWS)
                size, one, two, prefix = [], [], [], []
                for s in shingle_sets(part.column(1).to_pylist(), k):
                    n = len(s)
                    needed = (n * num + den - 1) // den
                    first = n - needed + min(SHARED, needed)
                    seen = cells[(s >> np.uint64(64 - _CELL_BITS)).astype(np.int64)]
                    chosen = s[np.lexsort((s, seen))[:first]] if seen.any() else s[:first]
                    a, b = digests(s)
                    size.append(n), one.append(a), two.append(b), prefix.append(chosen.view(np.int64))
                offsets = np.concatenate(([0], np.cumsum([len(p) for p in prefix])))
                flat = pa.array(np.concatenate(prefix) if prefix else np.empty(0, np.int64), pa.int64())
                columns = [pa.array(size, pa.int32()), pa.array(one, pa.int64()), pa.array(two, pa.int64()), pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), flat)]
                yield pa.RecordBatch.from_arrays([part.column(0), *columns], ["doc_id", "n", "d1", "d2", "prefix"])

    ready = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return ready.mapInArrow(lean(rows), "doc_id long, n int, d1 long, d2 long, prefix array<long>")


def _small(df: DataFrame) -> DataFrame:
    """A written table, to be broadcast if it has few rows."""
    return F.broadcast(df) if df.count() <= BROADCAST_GROUPS else df


def whole_sets(docs: DataFrame, wanted: DataFrame, k: int) -> DataFrame:
    """key, rep, copies, tokens of the classes in wanted (key, rep, copies)."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()  # rows that repeat a text stand in one task
        for batch in batches:
            for at in range(0, batch.num_rows, _ROWS):
                part = batch.slice(at, _ROWS)
                place, sets = [], []
                for i, (key, s) in enumerate(zip(part.column(0).to_pylist(), shingle_sets(part.column(3).to_pylist(), k), strict=True)):
                    if len(s) and key not in seen and digests(s)[0] == key:
                        seen.add(key)
                        place.append(i), sets.append(s.view(np.int64))
                offsets = np.concatenate(([0], np.cumsum([len(s) for s in sets])))
                flat = pa.array(np.concatenate(sets) if sets else np.empty(0, np.int64), pa.int64())
                tokens = pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), flat)
                chosen = part.take(pa.array(place, pa.int32()))
                yield pa.RecordBatch.from_arrays([*chosen.columns[:3], tokens], ["key", "rep", "copies", "tokens"])

    texts = docs.select(F.col("doc_id").cast("long").alias("rep"), F.col("text").cast("string").alias("text"))
    asked = texts.join(_small(written(wanted.select("key", "rep", "copies"), "wanted")), "rep").select("key", "rep", "copies", "text")
    return asked.mapInArrow(lean(rows), "key long, rep long, copies long, tokens array<long>")


class TokenGroup:
    """One group: the union of its members' tokens, and which members hold each."""

    def __init__(self, sets: list[np.ndarray]):
        self.sizes = np.array([len(s) for s in sets])
        self.union, at = np.unique(np.concatenate(sets), return_inverse=True)
        order = np.argsort(at, kind="stable")
        self.holders = np.repeat(np.arange(len(sets)), self.sizes)[order]
        self.begin = np.searchsorted(at[order], np.arange(len(self.union) + 1))

    def links(self, queries: list[np.ndarray], num: int, den: int) -> tuple[np.ndarray, np.ndarray]:
        """Query and member indices of all pairs that link."""
        found, m = [], len(self.sizes)
        step = max(1, min(64, _EXPANDED // (1 + m * max(map(len, queries)))))  # what is expanded at once stays bounded
        for first in range(0, len(queries), step):
            part = queries[first : first + step]
            sizes = np.array([len(s) for s in part])
            tokens, of = np.concatenate(part), np.repeat(np.arange(len(part)), sizes)
            at = np.minimum(np.searchsorted(self.union, tokens), len(self.union) - 1)
            hit = self.union[at] == tokens
            at, of = at[hit], of[hit]
            opened = np.bincount(of, minlength=len(part)) * den >= sizes * num
            at, of = at[opened[of]], of[opened[of]]
            n = self.begin[at + 1] - self.begin[at]
            holder = self.holders[np.repeat(self.begin[at] - (np.cumsum(n) - n), n) + np.arange(n.sum())]
            both = np.bincount(np.repeat(of, n) * m + holder, minlength=len(part) * m).reshape(len(part), m)
            q, g = np.nonzero(both * den >= (sizes[:, None] + self.sizes - both) * num)
            found.append((q + first, g))
        return np.concatenate([q for q, _ in found]), np.concatenate([g for _, g in found])


def _roots(a: np.ndarray, b: np.ndarray, n: int) -> np.ndarray:
    """The smallest index that each of n nodes reaches over the links a - b."""
    root = np.arange(n)
    while True:
        low = np.minimum(root[a], root[b])
        new = root.copy()
        np.minimum.at(new, root[a], low)
        np.minimum.at(new, root[b], low)
        new = new[new]
        if (new == root).all():
            return root
        root = new


def group_links(work: DataFrame, num: int, den: int, inner: bool = True) -> DataFrame:
    """node, root, links of the classes that link, for rows (gid, slice, part, own, home, key, rep, copies, tokens).

    Members (own) are compared with the others, and in part 0, with inner, with each other. Others of a member's size are compared where their home
    is above gid, smaller ones not at all: they meet the member's class from the other side.
    """

    def search(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.drop_duplicates(["key", "own"]).sort_values(["rep", "key"], ignore_index=True)
        own = rows["own"].to_numpy(bool)
        members, others = np.flatnonzero(own), np.flatnonzero(~own)
        sets = [t.view(np.uint64) if isinstance(t, np.ndarray) else np.array(t, np.int64).view(np.uint64) for t in rows["tokens"]]
        size = np.array([len(s) for s in sets])
        later = rows["home"].to_numpy(np.int64) > rows["gid"].iloc[0]
        a = b = np.empty(0, int)
        if len(members):
            group = TokenGroup([sets[i] for i in members])
            if len(others):
                q, g = group.links([sets[i] for i in others], num, den)
                q, g = others[q], members[g]
                ours = (size[q] > size[g]) | ((size[q] == size[g]) & later[q])
                a, b = q[ours], g[ours]
            if inner and rows["part"].iloc[0] == 0 and len(members) > 1:
                q, g = group.links([sets[i] for i in members], num, den)
                a, b = np.concatenate((a, members[q[q < g]])), np.concatenate((b, members[g[q < g]]))
        copies = rows["copies"].to_numpy(np.int64)
        links = np.bincount(a, copies[b], len(rows)) + np.bincount(b, copies[a], len(rows))
        root = _roots(a, b, len(rows))
        key, rep = rows["key"].to_numpy(np.int64), rows["rep"].to_numpy(np.int64)
        hit = links > 0
        return pd.DataFrame({"rep": rep[hit], "key": key[hit], "root_rep": rep[root[hit]], "root_key": key[root[hit]], "links": links[hit].astype(np.int64)})

    found = work.groupBy("gid", "slice", "part").applyInPandas(search, "rep long, key long, root_rep long, root_key long, links long")
    return found.select(F.struct("rep", "key").alias("node"), F.struct(F.col("root_rep").alias("rep"), F.col("root_key").alias("key")).alias("root"), "links")


def components(edges: DataFrame) -> DataFrame:
    """node, component (the smallest node reached) of all nodes in edges (a, b). Large and small stars, each round a written table."""
    both = lambda e: e.select(F.col("a").alias("u"), F.col("b").alias("v")).unionAll(e.select(F.col("b").alias("u"), F.col("a").alias("v")))
    edges = written(edges.filter("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "links")
    stars = lambda e: e.agg(F.count("*"), F.sum(F.xxhash64("a", "b") % F.lit(1 << 31))).first()
    before = stars(edges)
    while before[0]:
        around = both(edges)
        low = around.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("m", "u").alias("m"))
        large = around.filter("v > u").join(low, "u").select(F.col("v").alias("a"), F.col("m").alias("b")).filter("a <> b").distinct()
        low = large.groupBy("a").agg(F.min("b").alias("m"))
        joined = large.join(low, "a")
        small = joined.filter("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).unionAll(joined.select("a", F.col("m").alias("b"))).distinct()
        new = written(small, "links")
        state = stars(new)
        forget(edges)
        edges = new
        if state == before:
            break
        before = state
    roots = edges.groupBy("a").agg(F.min("b").alias("component")).select(F.col("a").alias("node"), "component")
    return roots.unionAll(edges.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct())


class _Thresholds:
    """Columns of what a set of n tokens needs in common with others."""

    def __init__(self, num: int, den: int):
        whole = lambda n, a, b: ((n.cast("long") * a + (b - 1)) / b).cast("long")
        self.any = lambda n: whole(n, num, den)
        self.larger = lambda n: whole(n, 2 * num, num + den)
        self.head = lambda n: n - self.larger(n) + F.least(F.lit(SHARED), self.larger(n))
        self.agree = lambda n, low: F.least(F.lit(SHARED), self.any(n), self.larger(low))
        self.least = lambda n: F.least(F.lit(SHARED), self.any(n), self.larger(self.any(n)))
        self.sizes_fit = lambda n, high: high.cast("long") * den >= n.cast("long") * num


def similar_groups(live: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Of postings (token, key, n, df): key, n, gid of each class, and key, gid of the pivots in all slices of their groups.

    Of a family, in which only some members lack any one token, nearly all elect the same one or the next.
    """
    elected = live.groupBy("key").agg(F.first("n").alias("n"), F.max(F.struct("df", "token"))["token"].alias("token"))
    elected = written(elected, "elected")
    sizes = elected.groupBy("token").agg(F.count("*").alias("members"), F.sum("n").alias("size"))
    slices = F.ceil(F.greatest(F.col("members") / MEMBERS, F.col("size") / TOKENS)).cast("int")
    split = written(sizes.withColumn("slices", slices).filter("slices > 1"), "slices")
    dealt = elected.join(_small(split), "token", "left")
    gid = F.xxhash64("token", F.pmod(F.xxhash64("key"), F.coalesce("slices", F.lit(1))).cast("int"))
    share = F.least(F.lit(PIVOTS) / F.col("members"), F.lit(TOKENS / 10) / F.col("size"))
    pivots = dealt.filter("slices is not null").filter(F.pmod(F.xxhash64(F.lit("pivot"), "key"), F.lit(1 << 30)) < share * (1 << 30))
    pivots = pivots.select("key", "token", F.explode(F.sequence(F.lit(0), F.col("slices") - 1)).alias("_slice")).select("key", F.xxhash64("token", "_slice").alias("gid"))
    return written(dealt.select("key", "n", gid.alias("gid")), "groups"), pivots


def _meetings(live: DataFrame, homes: DataFrame, need: _Thresholds) -> DataFrame:
    """key, n, place, met: the places that a class meets by the token-group matrix, for homes (key, gid, place)."""
    placed = live.join(homes.select("key", "gid", "place"), "key").select("token", "key", "n", "head", "gid", "place")
    matrix = placed.filter("head").groupBy("token", F.col("place").alias("met")).agg(F.min("n").alias("low"), F.max("n").alias("high"))
    elsewhere = (F.col("place") != F.col("met")) & (F.col("gid") != F.col("met"))
    not_larger = (F.col("low") < F.col("n")) | ((F.col("low") == F.col("n")) & (F.col("place") > F.col("met")))
    pairs = placed.join(matrix, "token").filter(elsewhere & not_larger & need.sizes_fit(F.col("n"), F.col("high")))
    met = pairs.groupBy("key", "n", "place", "met").agg(F.count("*").alias("_shared"), F.min("low").alias("_low"))
    return met.filter(F.col("_shared") >= need.agree(F.col("n"), F.col("_low"))).select("key", "n", "place", "met")


def _searches(met: DataFrame, homes: DataFrame, all_groups: bool) -> DataFrame:
    """gid, slice, part, own, home, key: rows of the tasks for the places that are met, and with all_groups for all of more than one member."""
    place_sizes = homes.groupBy(F.col("place").alias("gid")).agg(F.count("*").alias("members"), F.ceil(F.greatest(F.count("*") / F.lit(MEMBERS), F.sum("n") / F.lit(TOKENS))).cast("int").alias("slices"))
    asked = met.groupBy(F.col("met").alias("gid")).agg(F.ceil(F.greatest(F.count("*") / F.lit(QUERIES), F.sum("n") / F.lit(2 * TOKENS))).cast("int").alias("parts"))
    places = place_sizes.join(asked, "gid", "left" if all_groups else "inner").filter("members > 1 or parts is not null")
    places = written(places.select("gid", F.coalesce("parts", F.lit(1)).alias("parts"), F.lit(1).alias("slices") if all_groups else "slices"), "places")
    split = _small(written(places.filter("parts > 1 or slices > 1"), "split"))  # a place may meet any number of classes, so they are not dealt by place
    of_slice = F.pmod(F.xxhash64("key"), F.coalesce("slices", F.lit(1))).cast("int")
    upto = lambda n: F.sequence(F.lit(0), F.coalesce(n, F.lit(1)) - 1)
    here = homes.select(F.col("place").alias("gid"), "key").join(places.select("gid"), "gid", "left_semi").join(split, "gid", "left")
    members = here.select("gid", of_slice.alias("slice"), F.explode(upto(F.col("parts"))).alias("part"), F.lit(True).alias("own"), F.col("gid").alias("home"), "key")
    asking = met.select(F.col("met").alias("gid"), F.col("place").alias("home"), "key").join(split, "gid", "left")
    of_part = F.pmod(F.xxhash64("key"), F.coalesce("parts", F.lit(1))).cast("int")
    others = asking.select("gid", F.explode(upto(F.col("slices"))).alias("slice"), of_part.alias("part"), F.lit(False).alias("own"), "home", "key")
    return written(members.unionAll(others), "work")


def _linked(docs: DataFrame, k: int, num: int, den: int, count_links: bool) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Rows (doc_id, n, d1), their classes (key, rep, copies), and linked classes (node, component, links). Rows of no class have no words or no doc_id."""
    spark, need = docs.sparkSession, _Thresholds(num, den)
    small_batches(spark)
    features = written(set_features(docs, k, num, den), "sets")
    some = features.filter("n > 0 and doc_id is not null")
    full = written(some.groupBy("n", "d1", "d2").agg(F.min("doc_id").alias("rep"), F.count("*").alias("copies"), F.first("prefix").alias("prefix")).withColumnRenamed("d1", "key"), "classes")
    rows = written(features.select("doc_id", "n", "d1"), "sizes")
    forget(features)
    posted = full.select(F.posexplode("prefix").alias("_at", "token"), "key", "n").select("token", "key", "n", (F.col("_at") < need.head(F.col("n"))).alias("head"))
    shared = posted.groupBy("token").agg(F.count("*").alias("df"), F.max("head").alias("_head")).filter("df > 1 and _head").select("token", "df")
    live = written(posted.join(shared, "token"), "postings")
    enough = live.groupBy("key").agg(F.count("*").alias("_live"), F.first("n").alias("n")).filter(F.col("_live") >= need.least(F.col("n"))).select("key")
    dense, live = live, written(live.join(enough, "key"), "postings")
    forget(dense)
    classes = written(full.select("key", "rep", "copies"), "classes")
    forget(full)
    del features, some, full, posted, shared, enough, dense
    release(spark)

    grouped, pivots = similar_groups(live)
    # Rows of work are joined where the sets are made, if they are few, so that sets are shuffled once, to their groups.
    with_sets = lambda work: _small(work).join(whole_sets(docs, classes.join(work, "key", "left_semi"), k), "key")
    if count_links:
        homes = grouped.withColumn("place", F.col("gid"))
        met = written(_meetings(live, homes, need), "meetings")
        forget(live)
        work = _searches(met, homes, True)
        found = written(group_links(with_sets(work), num, den), "found")
        edges = found.select(F.col("node").alias("a"), F.col("root").alias("b"))
    else:
        alone = grouped.groupBy("gid").agg(F.count("*").alias("_n")).filter("_n > 1").select("gid")
        rows_of = grouped.select("gid", "key").unionAll(pivots.select("gid", "key")).join(alone, "gid", "left_semi")
        work = written(rows_of, "together").select("gid", F.lit(0).alias("slice"), F.lit(0).alias("part"), F.lit(True).alias("own"), F.col("gid").alias("home"), "key")
        inside = written(group_links(with_sets(work), num, den).select("node", "root"), "inside")
        forget(work)
        known = written(components(inside.select(F.col("node").alias("a"), F.col("root").alias("b"))), "known")
        forget(inside)
        release(spark)
        place = F.when(F.col("component").isNull(), F.col("gid")).otherwise(F.xxhash64(F.lit("component"), "component"))
        homes = grouped.join(known.select(F.col("node.key").alias("key"), "component"), "key", "left").select("key", "n", "gid", place.alias("place"))
        homes = written(homes, "homes")
        met = written(_meetings(live, homes, need), "meetings")
        forget(live)
        work = _searches(met, homes, False)
        across = written(group_links(with_sets(work), num, den, inner=False).select("node", "root"), "across")
        edges = known.select(F.col("node").alias("a"), F.col("component").alias("b")).unionAll(across.select(F.col("node").alias("a"), F.col("root").alias("b")))
        more = not across.isEmpty()
    forget(met, work)
    del met, work, homes
    release(spark)
    if not count_links and not more:
        return rows, classes, known
    joined = components(edges)
    if not count_links:
        return rows, classes, joined
    return rows, classes, joined.join(found.groupBy("node").agg(F.sum("links").alias("links")), "node")


def jaccard_classes(docs: DataFrame, k: int = WORDS, num: int = NUM, den: int = DEN, count_links: bool = True) -> DataFrame:
    """doc_id, n_shingles, component_id (smallest doc_id reached over links) and, with count_links, n_links (rows that the row itself links with)."""
    rows, classes, linked = _linked(docs, k, num, den, count_links)
    own = linked.select(F.col("node.key").alias("key"), F.col("component.rep").alias("_component"), *(["links"] if count_links else []))
    told = classes.join(own, "key", "left").select(F.col("key").alias("d1"), F.coalesce("_component", "rep").alias("component_id"), *([(F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links")] if count_links else []))
    out = rows.select("doc_id", "n", F.when((F.col("n") > 0) & F.col("doc_id").isNotNull(), F.col("d1")).alias("d1")).join(told, "d1", "left")
    return out.select("doc_id", F.col("n").cast("long").alias("n_shingles"), F.coalesce("component_id", "doc_id").alias("component_id"), *([F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links")] if count_links else []))


def _with_class(docs: DataFrame, k: int) -> DataFrame:
    """docs with _n and _d1, as in set_features."""
    at_text = docs.columns.index("text")
    schema = StructType([*docs.schema.fields, StructField("_n", IntegerType()), StructField("_d1", LongType())])

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, _ROWS):
                part = batch.slice(at, _ROWS)
                sets = shingle_sets(part.column(at_text).to_pylist(), k)
                n, d1 = zip(*((len(s), digests(s)[0]) for s in sets), strict=True)
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(n, pa.int32()), pa.array(d1, pa.int64())], schema.names)

    return docs.mapInArrow(lean(rows), schema)


def one_of_each(docs: DataFrame, k: int = WORDS, num: int = NUM, den: int = DEN) -> DataFrame:
    """docs with one row for each component (of the smallest doc_id, and of one class); rows without doc_id or words all stay."""
    columns = docs.columns
    rows, classes, linked = _linked(docs, k, num, den, False)
    others = linked.filter("node <> component").select(F.col("node.key").alias("key"))
    chosen = written(classes.join(others, "key", "left_anti").select(F.col("rep").alias("doc_id"), F.col("key").alias("_d1")), "chosen")
    of_id = rows.filter("doc_id is not null").groupBy("doc_id").agg(F.min("n").alias("_least"), F.max("n").alias("_n"), (F.min("d1") != F.max("d1")).alias("_several"))
    ids = written(of_id.join(chosen.select("doc_id").distinct().withColumn("_kept", F.lit(True)), "doc_id", "left").filter("_kept or _least = 0").select("doc_id", "_n", "_several"), "kept")
    # Copies within a class may differ in case, white space and other columns: the row is chosen by hash, so reruns agree.
    order = F.xxhash64(*[F.col(c) for c in columns if "map<" not in docs.schema[c].dataType.simpleString()])
    one = lambda rows, *by: rows.groupBy(*by).agg(F.min_by(F.struct(*columns), order).alias("_row")).select("_row.*")
    kept = docs.filter("doc_id is not null").join(ids.filter("not _several"), "doc_id")
    out = one(kept.filter("_n > 0"), "doc_id").unionByName(kept.filter("_n = 0").select(columns)).unionByName(docs.filter("doc_id is null"))
    several = ids.filter("_several").select("doc_id")
    n = several.count()
    if n:  # the id does not tell which of its texts stay: their sets do
        told = _with_class(docs.join(F.broadcast(several) if n <= BROADCAST_GROUPS else several, "doc_id").select(columns), k)
        out = out.unionByName(told.filter("_n = 0").select(columns)).unionByName(one(told.filter("_n > 0").join(chosen, ["doc_id", "_d1"]), "doc_id", "_d1"))
    return out
