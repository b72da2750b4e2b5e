"""Benchmark decontamination: SimHash of item-sized windows, multi-index Hamming search, exact weighted-shingle check.

Words are lower-cased and split at white space and ASCII marks. Windows of a document have an item's number of words. A window's
fingerprint is the 128-bit SimHash of its 5-word shingles, weighted by their rarity among the items. The items' fingerprints stand in an index of
12 bit blocks: if two fingerprints differ in at most RADIUS bits, some block differs in at most RADIUS // 12 bits, and the index lists each
item under all block values so near. It so returns every item within the radius. Candidates of the window's size are then
compared exactly: weighted shingle multisets, sum of minima / sum of maxima >= 0.8. RADIUS is four deviations over the mean
distance at that similarity. A document of fewer words than the item is its one window, and goes to the exact comparison at once.
A shingle's rarity is log((items + 1) / items that hold a shingle of its hash cell), at least one, over all different item texts; the table of cells
has a fixed size, so weights, and with them the results, do not depend on how the benchmark is split.

Only windows that share a shingle with an item are formed: others have similarity 0 with all. Documents are read once, where they are; the
different texts of the benchmark go to the tasks in blocks of about ITEMS, one pass for each block; with several, each pass is written before the next
block is fetched. So what is sent, and what the driver holds, never outgrows a bound.

Defined results: null and empty documents hold nothing; items that are null or have no word match nothing. Items of fewer than 5 words are one shingle
of all their words. Rows without doc_id are judged and reported with null. Repeated rows and items are judged each. Equal similarities of a document and
an item report the first window. Empty tables give empty results. Other columns are ignored (report) or kept (filter).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .store import lean, small_batches, written
from .words import Words, chained, mix, pieces

K, SIMILARITY, BITS, RADIUS, ITEMS = 5, 0.8, 128, 35, 20_000
#: Widths of the index's blocks.
BLOCKS = (11,) * 8 + (10,) * 4
_ROWS, _FILTER_BITS = 128, 22
#: Windows whose fingerprints are made at once, and candidates that the index lists at once.
_WINDOWS, _EXPANDED = 1 << 14, 1 << 22
#: Up to so many items their ids are broadcast to the hits.
_BROADCAST_ITEMS = 1_000_000
_MARKS = bytes(b if chr(b).isalnum() or b >= 0x80 else 0x20 for b in range(256))


def words_of(text: str | None) -> bytes:
    return text.lower().encode("utf-8", "surrogatepass").translate(_MARKS) if isinstance(text, str) else b""


def signs(shingles: np.ndarray) -> np.ndarray:
    """One row of BITS values +1 or -1 for each shingle."""
    two = np.stack([mix(shingles), mix(shingles + np.uint64(0xA0761D6478BD642F))], 1)
    return np.unpackbits(two.view(np.uint8), axis=1, bitorder="little").astype(np.float32) * 2 - 1


def packed(sums: np.ndarray) -> np.ndarray:
    """Fingerprints (two 64-bit words each) of rows of bit sums."""
    return np.packbits(sums > 0, axis=1, bitorder="little").view(np.uint64)


def cell(shingles: np.ndarray) -> np.ndarray:
    return (shingles >> np.uint64(64 - _FILTER_BITS)).astype(np.int64)


def item_shingles(text: str | None) -> tuple[np.ndarray, int]:
    """Shingles of an item, and its number of words."""
    h = Words([words_of(text)]).hashes()
    return chained(h, min(K, len(h))) if len(h) else h, len(h)


class HammingIndex:
    """All fingerprints within RADIUS of a given one, by blocks."""

    def __init__(self, prints: np.ndarray, radius: int = RADIUS):
        self.prints, self.radius = prints, radius
        self.tables = []
        near = radius // len(BLOCKS)
        for width, values in zip(BLOCKS, self._blocks(prints), strict=True):
            masks = np.array([m for m in range(1 << width) if m.bit_count() <= near])
            spots = (values[:, None] ^ masks).ravel()
            order = np.argsort(spots, kind="stable")
            self.tables.append((np.searchsorted(spots[order], np.arange((1 << width) + 1)), np.repeat(np.arange(len(prints)), len(masks))[order]))

    @staticmethod
    def _blocks(prints: np.ndarray) -> list[np.ndarray]:
        bits = np.unpackbits(np.ascontiguousarray(prints).view(np.uint8).reshape(len(prints), BITS // 8), axis=1, bitorder="little").astype(np.int64)
        ends = np.cumsum(BLOCKS)
        return [bits[:, e - w : e] @ (1 << np.arange(w)) for w, e in zip(BLOCKS, ends, strict=True)]

    def near(self, prints: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Pairs (given, indexed) of all fingerprints within the radius."""
        blocks = self._blocks(prints)
        listed = sum(begin[v + 1] - begin[v] for (begin, _), v in zip(self.tables, blocks, strict=True))
        cuts = np.flatnonzero(np.diff(np.cumsum(listed) // _EXPANDED)) + 1
        found = [self._near(prints[part], [v[part] for v in blocks], part[0]) for part in np.split(np.arange(len(prints)), cuts) if len(part)]
        return np.concatenate([a for a, _ in found]), np.concatenate([b for _, b in found])

    def _near(self, prints: np.ndarray, blocks: list[np.ndarray], first: int) -> tuple[np.ndarray, np.ndarray]:
        pairs = []
        for (begin, items), values in zip(self.tables, blocks, strict=True):
            n = begin[values + 1] - begin[values]
            at = np.repeat(begin[values] - (np.cumsum(n) - n), n) + np.arange(n.sum())
            pairs.append(np.repeat(np.arange(len(prints)), n) * len(self.prints) + items[at])
        both = np.unique(np.concatenate(pairs))
        a, b = both // len(self.prints), both % len(self.prints)
        close = np.bitwise_count(prints[a] ^ self.prints[b]).sum(1) <= self.radius
        return a[close] + first, b[close]


class Benchmark:
    """The items (ident, text) of one block: shingles, weights, fingerprints. counts: cells and how many of all n_items texts have a shingle there."""

    def __init__(self, items: list[tuple], similarity: float = SIMILARITY, counts: tuple[np.ndarray, np.ndarray] | None = None, n_items: int | None = None):
        self.similarity, self.ids, self.shingles, self.sizes = similarity, [], [], []
        for ident, text in items:
            shingles, size = item_shingles(text)
            if size:
                self.ids.append(ident), self.sizes.append(size), self.shingles.append(shingles)
        if counts is None:
            n_items = len(self.ids)
            counts = np.unique(np.concatenate([np.unique(cell(s)) for s in self.shingles] or [np.empty(0, np.int64)]), return_counts=True)
        self.cells, self.counts, self.n_items = counts[0], counts[1], n_items
        self.sizes = np.array(self.sizes, int)
        flat = np.concatenate(self.shingles) if self.ids else np.empty(0, np.uint64)
        of = np.repeat(np.arange(len(self.ids)), [len(s) for s in self.shingles])
        self.known, at = np.unique(flat, return_inverse=True)
        pairs = np.unique(at * max(1, len(self.ids)) + of)
        self.held = [pairs // max(1, len(self.ids)), pairs % max(1, len(self.ids))]
        self.filter = np.zeros(1 << _FILTER_BITS, bool)
        self.filter[cell(self.known)] = True
        self.lengths = sorted({min(K, int(n)) for n in self.sizes})
        self.totals = np.array([self.weights(s).sum() for s in self.shingles])
        self.index = HammingIndex(np.concatenate([packed(np.round(self.bit_sums(s), 6)[None]) for s in self.shingles])) if self.ids else None

    def weights(self, shingles: np.ndarray) -> np.ndarray:
        """Rarity among the items; a shingle of none is as rare as one of one item."""
        if not len(self.cells):
            return np.ones(len(shingles))
        wanted = cell(shingles)
        at = np.minimum(np.searchsorted(self.cells, wanted), len(self.cells) - 1)
        return np.log((self.n_items + 1) / np.where(self.cells[at] == wanted, self.counts[at], 1))

    def bit_sums(self, shingles: np.ndarray) -> np.ndarray:
        out = np.zeros(BITS)
        for at in range(0, len(shingles), _WINDOWS):
            part = shingles[at : at + _WINDOWS]
            out += (signs(part) * self.weights(part)[:, None]).sum(0)
        return out

    def alike(self, window: np.ndarray, item: int) -> float:
        """Weighted similarity of two shingle multisets."""
        own = self.shingles[item]
        values, at = np.unique(np.concatenate((window, own)), return_inverse=True)
        a, b = np.bincount(at[: len(window)], minlength=len(values)), np.bincount(at[len(window) :], minlength=len(values))
        w = self.weights(values)
        return float((w * np.minimum(a, b)).sum() / (w * np.maximum(a, b)).sum())

    def hits(self, shingles: np.ndarray) -> np.ndarray:
        """Places of shingles that some item has."""
        place = np.flatnonzero(self.filter[cell(shingles)])
        at = np.minimum(np.searchsorted(self.known, shingles[place]), len(self.known) - 1)
        return place[self.known[at] == shingles[place]]

    def found_in(self, words: np.ndarray, k: int, shingles: np.ndarray, hits: np.ndarray) -> dict[int, tuple[float, int]]:
        """Best similarity and window start by item, for a document's words, its k-word shingles and the places of those that items have."""
        best: dict[int, tuple[float, int]] = {}
        at = np.searchsorted(self.known, shingles[hits])
        begin, end = np.searchsorted(self.held[0], at), np.searchsorted(self.held[0], at, "right")
        items = np.unique(np.concatenate([self.held[1][a:b] for a, b in zip(begin.tolist(), end.tolist(), strict=True)]))
        # A document shorter than an item is its own one window. Its weight bounds the overlap; what can reach the similarity is compared exactly.
        longer = items[self.sizes[items] > len(words)]
        for item in longer[self.weights(shingles).sum() >= self.similarity * self.totals[longer] - 1e-6].tolist() if len(longer) else ():
            value = self.alike(shingles, item)
            if value >= self.similarity - 1e-9:
                best[item] = (value, 0)
        for size in np.unique(self.sizes[items]).tolist():
            if len(words) < size or min(K, size) != k:
                continue
            n = size - k + 1  # shingles in a window
            last = len(shingles) - n
            covered = np.zeros(last + 2, np.int64)  # window starts from which a hit is in the window
            np.add.at(covered, np.maximum(np.minimum(hits - n + 1, last), 0), 1)
            np.add.at(covered, np.minimum(hits, last) + 1, -1)
            starts = np.flatnonzero(np.cumsum(covered[:-1]) > 0)
            cuts = np.flatnonzero(np.diff(starts) > 1) + 1
            for run in (part[at : at + _WINDOWS] for part in np.split(starts, cuts) for at in range(0, len(part), _WINDOWS)):
                part = shingles[run[0] : run[-1] + n]
                sums = np.concatenate((np.zeros((1, BITS)), np.cumsum(signs(part) * self.weights(part)[:, None], 0)))
                prints = packed(np.round(sums[n:] - sums[:-n], 6))
                for w, item in zip(*(x.tolist() for x in self.index.near(prints)), strict=True):
                    if self.sizes[item] == size:
                        value = self.alike(part[w : w + n], item)
                        if value >= self.similarity - 1e-9 and value > best.get(item, (0.0, 0))[0]:
                            best[item] = (value, int(run[0]) + w)
        return best

    def search(self, texts: list) -> Iterator[tuple[int, dict[int, tuple[float, int]]]]:
        """For each text that holds an item: its place, and similarity and start of the best window by item."""
        if not self.ids:
            return
        for first, _, run in pieces([words_of(t) for t in texts]):
            words = Words(run)
            h, end = words.hashes(), np.cumsum(words.counts)
            found: dict[int, dict] = {}
            for k in self.lengths:
                shingles = chained(h, k)
                hits = self.hits(shingles)
                for doc in np.unique(words.doc[hits]).tolist():
                    a, b = int(end[doc] - words.counts[doc]), int(end[doc])
                    own = hits[(hits >= a) & (hits <= b - k)] - a
                    if len(own):
                        found.setdefault(doc, {}).update(self.found_in(h[a:b], k, shingles[a : b - k + 1], own))
            for doc in sorted(found):
                if found[doc]:
                    yield first + doc, found[doc]


def cell_counts(texts: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Hash cells, ascending, and how many of the texts have a shingle there. The table has a fixed size at most."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(1 << _FILTER_BITS, np.int64)
        for batch in batches:
            for text in batch.column(0).to_pylist():
                total[np.unique(cell(item_shingles(text)[0]))] += 1
        found = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(found, pa.int32()), pa.array(total[found], pa.int64())], ["cell", "n"])

    rows = texts.select("text").mapInArrow(lean(count), "cell int, n long").groupBy("cell").agg(F.sum("n").alias("n")).toArrow()
    cells, counts = rows["cell"].to_numpy().astype(np.int64), rows["n"].to_numpy()
    order = np.argsort(cells)
    return cells[order], counts[order]


def item_texts(items: DataFrame) -> DataFrame:
    """ident, text: the different texts of items that have words; equal texts are one, named by their hash."""
    text = F.col("text").cast("string").alias("text")
    return items.select(F.xxhash64(text).alias("ident"), text).filter(F.col("text").rlike(r"[A-Za-z0-9\x80-\x{10FFFF}]")).distinct()


def benchmark_blocks(items: DataFrame, similarity: float = SIMILARITY) -> tuple[int, Iterator[Benchmark]]:
    """The number of blocks of about ITEMS texts at most, and the blocks, each made when it is asked for."""
    small_batches(items.sparkSession)
    rows = item_texts(items)
    total = rows.count()
    n = max(1, -(-total // ITEMS))

    def made() -> Iterator[Benchmark]:
        counts = cell_counts(rows)
        for i in range(n):
            block = rows.filter(F.pmod(F.xxhash64("text", F.lit("block")), F.lit(n)) == i) if n > 1 else rows
            yield Benchmark(sorted(map(tuple, block.collect())), similarity, counts, total)

    return n, made()


def contaminated(docs: DataFrame, items: DataFrame, similarity: float = SIMILARITY) -> DataFrame:
    """doc_id, item_id, similarity, start_word for each item that a document holds."""
    ready = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    n, blocks = benchmark_blocks(items, similarity)
    out = None
    for block in blocks:

        def search(batches: Iterator[pa.RecordBatch], block=block) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                rows = [(batch.column(0)[at + i].as_py(), block.ids[item], value, start) for at in range(0, batch.num_rows, _ROWS) for i, found in block.search(batch.column(1).slice(at, _ROWS).to_pylist()) for item, (value, start) in sorted(found.items())]
                columns = zip(*rows, strict=True) if rows else ([], [], [], [])
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, (pa.int64(), pa.int64(), pa.float64(), pa.int64()), strict=True)], ["doc_id", "ident", "similarity", "start_word"])

        found = ready.mapInArrow(lean(search), "doc_id long, ident long, similarity double, start_word long")
        found = written(found, "hits") if n > 1 else found
        out = found if out is None else out.unionAll(found)
    ids = items.select(F.xxhash64(F.col("text").cast("string")).alias("ident"), F.col("item_id").cast("long").alias("item_id"))
    ids = F.broadcast(ids) if ids.count() <= _BROADCAST_ITEMS else ids
    return out.join(ids, "ident").select("doc_id", "item_id", "similarity", "start_word")


def drop_contaminated(docs: DataFrame, items: DataFrame, similarity: float = SIMILARITY) -> DataFrame:
    """The rows of docs that hold no item. Rows stay where they are; with several blocks each pass but the last is written."""
    at_text = docs.columns.index("text")
    n, blocks = benchmark_blocks(items, similarity)
    for i, block in enumerate(blocks):

        def keep(batches: Iterator[pa.RecordBatch], block=block) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                clean = np.ones(batch.num_rows, bool)
                for at in range(0, batch.num_rows, _ROWS):
                    for j, _ in block.search(batch.column(at_text).slice(at, _ROWS).to_pylist()):
                        clean[at + j] = False
                yield batch.filter(pa.array(clean))

        docs = docs.mapInArrow(lean(keep), docs.schema)
        docs = written(docs, "clean") if i < n - 1 else docs
    return docs
