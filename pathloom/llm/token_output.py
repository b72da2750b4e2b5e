"""Token ids as ORC files: integer run-length encoding, row index, Bloom filter on the document id.

Documents are dealt by ranges of doc_id (ascending, null first; equal ids by a hash of the text, so that many texts of one id need not share a
file), each range is one sorted file of rows
(doc_id, ids array<int>). ORC stores the ids of a stripe with its integer run-length encoding, keeps minima and maxima of doc_id for
each row group and a Bloom filter of doc_id, so readers skip stripes by metadata and read stripes in parallel.

Every text is encoded whole with the tokenizers library (null: as empty), with its defaults but add_special_tokens=False; one end id follows each document. Texts that hold a
special string of the tokenizer file, such as its end of text, go to the library whole, which gives the string its own id.
Any other text is cut where the tokenizer cuts too: at spaces, and between letters and ASCII marks. A piece is given to the library once and its
ids are then looked up by a 64-bit hash in a table of fixed size; ids of the pieces in a row are the ids of the text (checked in the tests). Repeated rows are documents of their own. Very long texts are
encoded piece by piece. Empty tables give an empty folder of one file. Other columns of the input are ignored.
"""

from __future__ import annotations

import itertools
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .store import lean, new_path, small_batches, written
from .words import Words
from .words import encoded as encoded_text

END_ID, BLOOM_FPP, ROW_INDEX_STRIDE = 2, 0.01, 1000
#: Pieces that a worker remembers at most, as a power of 2, and their ids.
_SLOT_BITS, _POOL = 20, 1 << 22
_ROWS = 128


def _kinds() -> np.ndarray:
    """Bytes: 0 space, 1 ASCII letter, 2 byte of a longer character, 3 mark or digit at which a cut is safe, 4 apostrophe, control and white space."""
    out = np.full(256, 4, np.uint8)
    for b in range(0x21, 0x7F):
        out[b] = 1 if chr(b).isalpha() else 3
    out[0x80:], out[ord("'")], out[0x20] = 2, 4, 0
    return out


class Encoder:
    """Ids of texts. One for each worker process and tokenizer file, see encoder_for."""

    def __init__(self, path: str):
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = True
        self.normalize, self.model = self.tokenizer.normalizer.normalize_str, self.tokenizer.model.tokenize
        # The tokenizer spells bytes as characters: printable ones as they are, the rest from U+0100 on.
        plain = [b for b in range(256) if 0x21 <= b <= 0x7E or 0xA1 <= b <= 0xAC or b >= 0xAE]
        self.spelling = {b: 0x100 + i for i, b in enumerate(sorted(set(range(256)) - set(plain)))}
        self.key = np.zeros(1 << _SLOT_BITS, np.uint64)
        self.begin = np.zeros(1 << _SLOT_BITS, np.int32)
        self.size = np.zeros(1 << _SLOT_BITS, np.int32)
        self.pool, self.used = np.zeros(_POOL, np.int32), 0
        self.kinds = _kinds()
        contents = sorted(re.escape(t.content) for t in self.tokenizer.get_added_tokens_decoder().values())
        self.special = re.compile("|".join(contents), re.IGNORECASE).search if contents else lambda text: None  # more than the library finds does no harm
        self.odd = re.compile(r"[^\x00-\x7F]").search, regex.compile(rf"[^\x00-\x7F\p{{L}}]|[{self.unsafe_letters()}]").search

    def unsafe_letters(self) -> str:
        """Letters whose normal form is more than letters: beside the mark that they end in, the tokenizer does not cut where it would beside a letter."""
        letters = "".join(regex.findall(r"\p{L}", "".join(map(chr, (*range(0x80, 0xD800), *range(0xE000, 0x110000))))))
        forms = self.normalize(" ".join(letters)).split(" ")
        return "".join(c for c, form in zip(letters, forms, strict=True) if not regex.fullmatch(r"\p{L}+", form))

    def documents(self, texts: list[str], end_id: int) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts in a row, each with the end id, and the number of ids of each text; special strings have their own ids."""
        whole = [i for i, t in enumerate(texts) if self.special(t)]
        if not whole:
            return self.run(texts, end_id)
        held = set(whole)
        flat, sizes = self.run(["" if i in held else t for i, t in enumerate(texts)], end_id)
        parts = np.split(flat, np.cumsum(sizes)[:-1])
        self.tokenizer.encode_special_tokens = False
        for i in whole:
            parts[i] = np.array([*self.tokenizer.encode(texts[i], add_special_tokens=False).ids, end_id], np.int32)
        self.tokenizer.encode_special_tokens = True
        return np.concatenate(parts), np.array([len(p) for p in parts], np.int64)

    def run(self, texts: list[str], end_id: int) -> tuple[np.ndarray, np.ndarray]:
        """As documents, with special strings as ordinary text."""
        raw = [encoded_text(t, lower=True) for t in texts]
        # Longer characters count as letters in texts where all of them are and stay letters; else nothing is cut beside them.
        plain = np.array([not self.odd[0](t) or not self.odd[1](t) for t in texts], bool)
        body = np.frombuffer(b" ".join([*raw, b""]), np.uint8)
        sizes = np.array([len(r) + 1 for r in raw])
        kind = self.kinds[body]
        if not plain.all():
            kind[np.repeat(~plain, sizes) & (kind == 2)] = 5
        else:
            kind[kind == 2] = 1
        if plain.any() and not plain.all():
            kind[kind == 2] = 1
        filled = kind != 0
        cut = np.empty(len(kind), bool)
        cut[0] = True
        one, two = kind[:-1], kind[1:]
        cut[1:] = ((one == 1) & (two == 3)) | ((one == 3) & (two == 1)) | (one == 0)
        starts = np.flatnonzero(cut & filled)
        out_sizes = np.ones(len(texts), np.int64)
        if not len(starts):
            return np.full(len(texts), end_id, np.int32), out_sizes
        stops = np.append(starts[1:], len(body))
        place = np.cumsum(filled)
        lens = place[stops - 1] - place[starts] + 1  # bytes of the piece: up to the next piece, less spaces
        words = Words.__new__(Words)
        words.body, words.lens, words.starts, words._at = body[filled], lens, np.cumsum(lens) - lens, None
        h = words.hashes() | np.uint64(1)
        doc = np.searchsorted(np.cumsum(sizes), starts, "right")
        begin, size = self.lookup(h, body, starts, lens)
        out_sizes += np.bincount(doc, size, len(texts)).astype(np.int64)
        total = int(size.sum())
        at = np.repeat(begin - (np.cumsum(size) - size), size) + np.arange(total)
        out = np.full(total + len(texts), end_id, np.int32)
        out[np.arange(total) + np.repeat(doc, size)] = self.pool[at]
        return out, out_sizes

    def lookup(self, h: np.ndarray, body: np.ndarray, starts: np.ndarray, lens: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Places and numbers of ids in the pool for each piece; unknown pieces are encoded first."""
        slot = (h >> np.uint64(64 - _SLOT_BITS)).astype(np.int64)
        missing = np.flatnonzero(self.key[slot] != h)
        begin, size = self.begin[slot], self.size[slot]
        if len(missing):
            new, first, back = np.unique(h[missing], return_index=True, return_inverse=True)
            first = missing[first]
            pieces_ = [body[a : a + n].tobytes().decode("utf-8", "surrogatepass") for a, n in zip(starts[first].tolist(), lens[first].tolist(), strict=True)]
            ids = list(map(self.piece, pieces_))
            n = np.array([len(x) for x in ids], np.int32)
            flat = np.fromiter(itertools.chain.from_iterable(ids), np.int32, int(n.sum()))
            if self.used + len(flat) > len(self.pool):  # forget all; pieces of this call that were known are encoded again
                self.key[:], self.used = 0, 0
                if len(flat) > len(self.pool) // 2:
                    self.pool = np.zeros(4 * len(flat), np.int32)
                if len(missing) < len(h):
                    return self.lookup(h, body, starts, lens)
            at = self.used + np.cumsum(n) - n
            self.pool[self.used : self.used + len(flat)] = flat
            self.used += len(flat)
            spot = (new >> np.uint64(64 - _SLOT_BITS)).astype(np.int64)
            self.key[spot], self.begin[spot], self.size[spot] = new, at, n
            begin[missing], size[missing] = at[back], n[back]
        return begin.astype(np.int64), size.astype(np.int64)

    def piece(self, text: str) -> list[int]:
        """Ids of one piece. A word of letters alone is one unit of the tokenizer's, and goes straight to its merges."""
        word = text if text.isascii() else self.normalize(text)
        if not word.isalpha():
            return self.tokenizer.encode(text, add_special_tokens=False).ids
        return [t.id for t in self.model(word if word.isascii() else word.encode().decode("latin-1").translate(self.spelling))]

    def ids(self, text: str) -> list[int]:
        return self.run([text], -1)[0][:-1].tolist()


def encoder_for(path: str) -> Encoder:
    """The worker's encoder: what it remembers serves all tasks that the process runs."""
    import sys
    import types

    kept = sys.modules.setdefault("_pathloom_worker", types.ModuleType("_pathloom_worker"))
    known = kept.__dict__.setdefault("encoders", {})
    if path not in known:
        known[path] = Encoder(path)
    return known[path]


def encoded(docs: DataFrame, tokenizer_path: str, end_id: int = END_ID) -> DataFrame:
    """doc_id, ids for rows (doc_id, text), in their order."""

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = encoder_for(tokenizer_path)
        for batch in batches:
            for at in range(0, batch.num_rows, _ROWS):
                part = batch.slice(at, _ROWS)
                flat, sizes = encoder.documents([t or "" for t in part["text"].to_pylist()], end_id)
                offsets = pa.array(np.concatenate(([0], np.cumsum(sizes))), pa.int32())
                yield pa.RecordBatch.from_arrays([part["doc_id"], pa.ListArray.from_arrays(offsets, pa.array(flat))], ["doc_id", "ids"])

    return docs.select("doc_id", "text").mapInArrow(lean(encode), "doc_id long, ids array<int>")


def write_tokens(docs: DataFrame, path: str, tokenizer_path: str, end_id: int = END_ID, files: int | None = None) -> str:
    """One ORC file for each range of doc_id, ascending within and between files; as many as given, else by size as Spark plans them. docs is read
    twice, once for the ranges."""
    small_batches(docs.sparkSession)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    order = [F.col("doc_id").asc_nulls_first(), F.xxhash64("text"), F.col("text")]  # texts of one id may go to several files
    ranged = (rows.repartitionByRange(files, *order[:2]) if files else rows.repartitionByRange(*order[:2])).sortWithinPartitions(*order)
    out = encoded(ranged, tokenizer_path, end_id).write.mode("overwrite")
    out.option("orc.bloom.filter.columns", "doc_id").option("orc.bloom.filter.fpp", BLOOM_FPP).option("orc.row.index.stride", ROW_INDEX_STRIDE).option("compression", "zstd").orc(path)
    return path


def read_tokens(spark: SparkSession, path: str, ordered: bool = False) -> DataFrame:
    """doc_id, ids; filters on doc_id reach the stripes' metadata. With ordered also _file, _block, _row: the written order (a task reads the rows of a block in their order)."""
    rows = spark.read.schema("doc_id long, ids array<int>").orc(path)
    if not ordered:
        return rows
    return rows.select("doc_id", "ids", F.col("_metadata.file_name").alias("_file"), F.col("_metadata.file_block_start").alias("_block"), F.monotonically_increasing_id().alias("_row"))


def token_report(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 from the files. Windows run over one file's rows and over one row for each file."""

    def digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch["ids"]
            ends, flat = ids.offsets.to_numpy(), ids.values.to_numpy().astype("<u4")
            crc = [zlib.crc32(flat[a:b].tobytes()) for a, b in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([batch["doc_id"], batch["_file"], batch["_block"], batch["_row"], pa.array(np.diff(ends), pa.int64()), pa.array(crc, pa.int64())], ["doc_id", "file", "block", "row", "n_tokens", "ids_crc32"])

    rows = written(read_tokens(spark, path, ordered=True).mapInArrow(lean(digest), "doc_id long, file string, block long, row long, n_tokens long, ids_crc32 long"), "digests")
    part = F.regexp_extract("file", r"part-(\d+)", 1).cast("long")  # files are numbered in the order of their ranges
    files = rows.groupBy("file").agg(F.sum("n_tokens").alias("_n")).withColumn("_part", part)
    before = lambda w: F.coalesce(F.sum("_n").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    offsets = files.select("file", before(Window.partitionBy(F.lit(0)).orderBy("_part", "file")).alias("_offset"))
    placed = rows.join(offsets, "file").withColumnRenamed("n_tokens", "_n")
    within = Window.partitionBy("file").orderBy("block", "row")
    return placed.select("doc_id", (F.col("_offset") + before(within)).alias("start"), F.col("_n").alias("n_tokens"), "ids_crc32")


def round_trip(docs: DataFrame, tokenizer_path: str, end_id: int = END_ID) -> DataFrame:
    """The report of files written in the shared folder."""
    path = write_tokens(docs, new_path(docs.sparkSession, "tokens"), tokenizer_path, end_id)
    return token_report(docs.sparkSession, path)
