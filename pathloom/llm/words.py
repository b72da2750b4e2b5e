"""Vectorised words, hashes and shingles of many texts at once (numpy; runs inside Arrow batches on executors).

Words are maximal runs outside space and \\x09-\\x0D of the UTF-8 text with A-Z lower-cased. A null text has no words.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

_PIECE = 1 << 20
_BASE = 0x9E3779B97F4A7C15


def _powers(n: int) -> np.ndarray:
    out = np.empty(n, np.uint64)
    out[0] = 1
    if n > 1:
        out[1:] = np.uint64(_BASE)
        with np.errstate(over="ignore"):
            np.multiply.accumulate(out, out=out)
    return out


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit integers that spreads every input bit."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _is_space() -> np.ndarray:
    out = np.zeros(256, bool)
    out[[0x20, *range(0x09, 0x0E)]] = True
    return out


def encoded(text: str | None, lower: bool = True) -> bytes:
    raw = text.encode("utf-8", "surrogatepass") if isinstance(text, str) else b""
    return raw.lower() if lower else raw


def pieces(texts: list[bytes], limit: int = _PIECE) -> Iterator[tuple[int, int, list[bytes]]]:
    """Runs [from, to) of texts of about limit bytes together; one long text makes a run of its own."""
    begin, size = 0, 0
    for i, t in enumerate(texts):
        if size and size + len(t) > limit:
            yield begin, i, texts[begin:i]
            begin, size = i, 0
        size += len(t) + 1
    if begin < len(texts):
        yield begin, len(texts), texts[begin:]


class Words:
    """Words of a run of texts: starts, lens into body (the bytes of all words); doc: index of the text of each word."""

    def __init__(self, texts: list[bytes]):
        raw = np.frombuffer(b"\n".join([*texts, b""]), np.uint8)
        space = _is_space()[raw]
        edge = np.diff(np.concatenate(([1], space, [1])).astype(np.int8))
        begin, end = np.flatnonzero(edge == -1), np.flatnonzero(edge == 1)
        self.body = raw[~space]
        self.lens = (end - begin).astype(np.int64)
        self.starts = np.cumsum(self.lens) - self.lens
        bounds = np.cumsum([len(t) + 1 for t in texts])
        self.doc = np.searchsorted(bounds, begin, "right")
        self.n_docs = len(texts)
        self.counts = np.bincount(self.doc, minlength=len(texts))
        self._at = None

    def at(self) -> np.ndarray:
        """Offset of each byte in its word."""
        if self._at is None:
            self._at = np.arange(len(self.body)) - np.repeat(self.starts, self.lens)
        return self._at

    def hashes(self, first: int | None = None, body: np.ndarray | None = None) -> np.ndarray:
        """A 64-bit hash of each word, or of its first bytes."""
        if not len(self.lens):
            return np.empty(0, np.uint64)
        at, bytes_ = self.at(), self.body if body is None else body
        with np.errstate(over="ignore"):
            part = (bytes_.astype(np.uint64) + np.uint64(1)) * _powers(int(self.lens.max()))[at]
            if first is not None:
                part[at >= first] = 0
            lens = self.lens if first is None else np.minimum(self.lens, first)
            return mix(np.add.reduceat(part, self.starts) + lens.astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))


def chained(h: np.ndarray, k: int) -> np.ndarray:
    """Hash of each run of k consecutive words (len(h) - k + 1 of them)."""
    n = len(h) - k + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    out = np.full(n, k, np.uint64)
    with np.errstate(over="ignore"):
        for i in range(k):
            out = mix(out * np.uint64(_BASE) + h[i : i + n])
    return out


def shingle_sets(texts: list[str | None], k: int) -> Iterator[np.ndarray]:
    """Per text, the ascending distinct hashes of its k-word shingles; with fewer words the whole sequence is the one shingle."""
    raw = [encoded(t) for t in texts]
    for _, _, run in pieces(raw):
        words = Words(run)
        h = words.hashes()
        grams = chained(h, k)
        at = 0
        for n in words.counts.tolist():
            if n >= k:
                yield np.unique(grams[at : at + n - k + 1])
            elif n:
                yield chained(h[at : at + n], n)
            else:
                yield np.empty(0, np.uint64)
            at += n
