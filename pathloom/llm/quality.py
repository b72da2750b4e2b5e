"""Quality classifier: logistic regression on hashed word n-grams, learnt by follow-the-regularised-leader, scored as sparse dot products.

Features of a text are its 1-grams and 2-grams of words, and the same of word shapes (letters, digits and other bytes, runs cut to one,
with a mark for a word equal to the one before). Each n-gram counts with the root of its share of the text, so partly bad texts weigh as
much as their bad part. N-grams are hashed to a fixed number of buckets; the first bucket is the constant.

Defined results: null and empty texts have the constant only, and get its score. Rows without doc_id are scored, not held out. Labels of rows that
are missing or null are not learnt; without any, every score is 0.5. Repeated rows get equal scores. Whole texts are read, of any length.
Empty tables give empty results. Other columns are ignored (op) or kept (filter).
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .linear import BUCKET_BITS, SAMPLE, Ftrl, Sparse, held_out, labelled_sample, model_of, scored, sigmoid
from .words import Words, chained, encoded, mix, pieces

THRESHOLD, EPOCHS, RATE, L1, L2 = 0.3, 4, 0.5, 0.02, 0.05
_LETTER, _UPPER, _DIGIT, _SCALE = 1, 2, 3, 4.0


def _classes() -> np.ndarray:
    """Bytes by class; other ASCII bytes stand for themselves, bytes of longer characters are letters."""
    out = np.arange(256, dtype=np.uint8)
    out[0x80:] = _LETTER
    out[ord("a") : ord("z") + 1] = _LETTER
    out[ord("A") : ord("Z") + 1] = _UPPER
    out[ord("0") : ord("9") + 1] = _DIGIT
    return out


def shapes(words: Words) -> np.ndarray:
    """A hash of each word's shape: its byte classes with runs cut to one."""
    kind = _classes()[words.body]
    fresh = np.ones(len(kind), bool)
    fresh[1:] = kind[1:] != kind[:-1]
    fresh[words.starts] = True
    place = np.cumsum(fresh) - 1
    place -= np.repeat(place[words.starts], words.lens)
    with np.errstate(over="ignore"):
        part = np.where(fresh & (place < 8), mix(kind.astype(np.uint64) + (place.astype(np.uint64) << np.uint64(8))), np.uint64(0))
        return mix(np.add.reduceat(part, words.starts)) if len(words.starts) else np.empty(0, np.uint64)


def features(texts: list) -> list[Sparse]:
    out = []
    shift = np.uint64(64 - BUCKET_BITS)
    for _, _, run in pieces([encoded(t, lower=False) for t in texts]):
        words = Words(run)
        lowered = words.body.copy()
        lowered[(lowered >= ord("A")) & (lowered <= ord("Z"))] += 32
        word, shape = words.hashes(body=lowered), shapes(words)
        same = np.zeros(len(word), bool)
        same[1:] = (word[1:] == word[:-1]) & (words.doc[1:] == words.doc[:-1])
        shape = np.where(same, mix(np.uint64([77]))[0], shape)
        kinds = [(mix(h ^ np.uint64(i + 1)), n) for i, (h, n) in enumerate(((word, 1), (chained(word, 2), 2), (shape, 1), (chained(shape, 2), 2)))]
        end = np.cumsum(words.counts)
        for a, b in zip((end - words.counts).tolist(), end.tolist(), strict=True):
            at, value = [np.zeros(1, np.int64)], [np.ones(1)]
            for h, n in kinds:
                if b - a >= n:
                    i, count = np.unique((h[a : b - n + 1] >> shift).astype(np.int64), return_counts=True)
                    at.append(i), value.append(np.sqrt(count / (b - a - n + 1)) * _SCALE)
            out.append((np.concatenate(at), np.concatenate(value)))
    return out


def fit(rows: list[tuple[Sparse, None]], y: np.ndarray) -> np.ndarray:
    learner = Ftrl(1 << BUCKET_BITS, RATE, L1, L2)
    for epoch in range(EPOCHS):
        for i in np.random.default_rng(epoch).permutation(len(rows)).tolist():
            at, value = rows[i][0]
            w = learner.weights(at)
            learner.step(at, (sigmoid((w * value).sum()) - y[i]) * value, w)
    return learner.weights(slice(None))


def train(docs: DataFrame, labels: DataFrame, bound: int = SAMPLE) -> np.ndarray:
    return model_of(labelled_sample(docs, labels, "quality", bound), lambda texts: [(x, None) for x in features(texts)], fit)


def quality_scores(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD, bound: int = SAMPLE) -> DataFrame:
    """doc_id, held_out, score, predicted of every row of docs."""
    rows = scored(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), features, train(docs, labels, bound))
    return rows.select("doc_id", held_out().alias("held_out"), F.col("_score").alias("score"), (F.col("_score") >= threshold).cast("int").alias("predicted"))


def keep_good(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD, bound: int = SAMPLE) -> DataFrame:
    """The rows of docs that score the threshold or more."""
    return scored(docs, features, train(docs, labels, bound), lambda p: p >= threshold)
