"""Counterfactual-regularised toxicity classifier.

A logistic regression on which words, and which beginnings of words, a text holds. Beside the loss of each labelled text it pays for
every change of score when the identity terms in the text are swapped for others of their group: strength x (score - swapped score)^2. A word
that only names a group so can't carry a score of its own, and neutral mentions of groups are not marked.

The identity terms are a parameter; texts without any have no swapped twin and only the plain loss. Learning is sparse and online, with an
absolute penalty that keeps words of no use at weight 0; scores are sparse sums over a fixed number of hash buckets.

Defined results: null and empty texts have the constant only, and get its score. Rows without doc_id are scored, not held out. Missing or null
labels are not learnt; without any, every score is 0.5, which predicts 1 by the contract's threshold (and the filter keeps such rows).
Repeated rows get equal scores. Whole texts are read, of any length. Empty tables give empty results. Other columns are ignored (op) or kept (filter).
"""

from __future__ import annotations

import re

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .linear import BUCKET_BITS, SAMPLE, Ftrl, Sparse, held_out, labelled_sample, model_of, scored, sigmoid
from .words import Words, encoded, mix, pieces

THRESHOLD, EPOCHS, RATE, L1, L2, STRENGTH = 0.5, 10, 2.0, 3.0, 0.0, 4.0
BEGINNINGS = (4, 5, 6)
#: Groups of identity terms; each term is swapped for the next of its group.
IDENTITY_TERMS = (
    ("women", "men"), ("woman", "man"), ("girls", "boys"), ("female", "male"), ("gay", "straight", "lesbian"), ("transgender", "cisgender"),
    ("muslim", "christian", "jewish", "hindu", "buddhist", "atheist"), ("muslims", "christians", "jews", "hindus", "buddhists", "atheists"),
    ("black", "white", "asian", "latino"), ("immigrants", "citizens"), ("african", "european"), ("blind", "deaf", "disabled"), ("old", "young"),
    ("femmes", "hommes"), ("musulmans", "chrétiens", "juifs"), ("frauen", "männer"), ("muslime", "christen", "juden"), ("mujeres", "hombres"), ("musulmanes", "cristianos", "judíos"),
)
#: ASCII marks at the ends of words are no part of them.
_MARKS = bytes(b if chr(b).isalnum() or b >= 0x80 else 0x20 for b in range(256))


def swapped(text: str, terms=IDENTITY_TERMS) -> str | None:
    """The text with each identity term exchanged; None if it holds none."""
    other = {t: group[(i + 1) % len(group)] for group in terms for i, t in enumerate(group)}
    if not other:
        return None
    new, n = re.subn(r"\w+", lambda m: other.get(m[0].lower(), m[0]), text), 0
    return new[0] if new[0] != text else None


def features(texts: list) -> list[Sparse]:
    """Distinct buckets of words and beginnings of words, all of value 1; bucket 0 is the constant."""
    out = []
    shift = np.uint64(64 - BUCKET_BITS)
    for _, _, run in pieces([encoded(t).translate(_MARKS) for t in texts]):
        words = Words(run)
        kinds = [words.hashes()]
        for n in BEGINNINGS:
            h = mix(words.hashes(first=n) ^ np.uint64(n))
            kinds.append(np.where(words.lens >= n, h, np.uint64(0)))
        at = np.stack([(h >> shift).astype(np.int32) for h in kinds], 1) if len(words.lens) else np.empty((0, 1 + len(BEGINNINGS)), np.int32)
        end = np.cumsum(words.counts)
        for a, b in zip((end - words.counts).tolist(), end.tolist(), strict=True):
            i = np.unique(np.append(at[a:b].ravel(), 0))
            out.append((i, np.ones(len(i), np.float32)))
    return out


def twin_features(texts: list, terms=IDENTITY_TERMS) -> list[tuple[Sparse, Sparse | None]]:
    """Features of each text and of its swapped twin."""
    twins = [swapped(t, terms) if isinstance(t, str) else None for t in texts]
    other = iter(features([t for t in twins if t is not None]))
    return [(x, None if t is None else next(other)) for x, t in zip(features(texts), twins, strict=True)]


def fit(rows: list[tuple[Sparse, Sparse | None]], y: np.ndarray, strength: float = STRENGTH) -> np.ndarray:
    learner = Ftrl(1 << BUCKET_BITS, RATE, L1, L2)
    for epoch in range(EPOCHS):
        for i in np.random.default_rng(epoch).permutation(len(rows)).tolist():
            (at, _), twin = rows[i]
            w = learner.weights(at)
            p = sigmoid(w.sum())
            if twin is None:
                learner.step(at, np.full(len(at), p - y[i]), w)
                continue
            all_ = np.union1d(at, twin[0])
            w = learner.weights(all_)
            one, two = np.isin(all_, at), np.isin(all_, twin[0])
            q = sigmoid(w[two].sum())
            pull = 2 * strength * (p - q)
            learner.step(all_, one * (p - y[i] + pull * p * (1 - p)) - two * (pull * q * (1 - q)), w)
    return learner.weights(slice(None))


def train(docs: DataFrame, labels: DataFrame, terms=IDENTITY_TERMS, strength: float = STRENGTH, bound: int = SAMPLE) -> np.ndarray:
    return model_of(labelled_sample(docs, labels, "toxic", bound), lambda texts: twin_features(texts, terms), lambda rows, y: fit(rows, y, strength))


def toxicity_scores(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD, **how) -> DataFrame:
    """doc_id, held_out, score, predicted of every row of docs."""
    rows = scored(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), features, train(docs, labels, **how))
    return rows.select("doc_id", held_out().alias("held_out"), F.col("_score").alias("score"), (F.col("_score") >= threshold).cast("int").alias("predicted"))


def drop_toxic(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD, **how) -> DataFrame:
    """The rows of docs that score under the threshold, or all where nothing was learnt."""
    weights = train(docs, labels, **how)
    return scored(docs, features, weights, lambda p: p < threshold) if weights.any() else docs
