"""Rows with nulls, empty and long texts, ties, repeats and further columns; and texts that are copies, near copies or neither."""

import random

DOCS = "doc_id long, text string, lang string, source string, n_chars long, _score double, token long"
VOCABULARY = [f"{a}{b}{c}" for a in ("ba", "ke", "lo", "mi", "tu", "ra") for b in ("n", "s", "t", "vel", "rd") for c in ("o", "i", "ar", "ek")]


def prose(rng, n):
    return " ".join(rng.choice(VOCABULARY) for _ in range(n))


def edited(rng, text, n):
    words = text.split(" ")
    for i in rng.sample(range(len(words)), n):
        words[i] = rng.choice(VOCABULARY) + "x"
    return " ".join(words)


def odd_rows():
    return [
        (None, "a row without id and more words", "en", "s1", 1, 0.5, 1), (1, None, None, None, None, None, None), (2, "", "en", "s1", 0, 0.1, 2), (3, " \t\n ", "en", "", 3, None, 3),
        (4, "One", "en", "s2", 3, 1.0, 4), (5, "one", "en", "s2", 3, 1.0, 4), (6, "two words", "en", "s1", 9, 1.0, 5), (6, "two words", "en", "s1", 9, 1.0, 5),
        (7, "Ça marche\u00a0bien, déjà vu ça — 日本語 текст", "fr", "s3", 5, 1.0, 6), (8, "long " * 20000 + "end", "en", "s1", 100003, 1.0, 7), (9, "x" * 50000, "en", "s1", 50000, 1.0, 8),
    ]


def docs(spark, rows=None):
    return spark.createDataFrame(odd_rows() if rows is None else rows, DOCS)


def corpus(seed=1, families=6, copies=5, alone=30, size=60):
    """doc_id, text: families of near and exact copies between texts of their own."""
    rng, texts = random.Random(seed), []
    for _ in range(families):
        base = prose(rng, size)
        texts += [base, base, base.upper()] + [edited(rng, base, rng.randrange(1, 5)) for _ in range(copies)]
    texts += [prose(rng, rng.randrange(1, 2 * size)) for _ in range(alone)]
    rng.shuffle(texts)
    return list(enumerate(texts, 100))
