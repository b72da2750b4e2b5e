"""Small graphs with known answers: label, src, dst."""

from pathloom.functions.automaton import compile_expr
from pathloom.functions.expr import parse_pattern
from pathloom.sources.graph import EDGE, EdgeTable

STEP = [("a", 3, 1), ("a", 1, 2), ("a", 2, 6), ("b", 3, 5), ("b", 2, 4), ("b", 7, 3)]
CHAIN = [("a", 1, 2), ("a", 2, 3)]
LOOP = [("a", 1, 2), ("a", 2, 1)]
ZIGZAG = [("a", 1, 2), ("a", 3, 2), ("a", 3, 4), ("a", 5, 4)]
TWO = [("a", 1, 2), ("a", 7, 8), ("b", 2, 3), ("b", 3, 7)]
RING = [("d", i, i % 5 + 1) for i in range(1, 6)]
HUB = [("c", 10, 1), ("c", 11, 1), ("g", 12, 2), ("d", 1, 2), ("d", 2, 3), ("e", 1, 9), ("e", 3, 9)]
RARE = [("p", 1, 2), ("p", 2, 3), ("p", 1, 3), ("p", 4, 5), ("r", 3, 4)]
DIAMOND = [("p", 1, 2), ("p", 1, 3), ("p", 2, 4), ("p", 3, 4)]


def graph(spark, rows):
    return EdgeTable(spark.createDataFrame(rows, EDGE))


def dfa(text):
    return compile_expr(parse_pattern(text))


def ends(df):
    return sorted(r["v"] for r in df.collect())


def pairs(df):
    return sorted((r["seed"], r["v"]) for r in df.collect())
