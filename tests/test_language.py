import random

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from pathloom.functions.automaton import Automaton, compile_expr, to_nfa
from pathloom.functions.cypher import NotExpressible, is_cypher_expressible, to_cypher
from pathloom.functions.expr import Alt, Concat, Empty, Label, Opt, ParseError, Plus, Star, parse_pattern
from pathloom.functions.sparql import parse_sparql_path, shorten

labels = st.builds(Label, st.sampled_from("abc"), st.integers(0, 1))
exprs = st.recursive(
    st.one_of(labels, st.just(Empty())),
    lambda x: st.one_of(st.lists(x, min_size=2, max_size=3).map(lambda p: Concat(tuple(p))), st.lists(x, min_size=2, max_size=3).map(lambda p: Alt(tuple(p))), x.map(Star), x.map(Plus), x.map(Opt)),
    max_leaves=6,
)
words = st.lists(st.tuples(st.sampled_from("abc"), st.integers(0, 1)), max_size=4).map(tuple)


def spells(e, word) -> bool:
    """Membership by definition."""
    if isinstance(e, Empty):
        return not word
    if isinstance(e, Label):
        return word == ((e.name, e.inv),)
    if isinstance(e, Alt):
        return any(spells(p, word) for p in e.parts)
    if isinstance(e, Concat):
        if len(e.parts) == 1:
            return spells(e.parts[0], word)
        return any(spells(e.parts[0], word[:i]) and spells(Concat(e.parts[1:]), word[i:]) for i in range(len(word) + 1))
    if isinstance(e, Opt):
        return not word or spells(e.body, word)
    if not word:
        return isinstance(e, Star) or spells(e.body, word)
    return any(spells(e.body, word[:i]) and (i == len(word) or spells(Star(e.body), word[i:])) for i in range(1, len(word) + 1))


@settings(max_examples=400, deadline=None)
@given(exprs, words)
def test_automata_accept_the_words_of_the_expression(e, w):
    want = spells(e, w)
    nfa = to_nfa(e)
    assert nfa.accepts(w) == want
    assert nfa.minimize().accepts(w) == want
    assert nfa.trim().accepts(w) == want
    assert (() in [w] and want) == (w == () and e.nullable())


@settings(max_examples=200, deadline=None)
@given(exprs, words)
def test_reversing_inverts_words(e, w):
    back = tuple((x, 1 - i) for x, i in reversed(w))
    assert compile_expr(e).reverse().accepts(back) == spells(e, w) == spells(e.inverse(), back)
    assert e.inverse().inverse() == e


@settings(max_examples=200, deadline=None)
@given(exprs, exprs, words)
def test_intersection(a, b, w):
    assert compile_expr(a).intersect(compile_expr(b)).accepts(w) == (spells(a, w) and spells(b, w))


@settings(max_examples=200, deadline=None)
@given(exprs)
def test_text_form_reads_back(e):
    assert compile_expr(parse_pattern(str(e))) == compile_expr(e)


@pytest.mark.parametrize(("text", "n"), [("d*", 1), ("d+", 2), ("a b c", 4), ("(a b)*", 2), ("(c|g)(d|e)*", 2), ("f g (d|e)*", 3), ("d* e", 2)])
def test_minimal_sizes(text, n):
    assert compile_expr(parse_pattern(text)).n == n


def test_intersection_has_one_word():
    both = compile_expr(parse_pattern("a* b")).intersect(compile_expr(parse_pattern("(a|b)(a|b)")))
    found = {w for n in range(5) for w in _all("ab", n) if both.accepts([(x, 0) for x in w])}
    assert found == {"ab"}


def _all(alphabet, n):
    return [""] if n == 0 else [x + w for x in alphabet for w in _all(alphabet, n - 1)]


def test_subset_limit_falls_back():
    e = parse_pattern("(a|b)* a (a|b)(a|b)(a|b)(a|b)")
    small = to_nfa(e).minimize(limit=8)
    rng = random.Random(1)
    for _ in range(50):
        w = [(rng.choice("ab"), 0) for _ in range(rng.randrange(8))]
        assert small.accepts(w) == to_nfa(e).accepts(w)


def test_parser():
    assert parse_pattern("a/^b | (c d)+ e?") == Alt((Concat((Label("a"), Label("b", 1))), Concat((Plus(Concat((Label("c"), Label("d")))), Opt(Label("e"))))))
    assert parse_pattern("^(a b)") == Concat((Label("b", 1), Label("a", 1)))
    assert parse_pattern("()") == Empty()
    assert parse_pattern("<http://x/y z>") == Label("http://x/y z")
    for bad in ("", "a |", "(a", "a)", "*", "a ! b"):
        with pytest.raises(ParseError):
            parse_pattern(bad)


def test_sparql_path():
    p = parse_sparql_path("wd:Q1 (wdt:P1/^wdt:P2)* ?x", {"wd": "urn:e:", "wdt": "urn:p:"})
    assert (p.source, p.target) == ("urn:e:Q1", None)
    assert shorten(p.expr, "urn:p:") == parse_pattern("(P1 ^P2)*")
    with pytest.raises(ParseError):
        parse_sparql_path("x:a x:b ?y", {})


@pytest.mark.parametrize(("text", "yes"), [("d*", True), ("a b c", True), ("f g (d|e)*", True), ("d* e", True), ("(a b)*", False), ("(^a|a)+", False), ("(^a|^b)+", True)])
def test_expressible(text, yes):
    e = parse_pattern(text)
    assert is_cypher_expressible(e) is yes
    if yes:
        assert to_cypher(e, 1).count("count(DISTINCT v)") == 1
    else:
        with pytest.raises(NotExpressible):
            to_cypher(e, 1)


def test_cypher_text():
    assert to_cypher(parse_pattern("a ^b+"), 7) == "MATCH (s {id: 7})-[:a]->()<-[:b*1..]-(v) RETURN count(DISTINCT v)"


def test_empty_automaton():
    a = Automaton(1, frozenset(), frozenset([0]), frozenset())
    assert not a.accepts([]) and a.trim().n == 0 and a.minimize().n in (0, 1)


def test_automaton_table_counts_the_given_edges(spark):
    from pathloom.plans.registry import QUERIES

    from .conftest import SF

    n = spark.read.parquet(f"{SF}/orders.parquet").count()
    assert sorted(map(tuple, QUERIES["automaton_table"](spark, SF).collect())) == [(0, "ordered_by", 0, 1, n), (0, "placed", 0, 0, n)]
