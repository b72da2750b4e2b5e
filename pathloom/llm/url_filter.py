"""URL filters: host and path rules, indexed by their rarest literal token, in DataFrame functions only.

A rule is (host, path, action). It fits a url whose host is the rule's or a subdomain of it and whose path starts with the rule's.
A second list holds patterns (name, pattern, action) for urls that no host rule fits. A pattern is text for the host and, after a bar, text for the path; it may
stand anywhere in them. In it * is any run of characters and ^ a place with no letter or digit on one side, the ends of host and path included.
Each rule has regular expressions, and tokens: the runs of letters and digits that every url which it fits must hold whole. Rules are indexed by the
one of their tokens that is rarest among the urls; a url runs only the expressions of the rules that its own tokens fetch.

Up to PLAN_RULES rules the index is a literal in the plan; more are a table that the urls' tokens are joined with.

Defined results: a null url, or one without "://", has empty host and path, fits no rule and gets the default verdict "allow".
Repeated rows are judged one by one. The rule that fits with the longest host and path wins; a tie goes to the smaller rule text.
An empty table gives an empty result. Other columns of the input are ignored; the rule list is a parameter of the caller.
"""

from __future__ import annotations

import re
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .store import written

PLAN_RULES = 500
#: Rules of the contract: host, path, action.
HOST_RULES = (("org", "/", "allow"), ("example.org", "/es/", "block"), ("example.org", "/en/1", "block"), ("com", "/fr/", "allow"), ("com", "/de/", "block"))
#: Patterns for urls without a host rule: name, pattern, action.
PATTERN_RULES = (
    ("gambling", "^casino^", "block"),
    ("adult", "^adult^", "block"),
    ("tracking", "^ads^", "block"),
    ("tracking pixels", "^cdn^|/pixel/*/beacon^", "block"),
)
_SPLIT = r"[^A-Za-z0-9]+"
_RULE = "token string, list string, rule string, length int, on_host string, on_path string, action string"


def url_host(url: Column) -> Column:
    """After the first :// up to /, ?, # or the end, A-Z lower-cased; empty without :// or url."""
    found = F.coalesce(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1), F.lit(""))
    return F.translate(found, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def url_path(url: Column) -> Column:
    """What follows the host up to ?, # or the end."""
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def literal_tokens(host: str, path: str) -> set[str]:
    """Tokens that every url which the rule fits must hold whole. What stands at the end of a path may go on in the url."""
    sure = path if path.endswith("/") else path.rpartition("/")[0]
    return {t for t in re.split(_SPLIT, f"{host}/{sure}") if t}


def pattern_expression(part: str) -> str:
    """The regular expression of a pattern's host or path text."""
    known = {"*": "(?s:.*)", "^": "(?:(?<![A-Za-z0-9])|(?![A-Za-z0-9]))"}
    return "".join(known.get(x, rf"\Q{x}\E") for x in re.split(r"([*^])", part) if x)


def pattern_tokens(pattern: str) -> set[str]:
    """Tokens that every url which the pattern fits must hold whole: those with a mark or ^ on both sides."""
    runs = (run for part in pattern.partition("|")[::2] for run in part.split("*"))
    return {t for run in runs for t in re.findall(r"(?<=[^A-Za-z0-9])[A-Za-z0-9]+(?=[^A-Za-z0-9])", run)}


def compiled(host_rules: Sequence[tuple], pattern_rules: Sequence[tuple]) -> list[tuple[set[str], tuple]]:
    """For each rule its sure tokens, and list, rule, length, on_host, on_path, action. on_host of a host rule is about host and path together."""
    out = [(literal_tokens(h, p), ("host", h + p, len(h + p), rf"^(?:[^/]*\.)?\Q{h}{p}\E" + ("" if p else "(?:/|$)"), "", a)) for h, p, a in host_rules]
    for name, pattern, action in pattern_rules:
        host, _, path = pattern.partition("|")
        out.append((pattern_tokens(pattern), ("pattern", name, 0, pattern_expression(host), pattern_expression(path), action)))
    return out


def rarest(tokens: set[str], counts: dict[str, int]) -> str:
    """The token that the fewest urls hold; "" of none, which every url holds."""
    return min(tokens, key=lambda t: (counts.get(t, 0), t), default="")


def held_tokens() -> Column:
    return F.array_distinct(F.array_append(F.split(F.concat_ws("/", "host", "path"), _SPLIT), F.lit("")))


def token_counts(urls: DataFrame, tokens: Sequence[str]) -> dict[str, int]:
    """In how many urls each of the rules' tokens stands; one pass over all urls, one row back for each token of a rule."""
    if len(tokens) <= PLAN_RULES:
        held = urls.select(F.explode(F.array_intersect(held_tokens(), F.array(*map(F.lit, tokens)))).alias("t"))
    else:
        known = urls.sparkSession.createDataFrame([(t,) for t in tokens], "t string")
        held = urls.select(F.explode(held_tokens()).alias("t")).join(known, "t")
    return {r[0]: r[1] for r in held.groupBy("t").count().collect()}


def _fits(rule: Column) -> Column:
    whole = F.rlike(F.concat("host", "path"), rule["on_host"])
    return F.when(rule["list"] == "host", whole).otherwise(F.rlike(F.col("host"), rule["on_host"]) & F.rlike(F.col("path"), rule["on_path"]))


def filter_urls(pages: DataFrame, host_rules: Sequence[tuple] = HOST_RULES, pattern_rules: Sequence[tuple] = PATTERN_RULES, id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """id_col, host, path, rule (of the host rule that fits, else null), pattern (name of the pattern that judged, else null), verdict."""
    urls = pages.select(F.col(id_col), url_host(F.col(url_col)).alias("host"), url_path(F.col(url_col)).alias("path"))
    rules = compiled(host_rules, pattern_rules)
    if not rules:
        return urls.select("*", F.lit(None).cast("string").alias("rule"), F.lit(None).cast("string").alias("pattern"), F.lit("allow").alias("verdict"))
    counts = token_counts(urls, sorted(set().union(*(t for t, _ in rules))))
    placed = [(rarest(tokens, counts), rule) for tokens, rule in rules]
    judged = _by_plan(urls, placed) if len(placed) <= PLAN_RULES else _by_table(urls, placed)
    named = lambda kind: F.when(F.col("_best.list") == kind, F.col("_best.rule"))
    return judged.select(id_col, "host", "path", named("host").alias("rule"), named("pattern").alias("pattern"), F.coalesce("_best.action", F.lit("allow")).alias("verdict"))


def _order(rule: Column) -> Column:
    return F.struct((-rule["length"]).alias("order"), rule["rule"].alias("rule"), rule["list"].alias("list"), rule["action"].alias("action"))


def _by_plan(urls: DataFrame, placed: list[tuple[str, tuple]]) -> DataFrame:
    """urls with _best, by rules that are literals in the plan."""
    names = [f.split()[0] for f in _RULE.split(", ")[1:]]
    index: dict[str, list[Column]] = {}
    for token, rule in placed:
        index.setdefault(token, []).append(F.struct(*(F.lit(x).alias(name) for name, x in zip(names, rule, strict=True))))
    keys = sorted(index)
    by_token = F.create_map(*(c for k in keys for c in (F.lit(k), F.array(*index[k]))))
    judged = urls.withColumn("_held", F.array_intersect(held_tokens(), F.array(*map(F.lit, keys))))
    fetched = F.flatten(F.transform("_held", lambda t: F.element_at(by_token, t)))
    best = F.get(F.array_sort(F.transform(F.filter(fetched, _fits), _order)), F.lit(0))
    return judged.withColumn("_best", F.when(F.size("_held") > 0, best))


def _by_table(urls: DataFrame, placed: list[tuple[str, tuple]]) -> DataFrame:
    """urls with _best, by rules in a table: the urls' tokens are joined with the rules' rarest ones."""
    rules = urls.sparkSession.createDataFrame([(token, *rule) for token, rule in placed], _RULE)
    rules = rules.select("token", F.struct(*rules.columns[1:]).alias("_rule"))
    numbered = written(urls.withColumn("_row", F.monotonically_increasing_id()), "urls")
    asked = numbered.select("_row", "host", "path", F.explode(held_tokens()).alias("token")).join(rules, "token").filter(_fits(F.col("_rule")))
    return numbered.join(asked.groupBy("_row").agg(F.min(_order(F.col("_rule"))).alias("_best")), "_row", "left")
