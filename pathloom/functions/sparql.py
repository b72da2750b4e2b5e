"""SPARQL property paths: one triple pattern with a path between two ends, as found in query logs."""

from __future__ import annotations

import re
from collections.abc import Mapping
from dataclasses import dataclass

from .expr import Expr, Label, ParseError, _Reader


@dataclass(frozen=True)
class PathPattern:
    """A path between two ends; an end is the full name of a vertex, or None for a variable."""

    expr: Expr
    source: str | None
    target: str | None


def expand(raw: str, prefixes: Mapping[str, str]) -> str:
    """The full name of an IRI in angle brackets, a prefixed name, or a plain name."""
    if raw[0] == "<":
        return raw[1:-1]
    prefix, colon, local = raw.partition(":")
    if not colon:
        return raw
    if prefix not in prefixes:
        raise ParseError(f"unknown prefix {prefix!r}")
    return prefixes[prefix] + local


def parse_sparql_path(text: str, prefixes: Mapping[str, str]) -> PathPattern:
    """Parse ``subject path object``; a subject or object that begins with ``?`` or ``$`` is a variable."""
    m = re.fullmatch(r"\s*(\S+)\s+(.+?)\s+(\S+?)\s*\.?\s*", text, re.DOTALL)
    if not m:
        raise ParseError(f"no triple pattern: {text!r}")
    end = lambda raw: None if raw[0] in "?$" else expand(raw, prefixes)
    return PathPattern(_Reader(m[2], lambda raw: expand(raw, prefixes)).whole(), end(m[1]), end(m[3]))


def shorten(expr: Expr, base: str) -> Expr:
    """The expression with labels relative to a base name."""
    if isinstance(expr, Label):
        return Label(expr.name.removeprefix(base), expr.inv)
    if hasattr(expr, "parts"):
        return type(expr)(tuple(shorten(p, base) for p in expr.parts))
    return type(expr)(shorten(expr.body, base)) if hasattr(expr, "body") else expr
