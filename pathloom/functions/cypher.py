"""Which expressions a graph pattern language without path algebra can state: single hops, and repetition of one hop.

A repetition may repeat a label, or a choice of labels of one direction; a repeated concatenation can't be stated.
"""

from __future__ import annotations

from .expr import Alt, Concat, Empty, Expr, Label, Opt, Plus, Star


class NotExpressible(ValueError):
    """The expression is outside the pattern language."""


def hop(expr: Expr) -> tuple[tuple[str, ...], int] | None:
    """Labels and direction if the expression is a label, or a choice of labels of one direction."""
    parts = expr.parts if isinstance(expr, Alt) else (expr,)
    if all(isinstance(p, Label) for p in parts) and len({p.inv for p in parts}) == 1:
        return tuple(p.name for p in parts), parts[0].inv
    return None


def is_cypher_expressible(expr: Expr) -> bool:
    if isinstance(expr, (Label, Empty)):
        return True
    if isinstance(expr, Concat):
        return all(map(is_cypher_expressible, expr.parts))
    if isinstance(expr, Alt):
        return hop(expr) is not None or all(map(is_cypher_expressible, expr.parts))
    if isinstance(expr, Opt):
        return hop(expr.body) is not None
    return isinstance(expr, (Star, Plus)) and hop(expr.body) is not None


def to_cypher(expr: Expr, source: int) -> str:
    """A counting query from one source vertex. Alternatives of whole patterns become a UNION of branches."""
    if not is_cypher_expressible(expr):
        raise NotExpressible(str(expr))

    def branches(e: Expr) -> list[list[str]]:
        reps = {Label: "", Alt: "", Star: "*0..", Plus: "*1..", Opt: "*0..1"}
        simple = hop(e if isinstance(e, (Label, Alt)) else getattr(e, "body", e))
        if isinstance(e, Empty):
            return [[]]
        if simple and type(e) in reps:
            names, inv = simple
            edge = f"[:{'|'.join(names)}{reps[type(e)]}]"
            return [[f"<-{edge}-" if inv else f"-{edge}->"]]
        if isinstance(e, Concat):
            out: list[list[str]] = [[]]
            for p in e.parts:
                out = [a + b for a in out for b in branches(p)]
            return out
        return [b for p in e.parts for b in branches(p)]

    def match(chain: list[str]) -> str:
        nodes = ["(s {id: %d})" % source, *["()"] * (len(chain) - 1), "(v)"] if chain else ["(v {id: %d})" % source]
        return "MATCH " + "".join(n + e for n, e in zip(nodes, [*chain, ""], strict=True)) + " RETURN v"

    parts = [match(b) for b in branches(expr)]
    return parts[0].replace("RETURN v", "RETURN count(DISTINCT v)") if len(parts) == 1 else "CALL { " + " UNION ".join(parts) + " } RETURN count(DISTINCT v)"
