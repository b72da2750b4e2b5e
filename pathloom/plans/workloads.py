"""Experiment workloads on the given tables: 20 patterns with both ends, 7 chains, a query log, and batches of seeds."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.vertices import KINDS, ROOM, number
from ..sources.graph import LabeledGraph

MANY = 1000


@dataclass(frozen=True)
class Work:
    """A pattern with one fixed end (or none), and the kind of vertices its batch takes seeds from."""

    name: str
    pattern: str
    end: str | None
    kind: str | None
    key: int | None

    @property
    def vertex(self) -> int | None:
        return None if self.kind is None else number(self.kind, self.key)


_BENCH = (
    ("bulk_supply sourced_from located", "supplier", "nation"),
    ("(bulk_supply sourced_from located)|(located adjacent adjacent)", "supplier", "nation"),
    ("adjacent*", "nation", "nation"),
    ("adjacent* within", "nation", "region"),
    ("adjacent+", "nation", "nation"),
    ("(bulk_supply sourced_from)*", "supplier", "supplier"),
    ("ordered_by resident_of (adjacent|within)", "order", "region"),
    ("ordered_by resident_of (adjacent|within)*", "order", "region"),
    ("(located|resident_of)(adjacent|within)", "order", "region"),
    ("(located|resident_of)(adjacent|within)*", "order", "region"),
)
_SEED_KEYS = {"supplier": 7, "nation": 3, "region": 3, "order": 42}


def bench20() -> list[Work]:
    out = []
    for i, (pattern, source, target) in enumerate(_BENCH):
        out.append(Work(f"bench{2 * i + 1:02d}_s", pattern, "S", source, _SEED_KEYS[source]))
        out.append(Work(f"bench{2 * i + 2:02d}_d", pattern, "D", target, _SEED_KEYS[target]))
    return out


def chain7() -> list[Work]:
    rows = (
        ("sourced_from located adjacent+ within+", "S", "part", 9), ("ordered_by resident_of adjacent+ within+", "D", "region", 3), ("is_customer placed follows+ has_item+", "S", "user", 5),
        ("^is_customer acted then+ event_kind+", "S", "customer", 5), ("has_item of_part succ_part+ made_by+", "S", "order", 42), ("placed has_item of_part+ succ_part+", "S", "customer", 5),
        ("ordered_by ^ordered_by follows+ has_item+", "S", "order", 42),
    )
    return [Work(f"chain7_{i}", *r) for i, r in enumerate(rows, 1)]


def query_log() -> list[Work]:
    rows = (
        ("placed", "S", "customer", 5), ("placed/has_item", "S", "customer", 5), ("is_customer/placed/has_item/of_part", "S", "user", 5), ("follows+", "S", "order", 42), ("then*", "S", "event", 0),
        ("ordered_by?", "S", "order", 42), ("(adjacent|within)*", "S", "nation", 3), ("located/adjacent*", "S", "supplier", 7), ("succ_part*/made_by", "S", "part", 9), ("^within", "S", "region", 3),
        ("^ordered_by/has_item", "S", "customer", 5), ("resident_of/^resident_of", "S", "customer", 7), ("(links/^links)+", "S", "page", 0), ("(bulk_supply/sourced_from)*", "S", "supplier", 7),
        ("(^adjacent|adjacent)+", "S", "nation", 3), ("((adjacent+/within)?/^within)*", "S", "nation", 3), ("no_such_label|within", "S", "nation", 3), ("within/within", "S", "nation", 3),
        ("adjacent*", "S", "region", 3), ("within*", "D", "region", 3), ("(located|resident_of)/within", "D", "region", 3), ("reply*", "S", "turn", 0), ("near+/in_class", "S", "vector", 0),
        ("same_text+/in_lang", "S", "doc", 0), ("event_kind", "D", "event_type", 1), ("succ_part+/made_by", "D", "brand", 3), ("quotes/^quotes", "S", "doc", 29), ("placed", "S", "customer", 10**9),
        ("placed", None, None, None),
    )
    return [Work(f"log_{i:02d}", *r) for i, r in enumerate(rows, 1)]


def hashed_seeds(graph: LabeledGraph, kind: str, labels, most: int = MANY) -> DataFrame:
    """v: up to most vertices of a kind that stand in an edge of the labels, chosen by a hash of their key."""
    low, high = KINDS[kind] * ROOM, (KINDS[kind] + 1) * ROOM
    key = (F.col("v") - low) % (1 << 31)
    own = graph.vertices(labels).filter((F.col("v") >= low) & (F.col("v") < high))
    return own.orderBy(key * 2654435761 % 4294967296, "v").limit(most)
