"""Vertex numbers: kind x 10^14 + key."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

ROOM = 10**14
#: Kinds of vertices by name.
KINDS = {
    "region": 1, "nation": 2, "customer": 3, "supplier": 4, "part": 5, "order": 6, "item": 7, "user": 8, "event": 9, "event_type": 10, "turn": 11, "page": 12,
    "href": 13, "doc": 14, "source": 15, "lang": 16, "vector": 17, "vector_class": 18, "bench_item": 19, "brand": 20, "part_type": 21, "segment": 22, "priority": 23, "host": 24,
}


def number(kind: str, key: int) -> int:
    return KINDS[kind] * ROOM + key


def vid(kind: str, key: Column | str) -> Column:
    key = F.col(key) if isinstance(key, str) else key
    return F.lit(KINDS[kind] * ROOM).cast("long") + key.cast("long")


def kind_of(v: Column | str) -> Column:
    return F.expr(f"{v} div {ROOM}") if isinstance(v, str) else F.floor(v / F.lit(ROOM))
