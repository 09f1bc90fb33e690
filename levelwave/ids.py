"""Vertex ids that tell what they stand for: key * 16 + kind."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

KINDS = {"part": 0, "supplier": 1, "customer": 2, "order": 3, "nation": 4, "region": 5, "page": 6, "link": 7, "event": 8, "user": 9, "document": 10, "vector": 11, "turn": 12}


def tag(key: Column | str, kind: str) -> Column:
    return (F.col(key) if isinstance(key, str) else key).cast("long") * 16 + KINDS[kind]


def vertex_key(vertex: Column | str) -> Column:
    return F.shiftright(F.col(vertex) if isinstance(vertex, str) else vertex, 4)


def vertex_kind(vertex: Column | str) -> Column:
    return F.pmod(F.col(vertex) if isinstance(vertex, str) else vertex, F.lit(16)).cast("int")


def untag(vertex: Column | str) -> Column:
    """(kind, key) of a tagged id, the kind by its name."""
    names = F.create_map(*[F.lit(x) for name, k in KINDS.items() for x in (k, name)])
    return F.struct(F.element_at(names, vertex_kind(vertex)).alias("kind"), vertex_key(vertex).alias("key"))


def hashed_key(text: Column) -> Column:
    """A 56-bit key of a string, from its MD5."""
    return F.conv(F.substring(F.md5(text), 1, 14), 16, 10).cast("long")
