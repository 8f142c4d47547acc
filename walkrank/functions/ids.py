"""Node ids: a kind and a key in one long, and ids from text."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..config import KEY_BITS

KINDS = ("part", "supplier", "customer", "order", "nation", "region", "user", "hour_event", "document", "page", "conversation", "item", "vector")
TEXT_BASE = 1 << 61


def pack(kind: str, key: str | Column) -> Column:
    key = F.col(key) if isinstance(key, str) else key
    return (key.cast("long") + F.lit(KINDS.index(kind) << KEY_BITS)).cast("long")


def kind_of(id_: Column) -> Column:
    return F.when(id_ >= TEXT_BASE, F.lit("text")).otherwise(F.element_at(F.array(*[F.lit(k) for k in KINDS]), (F.shiftright(id_, KEY_BITS) + 1).cast("int")))


def key_of(id_: Column) -> Column:
    return F.when(id_ >= TEXT_BASE, id_ - TEXT_BASE).otherwise(id_.bitwiseAND(F.lit((1 << KEY_BITS) - 1)))


def text_id(text: Column) -> Column:
    """60 bits of a digest, above all packed ids."""
    return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("long") + F.lit(TEXT_BASE)


def sql_pack(kind: str, key: str) -> str:
    return f"({key}::bigint + {KINDS.index(kind) << KEY_BITS})"


def sql_text_id(text: str) -> str:
    return f"(('0x' || left(md5({text}), 15))::bigint + {TEXT_BASE})"
