"""Canonical 8-byte cells: every value becomes a BIGINT, and its bytes are those of the big-endian number."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Stands for NULL; no other value may use it.
NULL_CELL = -(1 << 63)


def integer(value: Column) -> Column:
    return F.coalesce(value.cast("bigint"), F.lit(NULL_CELL))


def cents(value: Column) -> Column:
    """Money as cents; printing doubles differs between engines, rounding them does not."""
    return F.coalesce(F.round(value * 100).cast("bigint"), F.lit(NULL_CELL))


def micro(value: Column) -> Column:
    return F.coalesce(F.round(value.cast("double") * 1_000_000).cast("bigint"), F.lit(NULL_CELL))


def micros_of(timestamp: Column) -> Column:
    """Microseconds since 1970, UTC session time."""
    return F.coalesce(F.unix_micros(timestamp.cast("timestamp")), F.lit(NULL_CELL))


def cell_hex(cell: Column) -> Column:
    return F.lpad(F.hex(cell), 16, "0")


def utf8(value: Column) -> Column:
    return F.encode(F.coalesce(value, F.lit("")), "UTF-8")
