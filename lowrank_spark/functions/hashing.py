"""Hash expressions that give the same bits in Spark and in other SQL engines (md5), and fast ones (xxhash64)."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def text(*parts) -> Column:
    """Parts (columns or constants) as one ':'-joined string."""
    return F.concat_ws(":", *[p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts])


def md5_int(s: Column, digits: int = 8, start: int = 1) -> Column:
    """Hex digits of the md5 of a string, as a long (15 digits at most)."""
    return F.conv(F.substring(F.md5(s), start, digits), 16, 10).cast("long")


def md5_byte(s: Column) -> Column:
    return md5_int(s, 2)


def uniform(s: Column) -> Column:
    """In [0, 1), from 32 md5 bits."""
    return md5_int(s, 8) / F.lit(4294967296.0)


def duck_int(sql: str, digits: int = 8, start: int = 1) -> str:
    """The DuckDB form of md5_int."""
    return f"concat('0x', substr(md5({sql}), {start}, {digits}))::bigint"
