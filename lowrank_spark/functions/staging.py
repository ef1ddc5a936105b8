"""Computed-once columns.

Catalyst copies a projected expression into every filter above it, and into lambdas, where it would run once per
element. A generator over a one-element array is opaque to that: its columns are computed exactly once per row.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def once(df: DataFrame, cols: dict[str, Column], keep: list[str] | None = None) -> DataFrame:
    """df (or its columns `keep`) with the named columns, each evaluated once per row."""
    base = [F.col(c) for c in (df.columns if keep is None else keep) if c not in cols]
    return df.select(*base, F.inline_outer(F.array(F.struct(*[e.alias(n) for n, e in cols.items()]))))
