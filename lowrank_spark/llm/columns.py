"""Columns of an input that an operator does not know, kept out of the way of its own."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def shield(docs: DataFrame, known: tuple[str, ...]) -> DataFrame:
    """docs with every column but the known ones under a name that no operator uses."""
    return docs.select(*[F.col(f"`{c}`").alias(c if c in known else f"_carried_{n}") for n, c in enumerate(docs.columns)])


def unshield(df: DataFrame, docs: DataFrame) -> DataFrame:
    """The columns of docs, as they stand in df, under their own names."""
    have = set(df.columns)
    return df.select(*[F.col(f"_carried_{n}" if f"_carried_{n}" in have else f"`{c}`").alias(c) for n, c in enumerate(docs.columns)])
