"""Model parameters as DataFrames: rows (i, b, u) and columns (j, bh, v) plus neighbour weights (j, k, w, c)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from lowrank_spark.functions.hashing import text, uniform
from lowrank_spark.runtime import Scratch


def vector(tag: str, key: Column, f: int) -> Column:
    """f deterministic values in +-1/sqrt(f), from the hash of (tag, key, place)."""
    scale = 2.0 / f**0.5
    return F.array(*[(uniform(text(tag, key, k)) - 0.5) * F.lit(scale) for k in range(f)])


def init_rows(im: DataFrame, f: int) -> DataFrame:
    return im.select("i").distinct().select("i", vector("u", F.col("i"), f).alias("u"))


def init_cols(im: DataFrame, f: int) -> DataFrame:
    return im.select("j").distinct().select("j", vector("v", F.col("j"), f).alias("v"))


def init_neighbours(top: DataFrame, spread: float = 0.0) -> DataFrame:
    """(j, k, w, c): zeros, or hashed values in +-spread/2."""
    if not spread:
        return top.select("j", "k", F.lit(0.0).alias("w"), F.lit(0.0).alias("c"))
    one = lambda t: (uniform(text(t, F.col("j"), F.col("k"))) - 0.5) * F.lit(spread)
    return top.select("j", "k", one("w").alias("w"), one("c").alias("c"))


def dot(a: str, b: str) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


class Versions:
    """Parameter tables as numbered folders; a version counts once its write has ended, and old ones are removed."""

    def __init__(self, spark, name: str, keep: int = 2):
        self.scratch, self.keep, self.held = Scratch(spark, name), keep, []

    def commit(self, df: DataFrame) -> DataFrame:
        out = self.scratch.keep(df)
        self.held.append(out)
        while len(self.held) > self.keep:
            self.scratch.drop(self.held.pop(0))
        return out
