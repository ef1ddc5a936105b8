"""Connected components of an edge table by alternating large-star and small-star rounds.

Every round is two min-aggregations (combined map-side) joined back to the edges; no neighbourhood is ever collected.
The number of rounds grows with the logarithm of the longest path. Each round's edges are a table in the shared
scratch folder, which cuts the lineage; the round before is deleted.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lowrank_spark.runtime import Scratch

MAX_ROUNDS = 60


def connected(edges: DataFrame, scratch: Scratch) -> DataFrame:
    """(node, comp): comp is the smallest node reachable; nodes without an edge do not appear."""
    a, b = edges.columns[:2]
    e = edges.where(F.col(a) != F.col(b)).select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).distinct()
    e = scratch.keep(e)
    mark = _mark(e)
    for _ in range(MAX_ROUNDS):
        if mark[0] == 0:
            break
        both = e.union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        star = both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        star = star.distinct()
        low = star.groupBy("u").agg(F.min("v").alias("m"))
        j = star.join(low, "u")
        nxt = j.where("v != m").select(F.col("v").alias("u"), F.col("m").alias("v")).union(low.select("u", F.col("m").alias("v"))).distinct()
        nxt = scratch.keep(nxt)
        new = _mark(nxt)
        scratch.drop(e)
        e = nxt
        if new == mark:
            break
        mark = new
    else:
        raise RuntimeError(f"components have not settled in {MAX_ROUNDS} rounds")
    return e.select(F.col("u").alias("node"), F.col("v").alias("comp")).union(e.select(F.col("v"), F.col("v")).distinct())


def _mark(e: DataFrame) -> tuple:
    r = e.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("u", "v")), F.sum(F.pmod(F.xxhash64("v", "u"), F.lit(1_000_003)))).first()
    return tuple(r)
