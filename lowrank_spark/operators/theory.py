"""Collision probabilities of AND/OR banding, a planner for p and q, and empirical curves."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def pair_probability(prob: float, p: int, q: int) -> float:
    """Chance that a pair whose codes agree with `prob` becomes a candidate: falls in p, rises in q."""
    return 1 - (1 - prob**p) ** q


def collision(pairs: DataFrame, prob: str, ps: list[int], qs: list[int]) -> DataFrame:
    """The other columns of pairs + (p, q, and_prob, or_prob) on a grid of parameters; `prob` holds the chance that two codes agree."""
    ints = lambda xs: F.explode(F.array(*[F.lit(x).cast("int") for x in xs]))
    grid = pairs.withColumn("p", ints(ps)).withColumn("q", ints(qs))
    both = F.pow(prob, "p")
    return grid.select(*[c for c in pairs.columns if c != prob], "p", "q", F.round(both, 9).alias("and_prob"), F.round(1 - F.pow(1 - both, "q"), 9).alias("or_prob"))


def plan_pq(near: float, far: float, recall: float, false_rate: float, n_columns: int = 0, bucket: int = 1000, g: int = 8, max_p: int = 12, max_q: int = 2000) -> tuple[int, int] | None:
    """Smallest p, then q, with pair_probability(near) >= recall and pair_probability(far) <= false_rate.

    p * g bits must also keep mean buckets of n_columns columns below `bucket`.
    """
    least = math.ceil(math.log2(max(1.0, n_columns / bucket)) / g) if n_columns else 1
    for p in range(max(1, least), max_p + 1):
        hit = near**p
        q = 1 if hit >= 1 else math.ceil(math.log(1 - recall) / math.log(1 - hit)) if hit > 0 else max_q + 1
        if q <= max_q and pair_probability(far, p, q) <= false_rate:
            return p, q
    return None


def empirical_curve(code_rows: DataFrame, edges: DataFrame, bins: int = 10) -> DataFrame:
    """(bin, n_pairs, n_agree, n_codes): how often the codes of a pair agree, by similarity."""
    a = code_rows.select(F.col("j").alias("j1"), "rep", F.col("code").alias("c1"))
    b = code_rows.select(F.col("j").alias("j2"), "rep", F.col("code").alias("c2"))
    e = edges.select("j1", "j2", F.least(F.lit(bins - 1), F.floor(F.col("s") * bins)).cast("long").alias("bin"))
    x = e.join(a, "j1").join(b, ["j2", "rep"])
    return x.groupBy("bin").agg(F.count_distinct("j1", "j2").alias("n_pairs"), F.count_if(F.col("c1") == F.col("c2")).alias("n_agree"), F.count(F.lit(1)).alias("n_codes"))
