"""Accuracy measures; each ends in one row."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def errors(pred: DataFrame, scale: float = 1.0) -> DataFrame:
    """One row (n, rmse, mae) of rows (r, pred); `scale` undoes a rescaling."""
    d = (F.col("r") - F.col("pred")) * scale
    return pred.agg(F.count(F.lit(1)).alias("n"), F.sqrt(F.avg(d * d)).alias("rmse"), F.avg(F.abs(d)).alias("mae"))


def rmse(pred: DataFrame, scale: float = 1.0) -> float:
    return errors(pred, scale).first()["rmse"]


def hit_ratio(scores: DataFrame, k: int = 10) -> DataFrame:
    """One row (n, hr, ndcg) of rows (i, j, y, score) with one y = 1 a row: is it among the k best?"""
    w = Window.partitionBy("i").orderBy(F.col("score").desc(), "j")
    top = scores.withColumn("place", F.row_number().over(w)).where((F.col("place") <= k) & (F.col("y") == 1))
    n = scores.where("y = 1").agg(F.count_distinct("i").alias("n"))
    hits = top.agg(F.count(F.lit(1)).alias("h"), F.coalesce(F.sum(1 / F.log2(F.col("place") + 1.0)), F.lit(0.0)).alias("g"))
    return n.crossJoin(hits).select("n", (F.col("h") / F.greatest("n", F.lit(1))).alias("hr"), (F.col("g") / F.greatest("n", F.lit(1))).alias("ndcg"))


def topk_recall(approx: DataFrame, exact: DataFrame) -> DataFrame:
    """One row (n_exact, n_approx, n_common, recall, precision) of two (j, nbr) tables."""
    a, e = approx.select("j", "nbr").distinct(), exact.select("j", "nbr").distinct()
    both = a.join(e, ["j", "nbr"]).agg(F.count(F.lit(1)).alias("n_common"))
    x = e.agg(F.count(F.lit(1)).alias("n_exact")).crossJoin(a.agg(F.count(F.lit(1)).alias("n_approx"))).crossJoin(both)
    return x.select("n_exact", "n_approx", "n_common", (F.col("n_common") / F.greatest("n_exact", F.lit(1))).alias("recall"), (F.col("n_common") / F.greatest("n_approx", F.lit(1))).alias("precision"))


def group_purity(top: DataFrame, group) -> DataFrame:
    """Share of neighbours in the column's own group; `group` maps a Column to its group."""
    return top.agg(F.avg((group(F.col("j")) == group(F.col("nbr"))).cast("double")).alias("purity"))


def timed(action) -> tuple[float, object]:
    t = time.perf_counter()
    out = action()
    return time.perf_counter() - t, out


def run_noop(df: DataFrame) -> float:
    """Seconds to compute all of df, to no sink."""
    return timed(lambda: df.write.format("noop").mode("overwrite").save())[0]


def time_to_target(history: list[dict], target: float) -> float | None:
    """Seconds until an epoch's rmse is at most the target."""
    return next((h["seconds"] for h in history if h["rmse"] <= target), None)


def speedup(base: float, other: float) -> float:
    return base / other


def noise_gap(clean: float, noisy: float) -> float:
    return abs(noisy - clean)
