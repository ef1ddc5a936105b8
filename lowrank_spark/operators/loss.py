"""The regularised objective, its terms, and its logistic form."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lowrank_spark.config import Rates


def sigmoid(z):
    return 1 / (1 + F.exp(-z))


def data_term(scored: DataFrame, loss: str = "squared") -> DataFrame:
    """One row (data): squared error, or log-loss of y = r in {0, 1} with score pred."""
    if loss == "squared":
        return scored.agg(F.sum((F.col("r") - F.col("pred")) * (F.col("r") - F.col("pred"))).alias("data"))
    p = F.greatest(F.lit(1e-12), F.least(F.lit(1 - 1e-12), sigmoid(F.col("pred"))))
    return scored.agg(F.sum(-(F.col("r") * F.log(p) + (1 - F.col("r")) * F.log(1 - p))).alias("data"))


def penalties(b: DataFrame, bh: DataFrame, rows: DataFrame, cols: DataFrame, attached: DataFrame | None, weights: DataFrame | None, lam: Rates) -> DataFrame:
    """One row (pb, pbh, pu, pv, pw, pc). Neighbour weights are penalised once per entry that uses them."""
    sq = lambda c: F.aggregate(c, F.lit(0.0), lambda s, x: s + x * x)
    one = b.agg(F.sum(F.col("b") * F.col("b")).alias("x")).select((F.col("x") * lam.b).alias("pb"))
    one = one.crossJoin(bh.agg((F.sum(F.col("bh") * F.col("bh")) * lam.bh).alias("pbh")))
    one = one.crossJoin(rows.agg((F.sum(sq("u")) * lam.u).alias("pu"))).crossJoin(cols.agg((F.sum(sq("v")) * lam.v).alias("pv")))
    if attached is None:
        return one.withColumns({"pw": F.lit(0.0), "pc": F.lit(0.0)})
    x = attached.join(weights, ["j", "k"])
    w = F.sum(F.when(F.col("kind") == "explicit", F.col("w") * F.col("w")).otherwise(0.0)) * lam.w
    c = F.sum(F.when(F.col("kind") == "implicit", F.col("c") * F.col("c")).otherwise(0.0)) * lam.c
    return one.crossJoin(x.agg(w.alias("pw"), c.alias("pc")))


def objective(scored: DataFrame, b, bh, rows, cols, attached, weights, lam: Rates, loss: str = "squared") -> DataFrame:
    t = data_term(scored, loss).crossJoin(penalties(b, bh, rows, cols, attached, weights, lam))
    return t.withColumn("total", F.col("data") + F.col("pb") + F.col("pbh") + F.col("pu") + F.col("pv") + F.col("pw") + F.col("pc"))


def partial(scored: DataFrame, which: str, params: DataFrame, lam: Rates) -> DataFrame:
    """One row per owner of the sub-problem `which` (u, v, b, bh): its error and penalty with the rest frozen."""
    key = "i" if which in ("u", "b") else "j"
    e = scored.groupBy(key).agg(F.sum((F.col("r") - F.col("pred")) * (F.col("r") - F.col("pred"))).alias("data"))
    norm = F.aggregate(which, F.lit(0.0), lambda s, x: s + x * x) if which in ("u", "v") else F.col(which) * F.col(which)
    return e.join(params.select(key, (norm * getattr(lam, which)).alias("penalty")), key)
