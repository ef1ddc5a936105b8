"""Full-batch gradient steps of every parameter group, as joins and sums.

Each line of the stochastic update, averaged over the entries of the parameter's owner and applied once; all
gradients are taken at the old values. `e` is the error of the squared loss, or y - sigmoid(score).
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lowrank_spark.config import TrainConfig
from lowrank_spark.operators.loss import sigmoid


def rate(alpha: float, beta: float, t: float) -> float:
    """Step size in epoch t, from 0 on."""
    return alpha / (1 + beta * t**1.5)


def rates_table(times: DataFrame, alpha: float, beta: float) -> DataFrame:
    """times (a column t, and others) + gamma, the step size at t."""
    t = F.col("t").cast("double")
    return times.withColumn("gamma", F.round(F.lit(alpha) / (1 + F.lit(beta) * F.pow(t, F.lit(1.5))), 9))


def with_error(scored: DataFrame, loss: str = "squared") -> DataFrame:
    e = F.col("r") - F.col("pred") if loss == "squared" else F.col("r") - sigmoid(F.col("pred"))
    return scored.withColumn("e", e)


def _mean_step(old, grad, gamma: float, lam: float):
    return old + F.lit(gamma) * (grad - F.lit(lam) * old)


def step_b(err: DataFrame, b: DataFrame, cfg: TrainConfig, t: int = 0) -> DataFrame:
    g = err.groupBy("i").agg(F.avg("e").alias("g"))
    return b.join(g, "i").select("i", _mean_step(F.col("b"), F.col("g"), rate(cfg.alpha.b, cfg.beta, t), cfg.lam.b).alias("b"))


def step_bh(err: DataFrame, bh: DataFrame, cfg: TrainConfig, t: int = 0) -> DataFrame:
    g = err.groupBy("j").agg(F.avg("e").alias("g"))
    return bh.join(g, "j").select("j", _mean_step(F.col("bh"), F.col("g"), rate(cfg.alpha.bh, cfg.beta, t), cfg.lam.bh).alias("bh"))


def _vector_step(err: DataFrame, key: str, mine: str, other: str, f: int, gamma: float, lam: float, params: DataFrame) -> DataFrame:
    g = err.groupBy(key).agg(*[F.avg(F.col("e") * F.get(F.col(other), F.lit(k))).alias(f"g{k}") for k in range(f)])
    new = F.array(*[_mean_step(F.get(F.col(mine), F.lit(k)), F.col(f"g{k}"), gamma, lam) for k in range(f)])
    return params.select(key, mine).join(g, key).select(key, new.alias(mine))


def step_u(err: DataFrame, rows: DataFrame, cfg: TrainConfig, t: int = 0) -> DataFrame:
    """err carries the columns' vectors v."""
    return _vector_step(err, "i", "u", "v", cfg.F, rate(cfg.alpha.u, cfg.beta, t), cfg.lam.u, rows)


def step_v(err: DataFrame, cols: DataFrame, cfg: TrainConfig, t: int = 0) -> DataFrame:
    return _vector_step(err, "j", "v", "u", cfg.F, rate(cfg.alpha.v, cfg.beta, t), cfg.lam.v, cols)


def step_w(err: DataFrame, attached: DataFrame, mu, b, bh, weights: DataFrame, cfg: TrainConfig, t: int = 0) -> DataFrame:
    """(j, k, w) where some entry uses the neighbour explicitly."""
    x = attached.where("kind = 'explicit'").join(err.select("i", "j", "e", "n_ex"), ["i", "j"]).join(b, "i", "left")
    x = x.join(bh.select(F.col("j").alias("nbr"), F.col("bh").alias("bn")), "nbr", "left").crossJoin(F.broadcast(mu))
    res = F.col("rn") - (F.col("mu") + F.coalesce("b", F.lit(0.0)) + F.coalesce("bn", F.lit(0.0)))
    g = x.groupBy("j", "k").agg(F.avg(F.col("e") * res / F.sqrt(F.col("n_ex").cast("double"))).alias("g"))
    return weights.join(g, ["j", "k"]).select("j", "k", _mean_step(F.col("w"), F.col("g"), rate(cfg.alpha.w, cfg.beta, t), cfg.lam.w).alias("w"))


def step_c(err: DataFrame, attached: DataFrame, weights: DataFrame, cfg: TrainConfig, t: int = 0) -> DataFrame:
    x = attached.where("kind = 'implicit'").join(err.select("i", "j", "e", "n_im"), ["i", "j"])
    g = x.groupBy("j", "k").agg(F.avg(F.col("e") / F.sqrt(F.col("n_im").cast("double"))).alias("g"))
    return weights.join(g, ["j", "k"]).select("j", "k", _mean_step(F.col("c"), F.col("g"), rate(cfg.alpha.c, cfg.beta, t), cfg.lam.c).alias("c"))


def ccd_rank_one(im: DataFrame, cols: DataFrame, lam: float) -> tuple[DataFrame, DataFrame]:
    """One cyclic sweep of coordinate descent on one rank: rows given columns (j, v), then columns given rows.

    The penalty is weighted by the owner's number of entries.
    """
    x = im.join(cols, "j")
    u = x.groupBy("i").agg((F.sum(F.col("r") * F.col("v")) / (F.lit(lam) * F.count(F.lit(1)) + F.sum(F.col("v") * F.col("v")))).alias("u"))
    y = im.join(u, "i")
    v = y.groupBy("j").agg((F.sum(F.col("r") * F.col("u")) / (F.lit(lam) * F.count(F.lit(1)) + F.sum(F.col("u") * F.col("u")))).alias("v"))
    return u, v


def als_rank_one(im: DataFrame, cols: DataFrame, lam: float) -> tuple[DataFrame, DataFrame]:
    """One alternating least-squares sweep at rank one, plain ridge."""
    x = im.join(cols, "j")
    u = x.groupBy("i").agg((F.sum(F.col("r") * F.col("v")) / (F.lit(lam) + F.sum(F.col("v") * F.col("v")))).alias("u"))
    y = im.join(u, "i")
    v = y.groupBy("j").agg((F.sum(F.col("r") * F.col("u")) / (F.lit(lam) + F.sum(F.col("u") * F.col("u")))).alias("v"))
    return u, v


def nmf_rows(scored: DataFrame, rows: DataFrame, f: int) -> DataFrame:
    """Multiplicative step of the rows of a non-negative model: u_k * sum(r v_k) / sum(pred v_k). scored carries v."""
    sums = scored.groupBy("i").agg(*[F.sum(F.col("r") * F.get(F.col("v"), F.lit(k))).alias(f"n{k}") for k in range(f)], *[F.sum(F.col("pred") * F.get(F.col("v"), F.lit(k))).alias(f"d{k}") for k in range(f)])
    new = F.array(*[F.get(F.col("u"), F.lit(k)) * F.when(F.col(f"d{k}") > 0, F.col(f"n{k}") / F.col(f"d{k}")).otherwise(1.0) for k in range(f)])
    return rows.select("i", "u").join(sums, "i").select("i", new.alias("u"))
