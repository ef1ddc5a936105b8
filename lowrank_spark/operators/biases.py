"""The baseline: overall mean and the deviations of rows and columns."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def means(im: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(mu), (i, b), (j, bh) from one pass with grouping sets."""
    g = im.groupingSets([[], ["i"], ["j"]], "i", "j").agg(F.avg("r").alias("m"), F.grouping_id().alias("g"))
    mu = g.where("g = 3").select(F.col("m").alias("mu"))
    b = g.where("g = 1").crossJoin(F.broadcast(mu)).select("i", (F.col("m") - F.col("mu")).alias("b"))
    bh = g.where("g = 2").crossJoin(F.broadcast(mu)).select("j", (F.col("m") - F.col("mu")).alias("bh"))
    return mu, b, bh


def score(im: DataFrame, mu: DataFrame, b: DataFrame, bh: DataFrame) -> DataFrame:
    """im + pred = mu + b + bh; an unseen id adds 0. mu is one row."""
    x = im.join(b, "i", "left").join(bh, "j", "left").crossJoin(F.broadcast(mu))
    return x.withColumn("pred", F.col("mu") + F.coalesce("b", F.lit(0.0)) + F.coalesce("bh", F.lit(0.0)))
