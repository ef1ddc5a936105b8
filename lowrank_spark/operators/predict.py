"""The four-part prediction: baseline, explicit neighbours, implicit neighbours, factors; any subset for ablations."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from lowrank_spark.operators import biases, neigh
from lowrank_spark.operators.params import dot

PARTS = frozenset({"base", "explicit", "implicit", "factor"})


def neighbour_terms(attached: DataFrame, mu: DataFrame, b: DataFrame, bh: DataFrame, weights: DataFrame) -> DataFrame:
    """(i, j, ex, im, n_ex, n_im): the two scaled neighbour sums of every entry."""
    x = attached.join(weights, ["j", "k"]).join(b, "i", "left").join(bh.select(F.col("j").alias("nbr"), F.col("bh").alias("bn")), "nbr", "left").crossJoin(F.broadcast(mu))
    res = F.col("rn") - (F.col("mu") + F.coalesce("b", F.lit(0.0)) + F.coalesce("bn", F.lit(0.0)))
    ex, im = F.col("kind") == "explicit", F.col("kind") == "implicit"
    s = x.groupBy("i", "j").agg(
        F.coalesce(F.sum(F.when(ex, res * F.col("w"))), F.lit(0.0)).alias("sx"),
        F.coalesce(F.sum(F.when(im, F.col("c"))), F.lit(0.0)).alias("si"),
        F.count_if(ex).alias("n_ex"),
        F.count_if(im).alias("n_im"),
    )
    inv = lambda n: F.when(F.col(n) > 0, 1 / F.sqrt(F.col(n).cast("double"))).otherwise(0.0)
    return s.select("i", "j", (F.col("sx") * inv("n_ex")).alias("ex"), (F.col("si") * inv("n_im")).alias("im"), "n_ex", "n_im")


def score(im: DataFrame, mu: DataFrame, b: DataFrame, bh: DataFrame, rows: DataFrame, cols: DataFrame, top: DataFrame | None = None, weights: DataFrame | None = None, parts=PARTS, rated: DataFrame | None = None, clamp: tuple[float, float] | None = None) -> DataFrame:
    """im + pred (and n_ex, n_im where neighbours take part). `rated` is the training matrix when im is a test set."""
    x = biases.score(im, mu, b, bh).withColumnRenamed("pred", "base")
    total = F.col("base") if "base" in parts else F.lit(0.0)
    if top is not None and parts & {"explicit", "implicit"}:
        t = neighbour_terms(neigh.attach(im, top, rated), mu, b, bh, weights)
        x = x.join(t, ["i", "j"], "left")
        if "explicit" in parts:
            total = total + F.coalesce("ex", F.lit(0.0))
        if "implicit" in parts:
            total = total + F.coalesce("im", F.lit(0.0))
    if "factor" in parts:
        x = x.join(rows.select("i", "u"), "i", "left").join(cols.select("j", "v"), "j", "left")
        total = total + F.coalesce(dot("u", "v"), F.lit(0.0))
    if clamp:
        total = F.least(F.lit(clamp[1]), F.greatest(F.lit(clamp[0]), total))
    return x.withColumn("pred", total)


def recommend(rows: DataFrame, cols: DataFrame, n: int, seen: DataFrame | None = None, blocks: int = 8) -> DataFrame:
    """(i, j, score, place): the n best columns of every row by u.v.

    Columns are cut into blocks; each row keeps the n best of a block before blocks meet, so what is shuffled is
    rows * blocks * n, not rows * columns. Pass the query rows only: the product itself is inherent.
    """
    c = cols.select("j", "v", F.pmod(F.xxhash64("j"), F.lit(blocks)).alias("blk"))
    r = rows.select("i", "u").withColumn("blk", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long"))))
    s = r.join(c, "blk").select("i", "j", "blk", dot("u", "v").alias("score"))
    if seen is not None:
        s = s.join(seen.select("i", "j"), ["i", "j"], "left_anti")
    best = F.col("score").desc()
    one = s.withColumn("p", F.row_number().over(Window.partitionBy("i", "blk").orderBy(best, "j"))).where(F.col("p") <= n)
    top = one.withColumn("place", F.row_number().over(Window.partitionBy("i").orderBy(best, "j"))).where(F.col("place") <= n)
    return top.select("i", "j", "score", F.col("place").cast("long").alias("place"))
