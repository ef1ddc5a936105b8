"""Exact column similarity over co-rated rows, and exact top-K neighbours.

The join on rows never meets unrelated pairs, so its cost is the sum of squared row degrees, not N squared. Rows above
`row_cap` can be thinned by hash with their sums re-weighted; the default keeps all.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from lowrank_spark.config import LAMBDA_RHO
from lowrank_spark.functions.blocks import dealt_sides
from lowrank_spark.functions.hashing import md5_int, text

ROW_BLOCK = 4096


def _weighted(im: DataFrame, row_cap: int | None) -> DataFrame:
    """im + wt: entries of a row above the cap are kept by hash with weight degree / cap."""
    if row_cap is None:
        return im.select("i", "j", "r", F.lit(1.0).alias("wt"))
    deg = im.groupBy("i").agg(F.count(F.lit(1)).alias("deg"))
    keep = md5_int(text("cap", F.col("i"), F.col("j")), 8) < F.lit(4294967296) * row_cap / F.col("deg")
    return im.join(deg, "i").where(keep).select("i", "j", "r", F.greatest(F.lit(1.0), F.col("deg") / row_cap).alias("wt"))


def pair_rows(im: DataFrame, row_cap: int | None = None) -> DataFrame:
    """(j1, j2, x, y, wt) for every row that has both columns, j1 < j2. Rows above ROW_BLOCK entries are joined block by block."""
    a, b, on = dealt_sides(_weighted(im, row_cap), ["i"], "j", ROW_BLOCK)
    x = a.withColumnsRenamed({"j": "j1", "r": "x"})
    y = b.drop("wt").withColumnsRenamed({"j": "j2", "r": "y"})
    return x.join(y, on).where("j1 < j2").select("j1", "j2", "x", "y", "wt")


def co_counts(im: DataFrame, row_cap: int | None = None) -> DataFrame:
    n = F.count(F.lit(1)) if row_cap is None else F.sum("wt").cast("long")
    return pair_rows(im, row_cap).groupBy("j1", "j2").agg(n.alias("n"))


def pair_sums(im: DataFrame, row_cap: int | None = None) -> DataFrame:
    """The six sums over common rows, in one aggregate over one join."""
    s = lambda c: F.sum(c * F.col("wt"))
    x, y = F.col("x"), F.col("y")
    return pair_rows(im, row_cap).groupBy("j1", "j2").agg(F.sum("wt").alias("n"), s(x).alias("sx"), s(y).alias("sy"), s(x * x).alias("sxx"), s(y * y).alias("syy"), s(x * y).alias("sxy"))


def pearson(im: DataFrame, row_cap: int | None = None, centre: str = "common") -> DataFrame:
    """(j1, j2, n, rho): correlation over common rows; 0 where a side does not vary.

    centre='column' takes the means over the whole columns instead of the common rows.
    """
    n, sx, sy = F.col("n"), F.col("sx"), F.col("sy")
    s = pair_sums(im, row_cap)
    if centre == "column":
        m = im.groupBy("j").agg(F.avg("r").alias("m"))
        s = s.join(m.select(F.col("j").alias("j1"), F.col("m").alias("m1")), "j1").join(m.select(F.col("j").alias("j2"), F.col("m").alias("m2")), "j2")
        m1, m2 = F.col("m1"), F.col("m2")
        cov = F.col("sxy") - m1 * sy - m2 * sx + n * m1 * m2
        vx = F.col("sxx") - 2 * m1 * sx + n * m1 * m1
        vy = F.col("syy") - 2 * m2 * sy + n * m2 * m2
    else:
        cov = n * F.col("sxy") - sx * sy
        vx = n * F.col("sxx") - sx * sx
        vy = n * F.col("syy") - sy * sy
    rho = F.when((vx > 0) & (vy > 0), cov / F.sqrt(vx * vy)).otherwise(F.lit(0.0))
    return s.select("j1", "j2", n.cast("long").alias("n"), rho.alias("rho"))


def jaccard(im: DataFrame) -> DataFrame:
    d = im.groupBy("j").agg(F.count(F.lit(1)).alias("d"))
    c = co_counts(im).join(d.select(F.col("j").alias("j1"), F.col("d").alias("d1")), "j1").join(d.select(F.col("j").alias("j2"), F.col("d").alias("d2")), "j2")
    return c.select("j1", "j2", "n", (F.col("n") / (F.col("d1") + F.col("d2") - F.col("n"))).alias("rho"))


def cosine(im: DataFrame) -> DataFrame:
    d = im.groupBy("j").agg(F.sqrt(F.sum(F.col("r") * F.col("r"))).alias("d"))
    p = pair_sums(im).join(d.select(F.col("j").alias("j1"), F.col("d").alias("d1")), "j1").join(d.select(F.col("j").alias("j2"), F.col("d").alias("d2")), "j2")
    return p.select("j1", "j2", F.col("n").cast("long").alias("n"), F.when(F.col("d1") * F.col("d2") > 0, F.col("sxy") / (F.col("d1") * F.col("d2"))).otherwise(0.0).alias("rho"))


MEASURES = {"pearson": pearson, "jaccard": jaccard, "cosine": cosine}


def similarity_graph(im: DataFrame, lam: float = LAMBDA_RHO, measure: str = "pearson", **options) -> DataFrame:
    """(j1, j2, n, rho, s), j1 < j2: similarity shrunk by n / (n + lam)."""
    e = MEASURES[measure](im, **options)
    return e.withColumn("s", F.col("n") / (F.col("n") + F.lit(float(lam))) * F.col("rho"))


def topk(edges: DataFrame, k: int, largest: bool = True) -> DataFrame:
    """(j, nbr, s, k): the k best neighbours of each column; ties by neighbour. Planned as a group limit."""
    both = edges.select(F.col("j1").alias("j"), F.col("j2").alias("nbr"), "s").union(edges.select(F.col("j2"), F.col("j1"), "s"))
    w = Window.partitionBy("j").orderBy(F.col("s").desc() if largest else F.col("s").asc(), "nbr")
    return both.withColumn("k", F.row_number().over(w)).where(F.col("k") <= k).select("j", "nbr", "s", F.col("k").cast("long").alias("k"))
