"""Explicit and implicit neighbours of an entry: which of a column's K neighbours the row has rated."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from lowrank_spark.runtime import maybe_broadcast

#: Entries of a partition in which neighbours are looked up; there is one row a neighbour there.
ENTRIES_A_PART = 50_000


def attach(im: DataFrame, top: DataFrame, rated: DataFrame | None = None, implicit: DataFrame | None = None) -> DataFrame:
    """(i, j, r, k, nbr, rn, kind) for every entry and neighbour of its column; rn is the row's value there.

    kind is 'explicit' where the row has rated the neighbour, else 'implicit'; with `implicit` given, a table (i, j) of
    implicit relations, only neighbours in it are implicit and a neighbour can be both.
    """
    known = (im if rated is None else rated).select("i", F.col("j").alias("nbr"), F.col("r").alias("rn"))
    x = im.select("i", "j", "r").join(top.select("j", "nbr", "k"), "j").join(known, ["i", "nbr"], "left")
    if implicit is None:
        return x.withColumn("kind", F.when(F.col("rn").isNotNull(), "explicit").otherwise("implicit")).select("i", "j", "r", "k", "nbr", "rn", "kind")
    rel = implicit.select("i", F.col("j").alias("nbr")).distinct().withColumn("_n", F.lit(True))
    x = x.join(rel, ["i", "nbr"], "left")
    ex = x.where(F.col("rn").isNotNull()).withColumn("kind", F.lit("explicit"))
    im2 = x.where("_n").withColumn("kind", F.lit("implicit"))
    return ex.union(im2).select("i", "j", "r", "k", "nbr", "rn", "kind")


def near_lists(entries: DataFrame, top: DataFrame, means: tuple, rated: DataFrame | None = None) -> DataFrame:
    """(i, j, r, ex_k, ex_x, im_k): of every entry, the places and residuals at the means of the neighbours its row has
    rated, and the places of the others; null where its column has no neighbours.

    Entries and what is rated (the entries, if not given) are dealt by row once. An entry's neighbours become rows in its
    partition only, where a window over row and column tells which are rated: no row a neighbour is shuffled.
    """
    mu, b, bh = means
    one = top.select("j", F.col("nbr"), F.col("k").cast("int").alias("k")).join(bh.select(F.col("j").alias("nbr"), F.col("bh").alias("bn")), "nbr", "left")
    tops = one.groupBy("j").agg(F.collect_list(F.struct("nbr", "k", F.coalesce("bn", F.lit(0.0)).alias("bn"))).alias("near"))
    x = entries.select("i", "j", "r", F.lit(True).alias("asked"), F.lit(rated is None).alias("known"))
    if rated is not None:
        x = x.union(rated.select("i", "j", "r", F.lit(False), F.lit(True)))
    parts = max(1, -(-x.count() // ENTRIES_A_PART))
    x = x.repartition(parts, "i").join(maybe_broadcast(tops, bh.count(), 64 + 32 * (top.agg(F.max("k")).first()[0] or 0)), "j", "left")
    kinds = "array<struct<at:{0},k:int,bn:double,rn:double>>".format(x.schema["j"].dataType.simpleString())
    own = F.when(F.col("known"), F.array(F.struct(F.col("j").alias("at"), F.lit(0).alias("k"), F.lit(0.0).alias("bn"), F.col("r").cast("double").alias("rn"))).cast(kinds))
    theirs = F.when(F.col("asked"), F.transform(F.coalesce("near", F.array().cast(tops.schema["near"].dataType)), lambda n: F.struct(n["nbr"].alias("at"), n["k"].alias("k"), n["bn"].alias("bn"), F.lit(None).cast("double").alias("rn"))).cast(kinds))
    none = F.array().cast(kinds)
    # an entry without neighbours of its own keeps one row without a place
    mark = F.when(F.col("asked"), F.array(F.struct(F.col("j").alias("at"), F.lit(-1).alias("k"), F.lit(0.0).alias("bn"), F.lit(None).cast("double").alias("rn"))).cast(kinds))
    x = x.select("i", "j", "r", F.inline(F.concat(F.coalesce(own, none), F.coalesce(mark, none), F.coalesce(theirs, none))))
    x = x.withColumn("rn", F.max("rn").over(Window.partitionBy("i", "at"))).where("k <> 0")
    x = x.join(F.broadcast(mu)).join(maybe_broadcast(b, b.count(), 32), "i", "left")
    res = F.col("rn") - (F.col("mu") + F.coalesce("b", F.lit(0.0)) + F.col("bn"))
    near, ex = F.col("k") > 0, F.col("rn").isNotNull()
    lists = x.groupBy("i", "j").agg(
        F.collect_list(F.when(~near, F.col("r"))).alias("rs"),
        F.array_sort(F.collect_set(F.when(near & ex, F.struct("k", res.alias("x"))))).alias("ex"),
        F.array_sort(F.collect_set(F.when(near & ~ex, F.col("k")))).alias("im_k"),
    )
    some = (F.size("ex") > 0) | (F.size("im_k") > 0)
    return lists.select("i", "j", F.explode("rs").alias("r"), F.when(some, F.transform("ex", lambda s: s["k"])).alias("ex_k"), F.when(some, F.transform("ex", lambda s: s["x"])).alias("ex_x"), F.when(some, F.col("im_k")).alias("im_k"))


def attach_arrays(im: DataFrame, top: DataFrame) -> DataFrame:
    """(i, j, r, ex, ims): arrays of (k, nbr, rn) and of (k, nbr), for the training kernels."""
    x = attach(im, top)
    ex = F.collect_list(F.when(F.col("kind") == "explicit", F.struct("k", "nbr", "rn")))
    ims = F.collect_list(F.when(F.col("kind") == "implicit", F.struct("k", "nbr")))
    a = x.groupBy("i", "j").agg(F.array_sort(ex).alias("ex"), F.array_sort(ims).alias("ims"))
    return im.select("i", "j", "r").join(a, ["i", "j"], "left")


def counts(attached: DataFrame) -> DataFrame:
    """(i, j, n_explicit, n_implicit)."""
    return attached.groupBy("i", "j").agg(F.count_if(F.col("kind") == "explicit").alias("n_explicit"), F.count_if(F.col("kind") == "implicit").alias("n_implicit"))
