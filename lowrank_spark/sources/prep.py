"""Preparation of an interaction matrix: checks, ids, cleaning, splits, negatives, noise, order."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from lowrank_spark.functions.hashing import md5_byte, md5_int, text


def validate_interactions(df: DataFrame, agg: str = "max") -> DataFrame:
    """Drops rows with a null or NaN in i, j or r; joins duplicates of (i, j) by max, mean, sum or last (needs ts)."""
    ok = df.where(F.col("i").isNotNull() & F.col("j").isNotNull() & F.col("r").isNotNull() & ~F.isnan("r"))
    how = {"max": F.max("r"), "mean": F.avg("r"), "sum": F.sum("r")}
    r = F.max_by("r", "ts") if agg == "last" else how[agg]
    return ok.groupBy("i", "j").agg(r.cast("double").alias("r"))


def rejected(df: DataFrame) -> DataFrame:
    """One row: rows, rows dropped by validate_interactions, duplicates of (i, j)."""
    bad = F.col("i").isNull() | F.col("j").isNull() | F.col("r").isNull() | F.isnan("r")
    d = df.groupBy("i", "j").agg(F.count(F.lit(1)).alias("n"), F.count_if(bad).alias("bad"))
    return d.agg(F.sum("n").alias("n_rows"), F.sum("bad").alias("n_bad"), F.coalesce(F.sum(F.when(F.col("bad") == 0, F.col("n") - 1)), F.lit(0)).alias("n_dup"))


def numbered(df: DataFrame, order: list, name: str, partitions: int | None = None) -> DataFrame:
    """df + name: places from 0 on in the given order, which must be total, without a global window.

    Rows are range-partitioned; a partition's offset is the count before it (one number a partition goes through
    the driver), and places run inside partitions.
    """
    from lowrank_spark.runtime import Scratch

    spark = df.sparkSession
    n = partitions or int(spark.conf.get("spark.sql.shuffle.partitions"))
    kept = Scratch(spark, "places").keep(df.repartitionByRange(n, *order).withColumn("_p", F.spark_partition_id()))
    sizes = sorted((r["_p"], r["n"]) for r in kept.groupBy("_p").agg(F.count(F.lit(1)).alias("n")).collect())
    offsets, at = [], 0
    for p, k in sizes:
        offsets.append((p, at))
        at += k
    off = spark.createDataFrame(offsets or [(0, 0)], "_p int, _off long")
    rn = F.row_number().over(Window.partitionBy("_p").orderBy(*order))
    return kept.join(F.broadcast(off), "_p").withColumn(name, F.col("_off") + rn - 1).drop("_p", "_off")


def index_ids(df: DataFrame, col: str, partitions: int | None = None) -> DataFrame:
    """(col, id): dense ids in the column's order."""
    return numbered(df.select(col).where(F.col(col).isNotNull()).distinct(), [F.col(col)], "id", partitions).select(col, "id")


def lift_zeros(df: DataFrame, to: float = 0.5) -> DataFrame:
    return df.withColumn("r", F.when(F.col("r") == 0, F.lit(to)).otherwise(F.col("r")))


def rescale(df: DataFrame, by: float = 20.0) -> DataFrame:
    return df.withColumn("r", F.col("r") / by)


def in_test(pct_byte: int = 26, i: str = "i", j: str = "j"):
    """The test predicate: about pct_byte / 256 of the entries, by their own hash."""
    return md5_byte(text("split", F.col(i), F.col(j))) < pct_byte


def split(df: DataFrame, pct_byte: int = 26) -> tuple[DataFrame, DataFrame]:
    return df.where(~in_test(pct_byte)), df.where(in_test(pct_byte))


def leave_one_out(df: DataFrame, order=None) -> DataFrame:
    """df + held: true for one entry of each row, the largest by `order` (default: a hash of the entry)."""
    key = order if order is not None else F.md5(text("loo", F.col("i"), F.col("j")))
    top = df.groupBy("i").agg(F.max_by("j", F.struct(key.alias("k"), F.col("j").alias("t"))).alias("_j"))
    return df.join(top, "i").withColumn("held", F.col("j") == F.col("_j")).drop("_j")


def negatives(rows: DataFrame, seen: DataFrame, n_columns: int, n: int = 99) -> DataFrame:
    """(i, j): up to n hashed candidate columns of [0, n_columns) for each row, less what the row has."""
    t = F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("t")
    c = rows.select("i", t).select("i", (md5_int(text("neg", F.col("i"), F.col("t")), 14) % n_columns).alias("j")).distinct()
    return c.join(seen.select("i", "j"), ["i", "j"], "left_anti")


def inject_noise(df: DataFrame, rate: float, kind: str = "uniform") -> DataFrame:
    """A share `rate` of the entries, chosen by hash, gets another value: uniform in 1..5, or one step up or down."""
    hit = md5_int(text("noise", F.col("i"), F.col("j")), 8) < int(rate * 4294967296)
    x = md5_byte(text("nv", F.col("i"), F.col("j")))
    new = 1 + x % 5 if kind == "uniform" else F.greatest(F.lit(1), F.least(F.lit(5), F.col("r") + F.when(x % 2 == 0, 1).otherwise(-1)))
    return df.withColumn("r", F.when(hit, new.cast("double")).otherwise(F.col("r")))


def is_new(axis: str, rate: float = 0.01):
    return md5_int(text(f"new{axis}", F.col(axis)), 8) < int(rate * 4294967296)


def online_split(df: DataFrame, fi: float = 0.01, fj: float = 0.01) -> tuple[DataFrame, DataFrame]:
    """(original, new): entries that touch a new row or a new column are new."""
    new = is_new("i", fi) | is_new("j", fj)
    return df.where(~new), df.where(new)


def degree_order(df: DataFrame, axis: str = "i", blocks: int = 4) -> DataFrame:
    """(axis, degree, place, block): ids by falling degree, dealt to blocks in turn, back and forth.

    Ids are range-partitioned by degree, so no task sees all of them.
    """
    deg = df.groupBy(axis).agg(F.count(F.lit(1)).alias("degree"))
    d = numbered(deg, [F.col("degree").desc(), F.col(axis)], "place")
    k, lap = F.col("place") % blocks, F.floor(F.col("place") / blocks) % 2
    return d.select(axis, "degree", "place", F.when(lap == 0, k).otherwise(blocks - 1 - k).cast("long").alias("block"))


def profile(df: DataFrame) -> DataFrame:
    """One row: M, N, entries, largest and smallest value."""
    return df.agg(F.count_distinct("i").alias("m"), F.count_distinct("j").alias("n"), F.count(F.lit(1)).alias("entries"), F.max("r").alias("max_r"), F.min("r").alias("min_r"))
