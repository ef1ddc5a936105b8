"""Self-joins of groups that may be large: all pairs of a group, dealt so that no task holds more than a block's."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def dealt_sides(rows: DataFrame, keys: list[str], member: str, block: int | None) -> tuple[DataFrame, DataFrame, list[str]]:
    """(a, b, join keys): joined on those keys, every pair of members of a group meets exactly once as (a, b).

    Groups of more than `block` rows are cut into blocks by a hash of the member: side a has each row in its own block,
    side b in all of them. Other groups are joined as they are. Nothing is dropped.
    """
    if block is None:
        return rows, rows, keys
    big = rows.groupBy(*keys).agg(F.count(F.lit(1)).alias("_n")).where(F.col("_n") > block)
    big = big.select(*keys, F.ceil(F.col("_n") / block).cast("int").alias("_of"))
    x = rows.join(big, keys, "left").withColumn("_of", F.coalesce("_of", F.lit(1)))
    a = x.withColumn("_blk", F.pmod(F.xxhash64(member), F.col("_of")).cast("int")).drop("_of")
    b = x.withColumn("_blk", F.explode(F.sequence(F.lit(0), F.col("_of") - 1))).drop("_of")
    return a, b, [*keys, "_blk"]
