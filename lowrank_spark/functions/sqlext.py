"""User functions: Arrow scalar and grouped functions, a table function, and SQL functions of hashing and schedules."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F


def norm_udf():
    """Squared length of a vector, by Arrow batches."""

    @F.pandas_udf("double")
    def squared_norm(v: pd.Series) -> pd.Series:
        return v.map(lambda x: float(sum(float(a) * float(a) for a in x)) if x is not None else None)

    return squared_norm


def rmse_udaf():
    """Root mean squared difference of a group."""

    @F.pandas_udf("double")
    def rmse(x: pd.Series, y: pd.Series) -> float:
        return float((((x - y) ** 2).mean()) ** 0.5)

    return rmse


class BandKeys:
    """Rows (grp, key) of an array of keys."""

    def eval(self, keys):
        for g, k in enumerate(keys or []):
            yield g, k


def register(spark: SparkSession) -> None:
    spark.udtf.register("band_keys", F.udtf(BandKeys, returnType="grp int, key bigint"))
    register_sql(spark)


SQL_FUNCTIONS = {
    "step_size": ("alpha double, beta double, t double", "double", "alpha / (1 + beta * pow(t, 1.5D))"),
    "collision_prob": ("prob double, p int, q int", "double", "1 - pow(1 - pow(prob, p), q)"),
    "hamming": ("a bigint, b bigint", "int", "bit_count(a ^ b)"),
    "row_sign": ("seed int, i string, t int", "int", "2 * getbit(cast(conv(substr(md5(concat_ws(':', seed, i, t div 128)), 2 * ((t div 8) % 16) + 1, 2), 16, 10) as int), t % 8) - 1"),
    "sign_code": ("sums array<double>", "bigint", "aggregate(transform(sums, (s, k) -> if(s >= 0, shiftleft(1L, k), 0L)), 0L, (a, x) -> a | x)"),
}


def register_sql(spark: SparkSession) -> None:
    for name, (args, out, body) in SQL_FUNCTIONS.items():
        spark.sql(f"create or replace temporary function {name}({args}) returns {out} return {body}")
