"""The other ways to pick K neighbours: random, cosine hashing, min-hashing, and the library's hashes for cross-checks."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lowrank_spark.config import HashConfig
from lowrank_spark.functions.hashing import md5_int, text, uniform
from lowrank_spark.operators import band, signhash
from lowrank_spark.runtime import Scratch, maybe_broadcast


def random_k(columns: DataFrame, k: int, seed: int = 7) -> DataFrame:
    """(j, nbr, freq, k) with hashed random neighbours only."""
    empty = columns.select("j").distinct().withColumn("nbr", F.col("j")).withColumn("freq", F.lit(0).cast("long")).withColumn("k", F.lit(0).cast("long")).where("false")
    return band.fill_random(empty, band.universe_of(columns), k, seed)


def gaussian(seed: int, i, lane):
    """Normal deviate of (seed, i, lane) from two hashed uniforms."""
    u = F.greatest(uniform(text(seed, "g1", i, lane)), F.lit(2.0**-33))
    v = uniform(text(seed, "g2", i, lane))
    return F.sqrt(-2 * F.log(u)) * F.cos(F.lit(2 * math.pi) * v)


def cosine_sums(im: DataFrame, reps: int, g: int, seed: int = 7, kind: str = "gaussian", rows: DataFrame | None = None) -> DataFrame:
    """(j, rep, s0..): projections on hashed Gaussian (or +-1) directions, value unweighted.

    rows: the distinct i, where they are few; their directions are then drawn once, not for every entry.
    """
    if kind == "rademacher":
        return signhash.accumulate(im, HashConfig(G=g, p=1, q=reps, psi="identity", seed=seed))
    if rows is not None:
        drawn = rows.select("i", F.explode(F.sequence(F.lit(0), F.lit(reps - 1))).alias("rep"))
        drawn = drawn.select("i", "rep", *[gaussian(seed, F.col("i"), F.col("rep") * g + k).alias(f"d{k}") for k in range(g)])
        drawn = Scratch(im.sparkSession, "directions").keep(drawn)
        x = im.select("i", "j", "r").join(maybe_broadcast(drawn, drawn.count(), 24 + 8 * g), "i")
        return x.groupBy("j", F.col("rep").cast("long").alias("rep")).agg(*[F.sum(F.col("r") * F.col(f"d{k}")).alias(f"s{k}") for k in range(g)])
    x = im.select("i", "j", "r", F.explode(F.sequence(F.lit(0), F.lit(reps - 1))).alias("rep"))
    lanes = [F.sum(F.col("r") * gaussian(seed, F.col("i"), F.col("rep") * g + k)).alias(f"s{k}") for k in range(g)]
    return x.groupBy("j", F.col("rep").cast("long").alias("rep")).agg(*lanes)


def cosine_hash(im: DataFrame, cfg: HashConfig, kind: str = "gaussian") -> DataFrame:
    rows = signhash.codes(cosine_sums(im, cfg.reps, cfg.G, cfg.seed, kind), cfg.G)
    return band.fill_random(band.search_codes(rows, cfg), band.universe_of(im), cfg.K, cfg.seed)


def min_signatures(im: DataFrame, reps: int, seed: int = 7) -> DataFrame:
    """(j, rep, code): the smallest hash of a column's rows, per repetition; values of r play no part."""
    x = im.select("i", "j", F.explode(F.sequence(F.lit(0), F.lit(reps - 1))).alias("rep"))
    return x.groupBy("j", F.col("rep").cast("long").alias("rep")).agg(F.min(md5_int(text(seed, F.col("rep"), F.col("i")), 15)).alias("code"))


def min_hash(im: DataFrame, cfg: HashConfig, fill: bool = True) -> DataFrame:
    rows = min_signatures(im, cfg.reps, cfg.seed)
    top = band.topk_of_keys(Scratch(im.sparkSession, "band").keep(band.keys(rows, cfg.p, 60)), cfg.K, cfg.q, cfg.max_bucket)
    return band.fill_random(top, band.universe_of(im), cfg.K, cfg.seed) if fill else top


def text_sign_hash(im: DataFrame, cfg: HashConfig) -> DataFrame:
    """The unweighted form for presence data: psi = 1."""
    from dataclasses import replace

    return band.band_search(im, replace(cfg, psi="ones"))


def library_min_hash(sets: DataFrame, tables: int = 4, seed: int = 7):
    """The library's MinHashLSH over (id, features) sparse vectors, fitted: a cross-check."""
    from pyspark.ml.feature import MinHashLSH

    return MinHashLSH(inputCol="features", outputCol="hashes", numHashTables=tables, seed=seed).fit(sets)


def library_projection(vectors: DataFrame, width: float = 2.0, tables: int = 4, seed: int = 7):
    from pyspark.ml.feature import BucketedRandomProjectionLSH

    return BucketedRandomProjectionLSH(inputCol="features", outputCol="hashes", bucketLength=width, numHashTables=tables, seed=seed).fit(vectors)
