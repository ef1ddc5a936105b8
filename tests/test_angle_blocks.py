import random

import pytest
from pyspark.sql import functions as F

from lowrank_spark.operators import angles, baselines, graph, signhash
from lowrank_spark.plans import experiments


def test_blocks_equal_the_pairs(spark, monkeypatch):
    """Blocks of three columns give what the join of all pairs gives: vectors of two lengths, of zeros, with a null, equal ones."""
    rng = random.Random(5)
    vec = {j: [rng.gauss(0, 1) for _ in range(6 if j % 4 else 3)] for j in range(20)} | {50: [0.0] * 6, 51: [1.0, None, 2.0], 52: [1.0, 2.0], 53: [2.0, 4.0]}
    im = spark.createDataFrame([(i, j, r) for j, v in vec.items() for i, r in enumerate(v)], "i long, j long, r double").cache()
    codes = signhash.codes(baselines.cosine_sums(im, 2, 8), 8).cache()
    drawn_once = signhash.codes(baselines.cosine_sums(im, 2, 8, rows=im.select("i").distinct()), 8)
    assert sorted(map(tuple, drawn_once.collect())) == sorted(map(tuple, codes.collect()))
    e = graph.cosine(im).withColumn("turn", F.acos(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), "rho"))) / 3.141592653589793)
    j = e.join(codes.select(F.col("j").alias("j1"), "rep", F.col("code").alias("c1")), "j1").join(codes.select(F.col("j").alias("j2"), "rep", F.col("code").alias("c2")), ["j2", "rep"])
    j = j.groupBy(F.round("turn", 1).alias("bin")).agg((F.count("*") / 2).cast("long").alias("pairs"), F.sum(F.bit_count(F.expr("c1 ^ c2"))).alias("differ"), (F.sum("turn") / 2).alias("turn"))
    want = sorted(map(tuple, j.collect()))
    monkeypatch.setattr(angles, "BLOCK", 3)
    got = sorted(map(tuple, angles.by_angle(im, codes).collect()))
    assert [g[:3] for g in got] == [w[:3] for w in want]
    assert all(abs(g[3] - w[3]) < 1e-9 for g, w in zip(got, want, strict=True))


def test_angle_law_forms_no_pairs(spark, sf, monkeypatch):
    """The curve of all vectors needs no join of their entries, which has a row for every pair and dimension."""
    monkeypatch.setattr(graph, "pair_rows", lambda *a: pytest.fail("pairs of a row"))
    assert sum(r.n for r in experiments.x13_angle_law(spark, sf, reps=1, g=8).collect()) > 0
