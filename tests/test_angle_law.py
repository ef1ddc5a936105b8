from lowrank_spark.plans import experiments


def test_angle_law_takes_every_vector(spark, sf):
    """Every pair of the table's vectors is in the curve, and the curve follows the law."""
    got = experiments.x13_angle_law(spark, sf, reps=2, g=8).collect()
    m = spark.read.parquet(f"{sf}/embeddings.parquet").where("embedding is not null").select("vec_id").distinct().count()
    assert sum(r.n for r in got) == m * (m - 1) // 2 * 2 * 8
    assert all(abs(r.agree - r.law) < 0.05 for r in got if r.n > 10000)
