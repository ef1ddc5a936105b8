import pytest
from pyspark.sql import functions as F

from lowrank_spark import config as C
from lowrank_spark.operators import biases, neigh, params, predict, train


def _input(spark, kind):
    im = spark.createDataFrame([(i, j, float(1 + (i * 7 + j * 3) % 5)) for i in range(30) for j in range(20) if (i * j + i) % 3], "i long, j long, r double")
    top = spark.createDataFrame([(j, (j + 2 * k) % 23, k) for j in range(19) for k in range(1, 4) if (j + k) % 5], "j long, nbr long, k long")
    return im.withColumn("j", F.col("j").cast(kind)).cache(), top.withColumn("j", F.col("j").cast(kind)).withColumn("nbr", F.col("nbr").cast(kind)).cache()


@pytest.mark.parametrize("kind", ["long", "string"])
def test_lists_are_those_of_the_joined_neighbours(spark, kind):
    """The same neighbours as by joins, for the rated entries and for others, and no shuffle but that of the entries."""
    im, top = _input(spark, kind)
    means = tuple(m.cache() for m in biases.means(im))
    other = im.select("i", F.col("j").cast("long").alias("j"), "r").select("i", ((F.col("j") + 1) % 20).cast(kind).alias("j"), "r").distinct()
    for x, rated in ((im, None), (other, im)):
        mu, b, bh = means
        a = neigh.attach(x, top, rated).join(b, "i", "left").join(bh.select(F.col("j").alias("nbr"), F.col("bh").alias("bn")), "nbr", "left").crossJoin(mu).collect()
        want = {(r.i, r.j): ([], {}) for r in x.collect()}
        for r in a:
            if r.rn is None:
                want[r.i, r.j][0].append(r.k)
            else:
                want[r.i, r.j][1][r.k] = round(r.rn - r.mu - (r.b or 0) - (r.bn or 0), 9)
        got = neigh.near_lists(x, top, means, rated)
        assert got.count() == x.count()
        assert {(r.i, r.j): (r.im_k or [], {k: round(v, 9) for k, v in zip(r.ex_k or [], r.ex_x or [])}) for r in got.collect()} == {e: (sorted(n), d) for e, (n, d) in want.items()}
        assert "SortMergeJoin" not in got._jdf.queryExecution().executedPlan().toString()


def test_scores_are_those_of_the_four_part_prediction(spark):
    im, top = _input(spark, "long")
    test = im.where("(i + j) % 4 = 0")
    m = train.blend_mf(im, top, C.BLEND_PRESETS["stars"].but(F=3, K=3, epochs=2, D=2), test)
    t = predict.neighbour_terms(neigh.attach(test, m.top, m.rated), *m.means, m.weights())
    want = test.join(m.rows(), "i").join(m.cols(), "j").join(t, ["i", "j"], "left")
    want = want.select("i", "j", (F.lit(m.mu) + F.col("b") + F.col("bh") + params.dot("u", "v") + F.coalesce("ex", F.lit(0.0)) + F.coalesce("im", F.lit(0.0))).alias("p"))
    got = {(r.i, r.j): r.pred for r in train.score(m, test).collect()}
    assert got == {(r.i, r.j): pytest.approx(r.p, abs=1e-9) for r in want.collect()}
