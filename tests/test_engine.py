"""Behaviour on Spark: parity with SQL on a few queries, invariants, edges, plans."""

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from lowrank_spark import catalog
from lowrank_spark import config as C
from lowrank_spark.operators import band, baselines, biases, graph, metrics, neigh, online, signhash, train
from lowrank_spark.sources import interactions as W
from lowrank_spark.sources import prep


def rows(df):
    return sorted(map(str, (tuple(r) for r in df.collect())))


@pytest.fixture(scope="module")
def duck(sf):
    c = duckdb.connect()
    c.sql("set timezone = 'UTC'")
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        c.sql(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", ["exact_topk", "sign_codes_gathered", "band_topk_filled", "predict_blend_init", "batch_step_w", "merge_sums", "online_new_topk", "op_join_asof", "op_join_interval", "band_topk_dealt", "band_topk_of_few", "random_k", "cosine_hash_topk", "text_sign_topk", "popular_fill_topk", "degree_order", "dense_ids", "recommend_topn", "op_join_nullsafe", "op_agg_collect_sorted"])
def test_against_sql(spark, sf, duck, name):
    got = catalog.queries()[name](spark, sf)
    cols = sorted(got.columns)
    want = duck.sql(f"select {', '.join(cols)} from ({catalog.oracle_sql()[name]})").fetchall()
    assert sorted(map(str, want)) == rows(got.select(*cols))


def _im(spark, data):
    return spark.createDataFrame(data, "i long, j long, r double")


def test_gathered_equals_plain_and_order_is_free(spark, sf):
    im = W.planted_groups(spark, sf)
    cfg = C.HashConfig(p=2, q=3)
    a = signhash.codes(signhash.accumulate(im, cfg))
    b = signhash.accumulate_gathered(im.repartition(7, "r"), cfg, "codes").select("j", F.posexplode("codes").alias("rep", "code")).select("j", F.col("rep").cast("long").alias("rep"), "code")
    assert rows(a) == rows(b)


def test_scaling_leaves_codes(spark, sf):
    im, cfg = W.cust_brand(spark, sf), C.HashConfig(p=1, q=4)
    assert rows(signhash.codes(signhash.accumulate(im, cfg))) == rows(signhash.codes(signhash.accumulate(im.withColumn("r", F.col("r") * 2), cfg)))


def test_topk_is_k_distinct_others(spark, sf):
    im = W.planted_groups(spark, sf)
    for top in (band.band_search(im, C.HashConfig(p=1, q=8, K=5)), baselines.random_k(im, 5)):
        x = top.groupBy("j").agg(F.count_distinct("nbr").alias("n"), F.count_if(F.col("j") == F.col("nbr")).alias("me"))
        assert x.where("n != 5 or me > 0").count() == 0 and x.count() == im.select("j").distinct().count()


def test_more_groups_more_pairs(spark, sf):
    im = W.planted_groups(spark, sf)
    n = lambda p, q: band.pairs(band.keys(signhash.code_table(im, C.HashConfig(p=p, q=q)), p)).count()
    assert n(1, 8) > n(1, 4) > 0 and n(2, 4) < n(1, 8)


def test_neighbour_sets_are_disjoint_and_whole(spark, sf):
    im = W.planted_groups(spark, sf)
    top = graph.topk(graph.similarity_graph(im), 4)
    c = neigh.counts(neigh.attach(im, top)).withColumn("n", F.col("n_explicit") + F.col("n_implicit"))
    k = top.groupBy("j").agg(F.count(F.lit(1)).alias("k"))
    assert c.join(k, "j").where("n != k").count() == 0


def test_purity_above_chance(spark, sf):
    im = W.planted_groups(spark, sf)
    p = metrics.group_purity(band.band_search(im, C.HashConfig(p=1, q=60, K=16), fill="none"), lambda c: c % 5).first()["purity"]
    assert p > 0.4


def test_training_beats_means_and_online_keeps_old(spark, sf):
    im = W.planted_groups(spark, sf).select("i", "j", "r")
    tr, te = prep.split(im)
    means = metrics.rmse(biases.score(te, *biases.means(tr)))
    cfg = C.BLEND_PRESETS["stars"].but(F=8, K=4, epochs=3, D=2)
    top = graph.topk(graph.similarity_graph(tr), 4)
    m = train.blend_mf(tr, top, cfg, te)
    assert m.history[-1]["rmse"] < means and m.history[-1]["rmse"] < m.history[0]["rmse"]
    old, new = prep.online_split(tr, 0.05, 0.05)
    base = train.blend_mf(old, top, cfg.but(epochs=1))
    up = online.online_update(base, new)
    before = {(r.side, r.id): r for r in base.state.collect()}
    after = {(r.side, r.id): r for r in up.state.collect()}
    assert all(after[k] == before[k] for k in before) and len(after) > len(before)


def test_edges(spark):
    empty = _im(spark, [])
    assert band.band_search(empty, C.HashConfig(p=1, q=2, K=3)).count() == 0
    one = _im(spark, [(1, 1, 3.0)])
    assert graph.similarity_graph(one).count() == 0 and band.band_search(one, C.HashConfig(p=1, q=2, K=3)).count() == 0
    flat = _im(spark, [(i, j, 2.0) for i in range(4) for j in range(3)])
    assert {r["rho"] for r in graph.pearson(flat).collect()} == {0.0}
    assert band.band_search(flat, C.HashConfig(p=1, q=2, K=9)).groupBy("j").count().where("count != 2").count() == 0
    dirty = spark.createDataFrame([(1, 1, 1.0), (1, 1, 3.0), (None, 1, 1.0), (1, 2, float("nan"))], "i long, j long, r double")
    assert [tuple(r) for r in prep.validate_interactions(dirty, "mean").collect()] == [(1, 1, 2.0)]
    assert tuple(prep.rejected(dirty).first()) == (4, 2, 1)
    m = biases.means(one)
    assert biases.score(_im(spark, [(9, 9, 1.0)]), *m).first()["pred"] == 3.0


def test_plans(spark, sf):
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    p = plan(graph.topk(graph.similarity_graph(W.cust_brand(spark, sf)), 4))
    assert "WindowGroupLimit" in p and "CartesianProduct" not in p
    p = plan(catalog.queries()["op_filter_pushdown"](spark, sf))
    assert "PushedFilters: [IsNotNull" in p and "l_comment" not in p


def test_every_query_has_a_form():
    assert set(catalog.oracle_sql()) <= set(catalog.queries()) and len(catalog.queries()) >= 150
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_large_groups_are_dealt_without_loss(spark, sf, monkeypatch):
    im = W.planted_groups(spark, sf)
    want = rows(graph.co_counts(im))
    monkeypatch.setattr(graph, "ROW_BLOCK", 7)
    assert rows(graph.co_counts(im)) == want
    keys = spark.createDataFrame([(0, 5, j) for j in range(60)], "grp long, key long, j long")
    assert band.pairs(keys, 8).count() == band.pairs(keys).count() == 60 * 59 // 2


def test_fill_reaches_k_in_small_universes(spark):
    for n, k in ((33, 32), (40, 32), (12, 8), (5, 9), (2, 1)):
        top = baselines.random_k(_im(spark, [(1, j, 1.0) for j in range(n)]), k)
        x = top.groupBy("j").agg(F.count_distinct("nbr").alias("n"), F.count(F.lit(1)).alias("m"), F.max("k").alias("k"))
        assert {tuple(r) for r in x.select("n", "m", "k").collect()} == {(min(k, n - 1),) * 3} and x.count() == n


def test_new_rows_meet_trained_columns_only(spark, monkeypatch):
    old = _im(spark, [(i, j, 3.0) for i in range(4) for j in range(4)])
    new = _im(spark, [(9, 1, 4.0), (9, 77, 5.0), (2, 77, 1.0)])
    m = train.factor_bias_sgd(old, C.BLEND_PRESETS["stars"].but(F=2, epochs=1, D=1))
    seen, fit = [], train.fit
    monkeypatch.setattr(train, "fit", lambda e, *a, **k: (seen.append(sorted((r.i, r.j) for r in e.collect())), fit(e, *a, **k))[1])
    online.online_update(m, new)
    assert seen == [[("9", "1")], [("2", "77"), ("9", "77")]]
