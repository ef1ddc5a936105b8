"""The published comparisons on the stand-in workloads. Each returns a small table; `python -m lowrank_spark.plans.experiments`
runs them all and prints it. Defaults are reduced grids; the published ones are parameters."""

from __future__ import annotations

import sys
import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lowrank_spark import config as C
from lowrank_spark.operators import angles, band, baselines, cost, graph, loss, metrics, neural, online, signhash, theory, train
from lowrank_spark.runtime import Scratch
from lowrank_spark.sources import interactions as W
from lowrank_spark.sources import prep


def _table(s: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return s.createDataFrame(rows, schema)


def _data(s, d, workload="planted_groups"):
    sc = Scratch(s, "x")
    tr, te = prep.split(W.load_interactions(s, d, workload).select("i", "j", "r"))
    return sc.keep(tr), sc.keep(te)


def _last(model) -> tuple[float, float]:
    h = model.history[-1]
    return round(h["rmse"], 6), round(h["seconds"], 3)


def _factor(f=8, epochs=4, d=2, **k):
    return C.FACTOR_PRESETS["stars"].but(F=f, epochs=epochs, D=d, **k)


def _blend(f=8, k=8, epochs=4, d=2, **m):
    return C.BLEND_PRESETS["stars"].but(F=f, K=k, epochs=epochs, D=d, **m)


def _searches(tr, k, q=50):
    return {
        "random": lambda: baselines.random_k(tr, k),
        "exact": lambda: graph.topk(graph.similarity_graph(tr), k),
        "sign": lambda: band.band_search(tr, C.HashConfig(p=1, q=q, K=k)),
        "sign_twice": lambda: band.band_search(tr, C.HashConfig(p=1, q=2 * q, K=k)),
        "cosine": lambda: baselines.cosine_hash(tr, C.HashConfig(G=4, p=1, q=min(q, 8), K=k)),
        "min": lambda: baselines.min_hash(tr, C.HashConfig(p=1, q=min(q, 20), K=k)),
    }


def x1_solvers(s, d, epochs=4, f=8):
    """Error and seconds of ALS, entry-parallel and row-resident descent after equal passes."""
    tr, te = _data(s, d)
    h = train.als(tr, f, 0.1, epochs, test=te)[2][-1]
    rows = [("als", round(h["rmse"], 6), round(h["seconds"], 3)), ("entry", *_last(train.entry_sgd(tr, _factor(f, epochs), test=te))), ("resident", *_last(train.resident_sgd(tr, _factor(f, epochs), test=te)))]
    return _table(s, rows, "solver string, rmse double, seconds double")


def x2_order(s, d):
    """Row order by degree against hashed order."""
    tr, te = _data(s, d)
    return _table(s, [(o, *_last(train.resident_sgd(tr, _factor(order=o), test=te))) for o in ("degree", "hashed")], "row_order string, rmse double, seconds double")


def x3_serial_and_parallel(s, d):
    """Blended model: serial with the exact graph, serial with hashed neighbours, parallel with hashed neighbours."""
    tr, te = _data(s, d)
    rows = []
    for name, how, blocks in (("serial_exact", "exact", 1), ("serial_hashed", "sign", 1), ("parallel_hashed", "sign", 4)):
        t = time.perf_counter()
        top = Scratch(s, "x3").keep(_searches(tr, 8)[how]())
        search = time.perf_counter() - t
        rows.append((name, round(search, 3), *_last(train.blend_mf(tr, top, _blend(d=blocks), te))))
    return _table(s, rows, "variant string, search_seconds double, rmse double, train_seconds double")


def x4_searches(s, d, k=8):
    """Top-K methods: error, purity of the planted groups, seconds and published space."""
    tr, te = _data(s, d)
    n = tr.select("j").distinct().count()
    rows = []
    for name, search in _searches(tr, k).items():
        t = time.perf_counter()
        top = Scratch(s, "x4").keep(search())
        sec = time.perf_counter() - t
        pure = metrics.group_purity(top, lambda c: c % 5).first()["purity"]
        size = cost.space_bytes("random" if name == "random" else "graph" if name == "exact" else "hash", n, 1, 100 if name == "sign_twice" else 50)
        rows.append((name, _last(train.blend_mf(tr, top, _blend(k=k, epochs=3), te))[0], round(pure, 4), round(sec, 3), size))
    return _table(s, rows, "method string, rmse double, purity double, seconds double, bytes long")


def x5_pq(s, d, ps=(1, 2, 3), qs=(10, 20, 40), k=8):
    """Candidates, recall of the exact neighbours and purity by p and q, beside the theory at agreement 0.9."""
    im = W.planted_groups(s, d)
    exact = Scratch(s, "x5").keep(graph.topk(graph.similarity_graph(im), k))
    rows = []
    for p in ps:
        for q in qs:
            scratch = Scratch(s, "x5")
            keys = scratch.keep(band.keys(signhash.code_table(im, C.HashConfig(p=p, q=q)), p))
            pairs = scratch.keep(band.pairs(keys))
            top = band.topk(pairs, k)
            rec = metrics.topk_recall(top, exact).first()["recall"]
            pure = metrics.group_purity(top, lambda c: c % 5).first()["purity"]
            rows.append((p, q, pairs.count(), round(rec, 4), round(pure, 4) if pure is not None else None, round(theory.pair_probability(0.9, p, q), 6)))
            scratch.drop(pairs)
            scratch.drop(keys)
    return _table(s, rows, "p int, q int, pairs long, recall double, purity double, theory double")


def x6_fk(s, d, fs=(4, 8), ks=(4, 8)):
    tr, te = _data(s, d)
    top = Scratch(s, "x6").keep(band.band_search(tr, C.HashConfig(p=1, q=50, K=max(ks))))
    rows = [(f, k, *_last(train.blend_mf(tr, top, _blend(f, k, 3), te)), cost.model_cells(tr.count(), 0, 0, f, k)) for f in fs for k in ks]
    return _table(s, rows, "f int, k int, rmse double, seconds double, entries long").drop("entries")


def x7_blend_or_factor(s, d, fs=(4, 8), k=8):
    """Blended against factor-only and bias-plus-factor, by epoch."""
    tr, te = _data(s, d)
    top = Scratch(s, "x7").keep(band.band_search(tr, C.HashConfig(p=1, q=50, K=k)))
    rows = []
    for f in fs:
        for name, m in (("blend", train.blend_mf(tr, top, _blend(f, k, 3), te)), ("bias_factor", train.factor_bias_sgd(tr, _blend(f, k, 3), te)), ("factor", train.resident_sgd(tr, _factor(f, 3), test=te))):
            rows += [(name, f, h["epoch"], round(h["rmse"], 6), round(h["seconds"], 3)) for h in m.history]
    return _table(s, rows, "model string, f int, epoch int, rmse double, seconds double")


def x8_noise(s, d, rates=(0.01, 0.001), kind="uniform"):
    """Deviation of the error under noise, factor-only and blended."""
    tr, te = _data(s, d)
    top = Scratch(s, "x8").keep(band.band_search(tr, C.HashConfig(p=1, q=50, K=8)))
    fits = {"factor": lambda x: _last(train.resident_sgd(x, _factor(epochs=3), test=te))[0], "blend": lambda x: _last(train.blend_mf(x, top, _blend(epochs=3), te))[0]}
    clean = {n: f(tr) for n, f in fits.items()}
    rows = [(n, r, round(metrics.noise_gap(clean[n], f(prep.inject_noise(tr, r, kind))), 6)) for r in rates for n, f in fits.items()]
    return _table(s, rows, "model string, rate double, gap double")


def x9_online(s, d, share=0.05):
    """Error of an updated model against training on everything, on the test entries of new ids."""
    tr, te = _data(s, d)
    old, new = prep.online_split(tr, share, share)
    full = train.factor_bias_sgd(tr, _blend(epochs=3))
    up = online.online_update(train.factor_bias_sgd(old, _blend(epochs=3)), new)
    rows = [("full", round(metrics.rmse(train.score(full, te)), 6)), ("online", round(metrics.rmse(train.score(up, te)), 6))]
    return _table(s, rows, "model string, rmse double")


def x10_workers(s, d, ds=(1, 2, 4)):
    tr, te = _data(s, d)
    return _table(s, [(w, *_last(train.rotation(tr, _factor(epochs=2), w, test=te))) for w in ds], "workers int, rmse double, seconds double")


def x11_hit_ratio(s, d, epochs=3):
    """Hit ratio at 10 of the blended model under log-loss and of the neural baselines."""
    im = W.user_key(s, d).select("i", "j", "r")
    loo = Scratch(s, "x11").keep(prep.leave_one_out(im))
    held, pos = loo.where("held"), loo.where("not held").drop("held")
    neg = prep.negatives(held.select("i"), im, 100, 60)
    cand = Scratch(s, "x11").keep(held.select("i", "j", F.lit(1).alias("y")).union(neg.select("i", "j", F.lit(0).alias("y"))))
    ex = Scratch(s, "x11").keep(neural.examples(pos, 3))
    rows = []
    t = time.perf_counter()
    top = band.band_search(pos.withColumn("r", F.lit(1.0)), C.HashConfig(p=1, q=50, K=8, psi="ones"))
    m = train._train(ex.select("i", "j", F.col("y").cast("double").alias("r")), _blend(epochs=epochs, loss="logistic").but(side="col", alpha=C.Rates(0.1, 0.1, 0.1, 0.1, 0.01, 0.01)), top, None)
    score = train.score(m, cand.select("i", "j", F.col("y").cast("double").alias("r"))).select("i", "j", F.col("r").cast("int").alias("y"), loss.sigmoid(F.col("pred")).alias("score"))
    rows.append(("blend", round(metrics.hit_ratio(score).first()["hr"], 4), round(time.perf_counter() - t, 3), cost.model_params("blend", 1, 1, 8, 8)))
    for kind in ("product", "mlp", "fused"):
        t = time.perf_counter()
        net = neural.train(ex, neural.NetConfig(kind=kind, epochs=epochs, D=2))
        hr = metrics.hit_ratio(neural.score(net, cand)).first()["hr"]
        rows.append((f"net_{kind}", round(hr, 4), round(time.perf_counter() - t, 3), cost.model_params(f"net_{kind}", 1, 1, 8, 8, (16, 8))))
    return _table(s, rows, "model string, hr double, seconds double, params_per_id long")


def x12_rescaled(s, d):
    """The 0.5 to 100 scale: trained on values divided by 20, error on the original scale."""
    tr, te = _data(s, d, "discount")
    tr, te = prep.rescale(prep.lift_zeros(tr), 20), prep.rescale(prep.lift_zeros(te), 20)
    m = train.factor_bias_sgd(tr, C.BLEND_PRESETS["hundred"].but(F=4, epochs=2, D=2))
    return metrics.errors(train.score(m, te), 20.0)


def x13_angle_law(s, d, reps=16, g=8):
    """Cosine hashing of vectors: agreement of bits by angle against 1 - angle / pi."""
    im = Scratch(s, "x13").keep(W.dim_vec(s, d))
    x = baselines.cosine_sums(im, reps, g, rows=im.select("i").distinct())
    a = x.select("j", "rep", sum(F.when(F.col(f"s{k}") >= 0, 1 << k).otherwise(0) for k in range(g)).cast("long").alias("code"))
    e = angles.by_angle(im, a)
    bits = F.col("pairs") * reps * g
    return e.select("bin", bits.alias("n"), (1 - F.col("differ") / bits).alias("agree"), (1 - F.col("turn") / F.col("pairs")).alias("law"))


ALL = {f.__name__: f for f in (x1_solvers, x2_order, x3_serial_and_parallel, x4_searches, x5_pq, x6_fk, x7_blend_or_factor, x8_noise, x9_online, x10_workers, x11_hit_ratio, x12_rescaled, x13_angle_law)}


def main(sf_dir: str = "/root/testdata/sf0.01") -> None:
    spark = SparkSession.builder.master("local[*]").config("spark.sql.shuffle.partitions", "8").config("spark.ui.enabled", "false").config("spark.driver.memory", "8g").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    for name, run in ALL.items():
        print(f"\n{name}: {(run.__doc__ or '').strip().splitlines()[0] if run.__doc__ else ''}", flush=True)
        run(spark, sf_dir).show(60, truncate=False)


if __name__ == "__main__":
    main(*sys.argv[1:])
