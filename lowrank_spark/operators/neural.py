"""Neural baselines on implicit feedback: elementwise product, dense layers, and both fused.

Users are dealt to D tasks; each task trains on its users' examples with its own copy of the item embeddings and
dense weights it needs, and copies are averaged after an epoch (item embeddings in the JVM, the dense weights, whose
size does not depend on the data, on the driver). Plain mini-batch descent on log-loss, numpy only.
"""

from __future__ import annotations

import json
import time
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lowrank_spark.functions.hashing import md5_int, text
from lowrank_spark.operators.params import Versions, vector
from lowrank_spark.runtime import Scratch, ship_package

STATE = "side string, id string, p array<double>, m array<double>"


@dataclass(frozen=True)
class NetConfig:
    kind: str = "fused"  # product, mlp, fused
    F: int = 8
    layers: tuple[int, ...] = (16, 8)
    epochs: int = 5
    rate: float = 0.5
    batch: int = 256
    D: int = 4
    seed: int = 3


@dataclass
class Net:
    cfg: NetConfig
    state: DataFrame
    dense: dict
    history: list = field(default_factory=list)


def init_dense(cfg: NetConfig) -> dict[str, np.ndarray]:
    rng = np.random.default_rng(cfg.seed)
    out, size = {}, 2 * cfg.F
    if cfg.kind != "product":
        for n, h in enumerate(cfg.layers):
            out[f"W{n}"], out[f"b{n}"] = rng.normal(0, (2 / size) ** 0.5, (size, h)), np.zeros(h)
            size = h
    last = (cfg.F if cfg.kind != "mlp" else 0) + (size if cfg.kind != "product" else 0)
    out["h"], out["h0"] = rng.normal(0, 1 / last**0.5, last), np.zeros(1)
    return out


def forward(cfg: NetConfig, d: dict, pu, pi, mu, mi) -> tuple[np.ndarray, list]:
    """(scores, activations): p* feed the product, m* the dense layers."""
    acts, tail = [], []
    if cfg.kind != "mlp":
        tail.append(pu * pi)
    if cfg.kind != "product":
        x = np.concatenate([mu, mi], axis=1)
        acts.append(x)
        for n in range(len(cfg.layers)):
            x = np.maximum(x @ d[f"W{n}"] + d[f"b{n}"], 0)
            acts.append(x)
        tail.append(x)
    z = np.concatenate(tail, axis=1)
    return z @ d["h"] + d["h0"][0], [*acts, z]


def train_batch(cfg: NetConfig, d: dict, P: np.ndarray, Q: np.ndarray, M: np.ndarray, N: np.ndarray, u: np.ndarray, i: np.ndarray, y: np.ndarray, rate: float) -> None:
    """One step on a mini-batch, in place. P, M: user vectors; Q, N: item vectors."""
    s, acts = forward(cfg, d, P[u], Q[i], M[u], N[i])
    g = (1 / (1 + np.exp(-np.clip(s, -35, 35))) - y) / len(y)
    z = acts[-1]
    gz = g[:, None] * d["h"][None, :]
    gh, gh0 = z.T @ g, g.sum()
    pu, qi = P[u], Q[i]
    n = cfg.F if cfg.kind != "mlp" else 0
    if n:
        gp, gq = gz[:, :n] * qi, gz[:, :n] * pu
    if cfg.kind != "product":
        gx = gz[:, n:]
        for k in range(len(cfg.layers) - 1, -1, -1):
            gx = gx * (acts[k + 1] > 0)
            back = gx @ d[f"W{k}"].T
            d[f"W{k}"] -= rate * acts[k].T @ gx
            d[f"b{k}"] -= rate * gx.sum(0)
            gx = back
        np.add.at(M, u, -rate * len(y) * 0.1 * gx[:, : cfg.F])
        np.add.at(N, i, -rate * len(y) * 0.1 * gx[:, cfg.F :])
    if n:
        np.add.at(P, u, -rate * len(y) * 0.1 * gp)
        np.add.at(Q, i, -rate * len(y) * 0.1 * gq)
    d["h"] -= rate * gh
    d["h0"] -= rate * gh0


def _pack(d: dict) -> str:
    return json.dumps({k: [list(v.shape), v.ravel().tolist()] for k, v in d.items()})


def _unpack(s: str) -> dict:
    return {k: np.array(v).reshape(shape) for k, (shape, v) in json.loads(s).items()}


def _worker(cfg: NetConfig, dense: str, t: int):
    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        side, ids = right.column("side").to_pylist(), right.column("id").to_pylist()
        at = {(s, x): n for n, (s, x) in enumerate(zip(side, ids, strict=True))}
        p = np.array(right.column("p").to_pylist(), float).reshape(len(ids), cfg.F)
        m = np.array(right.column("m").to_pylist(), float).reshape(len(ids), cfg.F)
        d = _unpack(dense)
        if left.num_rows:
            keys = sorted(zip(left.column("ord").to_pylist(), left.column("i").to_pylist(), left.column("j").to_pylist(), left.column("y").to_pylist(), strict=True))
            u, i = np.array([at["r", k[1]] for k in keys]), np.array([at["c", k[2]] for k in keys])
            y = np.array([k[3] for k in keys], float)
            order = np.random.default_rng(cfg.seed * 1000 + t).permutation(len(y))
            for lo in range(0, len(y), cfg.batch):
                s = order[lo : lo + cfg.batch]
                train_batch(cfg, d, p, p, m, m, u[s], i[s], y[s], cfg.rate)
        lists = lambda x: pa.array(list(x), pa.list_(pa.float64()))
        out = pa.table({"side": pa.array(side, pa.string()), "id": pa.array(ids, pa.string()), "p": lists(p), "m": lists(m)})
        flat = pa.table({"side": pa.array(["dense"]), "id": pa.array([_pack(d)]), "p": lists([[float(max(1, left.num_rows))]]), "m": lists([[]])})
        return pa.concat_tables([out, flat.cast(out.schema)])

    return run


def examples(positive: DataFrame, n_negative: int = 4) -> DataFrame:
    """(i, j, y): the positives, and hashed columns of the observed ones that the row does not have."""
    cols = positive.select("j").distinct()
    from lowrank_spark.sources.prep import index_ids

    ids = index_ids(cols, "j").select("j", "id")
    n = ids.count()
    t = F.explode(F.sequence(F.lit(0), F.lit(n_negative - 1))).alias("t")
    neg = positive.select("i", "j", t).select("i", (md5_int(text("nneg", F.col("i"), F.col("j"), F.col("t")), 14) % max(1, n)).alias("id")).distinct().join(ids, "id").select("i", "j")
    neg = neg.join(positive.select("i", "j"), ["i", "j"], "left_anti")
    return positive.select("i", "j", F.lit(1).alias("y")).union(neg.select("i", "j", F.lit(0).alias("y")))


def train(ex: DataFrame, cfg: NetConfig, watch=None) -> Net:
    spark = ex.sparkSession
    ship_package(spark)
    scratch, versions = Scratch(spark, "net"), Versions(spark, "net-state")
    e = ex.select(F.col("i").cast("string").alias("i"), F.col("j").cast("string").alias("j"), "y")
    e = scratch.keep(e.withColumns({"task": md5_int(text("nt", F.col("i")), 8) % cfg.D, "ord": md5_int(text("no", F.col("i"), F.col("j")), 8)}))
    ids = e.select(F.lit("r").alias("side"), F.col("i").alias("id")).union(e.select(F.lit("c"), "j")).distinct()
    small = lambda tag: F.transform(vector(tag, F.concat("side", "id"), cfg.F), lambda x: x * 0.5)
    state = versions.commit(ids.select("side", "id", small("np").alias("p"), small("nm").alias("m")))
    need = scratch.keep(e.select("task", F.lit("r").alias("side"), F.col("i").alias("id")).union(e.select("task", F.lit("c"), "j")).distinct())
    net, began = Net(cfg, state, init_dense(cfg)), time.perf_counter()
    mean = lambda c: F.array(*[F.avg(F.get(F.col(c), F.lit(k))) for k in range(cfg.F)])
    for t in range(cfg.epochs):
        moved = scratch.keep(e.groupBy("task").cogroup(state.join(need, ["side", "id"]).groupBy("task")).applyInArrow(_worker(cfg, _pack(net.dense), t), STATE))
        got = moved.where("side = 'dense'").select("id", F.get("p", F.lit(0)).alias("n")).collect()  # D rows of fixed size
        total = sum(r["n"] for r in got)
        parts = [(r["n"] / total, _unpack(r["id"])) for r in got]
        net.dense = {k: sum(w * d[k] for w, d in parts) for k in net.dense}
        state = net.state = versions.commit(moved.where("side != 'dense'").groupBy("side", "id").agg(mean("p").alias("p"), mean("m").alias("m")))
        scratch.drop(moved)
        if watch is not None:
            net.history.append({"epoch": t + 1, "seconds": time.perf_counter() - began, "hr": watch(net)})
    return net


def score(net: Net, pairs: DataFrame) -> DataFrame:
    """pairs (i, j, y) + score; one narrow pass over the joined embeddings."""
    cfg, dense = net.cfg, _pack(net.dense)
    ship_package(pairs.sparkSession)
    r = net.state.where("side = 'r'").select(F.col("id").alias("_i"), F.col("p").alias("pu"), F.col("m").alias("mu"))
    c = net.state.where("side = 'c'").select(F.col("id").alias("_j"), F.col("p").alias("pi"), F.col("m").alias("mi"))
    x = pairs.join(r, pairs["i"].cast("string") == r["_i"]).join(c, pairs["j"].cast("string") == c["_j"]).select("i", "j", "y", "pu", "pi", "mu", "mi")
    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in x.schema.fields[:3]) + ", score double"

    def run(batches):
        d = _unpack(dense)
        for b in batches:
            if not b.num_rows:
                continue
            v = [np.array(b.column(k).to_pylist(), float).reshape(b.num_rows, cfg.F) for k in range(3, 7)]
            s, _ = forward(cfg, d, *v)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(2), pa.array(s)], names=["i", "j", "y", "score"])

    return x.mapInArrow(run, schema)


def net_product(ex: DataFrame, cfg: NetConfig = NetConfig(), watch=None) -> Net:
    from dataclasses import replace

    return train(ex, replace(cfg, kind="product"), watch)


def net_mlp(ex: DataFrame, cfg: NetConfig = NetConfig(), watch=None) -> Net:
    from dataclasses import replace

    return train(ex, replace(cfg, kind="mlp"), watch)


def net_fused(ex: DataFrame, cfg: NetConfig = NetConfig(), watch=None) -> Net:
    from dataclasses import replace

    return train(ex, replace(cfg, kind="fused"), watch)
