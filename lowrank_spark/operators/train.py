"""Solvers: block-rotating stochastic descent (factor-only and blended), entry-parallel descent, ALS, coordinate descent.

Layout of the rotation: rows and columns are hashed into D blocks; in sub-step s worker d holds column block d, with
its biases, vectors and neighbour weights, and row block (d + s) mod D. No two workers share a row or a column, D
sub-steps cover every entry once, and between sub-steps only row state moves to its next worker. Entries are laid out
once per training; parameters are committed as a version per epoch, which cuts the lineage.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from lowrank_spark.config import TrainConfig
from lowrank_spark.functions.hashing import md5_int, text
from lowrank_spark.operators import biases, kernel, metrics, neigh, params, steps
from lowrank_spark.runtime import Scratch, ship_package

#: Entries, with the other side's vectors, that one task of the least-squares baseline holds.
ENTRIES_A_BUCKET = 200_000
#: Lists of an entry's neighbours, which only blended models have; packed as bytes once the waves are laid.
NEAR = {"ex_k": np.int32, "ex_x": np.float64, "im_k": np.int32}
STATE = "side string, id string, bias double, vec array<double>, w array<double>, c array<double>"
_STATE_ARROW = pa.schema([("side", pa.string()), ("id", pa.string()), ("bias", pa.float64()), ("vec", pa.list_(pa.float64())), ("w", pa.list_(pa.float64())), ("c", pa.list_(pa.float64()))])


@dataclass
class Model:
    cfg: TrainConfig
    mu: float
    state: DataFrame
    types: tuple[str, str]
    top: DataFrame | None = None
    means: tuple | None = None
    rated: DataFrame | None = None
    history: list[dict] = field(default_factory=list)

    def rows(self) -> DataFrame:
        return self.state.where("side = 'r'").select(F.col("id").cast(self.types[0]).alias("i"), F.col("bias").alias("b"), F.col("vec").alias("u"))

    def cols(self, weights: bool = False) -> DataFrame:
        return self.state.where("side = 'c'").select(F.col("id").cast(self.types[1]).alias("j"), F.col("bias").alias("bh"), F.col("vec").alias("v"), *["w", "c"] * weights)

    def weights(self) -> DataFrame:
        x = self.state.where("side = 'c'").select(F.col("id").cast(self.types[1]).alias("j"), F.posexplode(F.arrays_zip("w", "c")).alias("k", "wc"))
        return x.select("j", (F.col("k") + 1).cast("long").alias("k"), "wc.w", "wc.c")


def block_of(axis: str, ident, d: int):
    return md5_int(text("blk", axis, ident), 8) % d


def plan(d: int) -> list[tuple[int, int, int, int]]:
    """(step, worker, row block, column block), all from 1."""
    return [(s, w, (w + s - 2) % d + 1, w) for s in range(1, d + 1) for w in range(1, d + 1)]


def layout(im: DataFrame, cfg: TrainConfig, top: DataFrame | None = None, means: tuple | None = None, rated: DataFrame | None = None) -> DataFrame:
    """Entries with blocks and, for the blended model, the residuals at rated neighbours and the places of the others."""
    x = im.select("i", "j", "r")
    if top is not None and cfg.parts & {"explicit", "implicit"}:
        x = neigh.near_lists(x, top, means, rated)
    place = {"degree": F.lit(0), "id": F.lit(0), "hashed": md5_int(text("ord", F.col("i"), F.col("j")), 8)}[cfg.order]
    if cfg.order == "degree":
        axis = "i" if cfg.side == "row" else "j"
        deg = im.groupBy(axis).agg(F.count(F.lit(1)).alias("_d"))
        x = x.join(deg, axis).withColumn("place", -F.col("_d")).drop("_d")
    else:
        x = x.withColumn("place", place.cast("long"))
    return x.select(block_of("i", F.col("i"), cfg.D).alias("rb"), block_of("j", F.col("j"), cfg.D).alias("cb"), F.col("i").cast("string").alias("i"), F.col("j").cast("string").alias("j"), "r", "place", *[c for c in NEAR if c in x.columns])


def init_state(im: DataFrame, cfg: TrainConfig, means: tuple, k: int) -> DataFrame:
    """Biases from the means (0 for a model without), hashed vectors, zero neighbour weights."""
    _, b, bh = means
    zero = F.array_repeat(F.lit(0.0), k)
    rows = params.init_rows(im, cfg.F).join(b, "i", "left").select(F.lit("r").alias("side"), F.col("i").cast("string").alias("id"), F.coalesce("b", F.lit(0.0)).alias("bias"), F.col("u").alias("vec"), F.array_repeat(F.lit(0.0), 0).alias("w"), F.array_repeat(F.lit(0.0), 0).alias("c"))
    cols = params.init_cols(im, cfg.F).join(bh, "j", "left").select(F.lit("c").alias("side"), F.col("j").cast("string").alias("id"), F.coalesce("bh", F.lit(0.0)).alias("bias"), F.col("v").alias("vec"), zero.alias("w"), zero.alias("c"))
    return rows.union(cols)


def _matrix(col: pa.ChunkedArray, width: int, n: int) -> np.ndarray:
    flat = col.combine_chunks().flatten().to_numpy(zero_copy_only=False) if n else np.zeros(0)
    return flat.reshape(n, width).copy() if width else np.zeros((n, 0))


def _packed(col: pa.ChunkedArray) -> pa.Array:
    """A column of lists as one of bytes, null as none: rows of lists are slow to move between Spark and Python."""
    lists = col.combine_chunks()
    flat = lists.flatten().to_numpy(zero_copy_only=False)
    ends = np.concatenate([[0], np.cumsum(pc.list_value_length(lists).fill_null(0).to_numpy(zero_copy_only=False))]) * flat.itemsize
    return pa.Array.from_buffers(pa.binary(), len(lists), [None, pa.py_buffer(ends.astype(np.int32)), pa.py_buffer(np.ascontiguousarray(flat))])


def _unpacked(col: pa.ChunkedArray, kind: type) -> tuple[np.ndarray, np.ndarray]:
    """(lengths, values) of a column that `_packed` made."""
    size = pc.binary_length(col).to_numpy() // np.dtype(kind).itemsize
    whole = col.combine_chunks()
    ends = np.frombuffer(whole.buffers()[1], np.int32)[whole.offset : whole.offset + len(whole) + 1]
    data = whole.buffers()[2]
    return size, np.frombuffer(data.slice(ends[0], ends[-1] - ends[0]), kind) if data is not None else np.zeros(0, kind)


def _dense(entries: pa.Table, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    n = entries.num_rows
    res, is_ex, is_im = np.zeros((n, k)), np.zeros((n, k), bool), np.zeros((n, k), bool)
    for name, fill in (("ex_k", is_ex), ("im_k", is_im)):
        size, place = _unpacked(entries.column(name), NEAR[name])
        at = np.repeat(np.arange(n), size)
        fill[at, place - 1] = True
        if name == "ex_k":
            res[at, place - 1] = _unpacked(entries.column("ex_x"), NEAR["ex_x"])[1]
    return res, is_ex, is_im


def _places(ids: pa.ChunkedArray, among: pa.ChunkedArray) -> np.ndarray:
    return pc.index_in(ids, value_set=among.combine_chunks()).to_numpy()


def with_waves(entries: pa.Table, side: str) -> pa.Table:
    """entries + wave (see kernel.waves), taken in the order of the training; it is the same in every epoch."""
    first, second = ("i", "j") if side == "row" else ("j", "i")
    entries = entries.take(pc.sort_indices(entries, sort_keys=[(c, "ascending") for c in ("place", first, second)]))
    for c in [c for c in NEAR if c in entries.column_names]:
        entries = entries.set_column(entries.column_names.index(c), c, _packed(entries.column(c)))
    code = lambda c: entries.column(c).combine_chunks().dictionary_encode().indices.to_numpy()
    return entries.append_column("wave", pa.array(kernel.wave_of(code("i"), code("j")), pa.int64()))


def lay_waves(entries: DataFrame, by: list[str], side: str) -> DataFrame:
    """entries + wave, worked out once for each block of a training."""
    fields = [T.StructField(f.name, T.BinaryType()) if f.name in NEAR else f for f in entries.schema.fields]
    return entries.groupBy(*by).applyInArrow(lambda t: with_waves(t, side), T.StructType([*fields, T.StructField("wave", T.LongType())]))


def run_block(entries: pa.Table, state: pa.Table, mu: float, cfg: TrainConfig, t: int, k: int, freeze_rows: bool, freeze_cols: bool) -> pa.Table:
    """One worker's sub-step: its entries against its row and column state."""
    if not entries.num_rows:
        return state.select(_STATE_ARROW.names).cast(_STATE_ARROW)
    if "wave" not in entries.column_names:
        entries = with_waves(entries, cfg.side)
    # entries of one wave share nothing, so their order does not matter
    entries = entries.take(pc.array_sort_indices(entries.column("wave")))
    side = np.array(state.column("side").to_pylist())
    parts = {s: state.filter(pa.array(side == s)) for s in ("r", "c")}
    num = lambda s: parts[s].num_rows
    bias = {s: parts[s].column("bias").to_numpy().copy() for s in parts}
    vec = {s: _matrix(parts[s].column("vec"), cfg.F, num(s)) for s in parts}
    w, c = (_matrix(parts["c"].column(x), k, num("c")) for x in ("w", "c"))
    near = _dense(entries, k) if k and cfg.parts & {"explicit", "implicit"} else (None, None, None)
    rows, cols = (_places(entries.column(e), parts[s].column("id")) for s, e in (("r", "i"), ("c", "j")))
    block = kernel.Block(rows, cols, entries.column("r").to_numpy(), bias["r"], vec["r"], bias["c"], vec["c"], w, c, *near)
    wave = entries.column("wave").to_numpy()
    cuts = np.split(np.arange(len(wave)), np.flatnonzero(np.diff(wave)) + 1)
    kernel.sgd(block, mu, cfg, t, freeze_rows, freeze_cols, cuts)
    lists = lambda m: pa.ListArray.from_arrays(np.arange(0, m.size + 1, m.shape[1], np.int32) if m.shape[1] else np.zeros(len(m) + 1, np.int32), pa.array(np.ascontiguousarray(m).ravel()))
    empty = [[]] * num("r")
    out = [pa.concat_arrays([parts[s].column(x).combine_chunks() for s in ("r", "c")]) for x in ("side", "id")]
    return pa.table([*out, pa.array(np.concatenate([bias["r"], bias["c"]])), pa.concat_arrays([lists(vec["r"]), lists(vec["c"])]), pa.concat_arrays([pa.array(empty, pa.list_(pa.float64())), lists(w)]), pa.concat_arrays([pa.array(empty, pa.list_(pa.float64())), lists(c)])], schema=_STATE_ARROW)


def _worker(mu: float, cfg: TrainConfig, t: int, k: int, freeze_rows: bool = False, freeze_cols: bool = False):
    return lambda left, right: run_block(left, right, mu, cfg, t, k, freeze_rows, freeze_cols)


def substep(entries: DataFrame, state: DataFrame, s: int, mu: float, cfg: TrainConfig, t: int, k: int, freeze_rows: bool = False, freeze_cols: bool = False) -> DataFrame:
    d = cfg.D
    e = entries.where(F.col("turn") == s).drop("turn").withColumn("task", F.col("cb"))
    blk = F.when(F.col("side") == "c", block_of("j", F.col("id"), d)).otherwise(F.pmod(block_of("i", F.col("id"), d) - s, F.lit(d)))
    st = state.withColumn("task", blk)
    return e.groupBy("task").cogroup(st.groupBy("task")).applyInArrow(_worker(mu, cfg, t, k, freeze_rows, freeze_cols), STATE)


def fit(entries: DataFrame, state: DataFrame, mu: float, cfg: TrainConfig, k: int, freeze_rows: bool = False, freeze_cols: bool = False, watch: Callable[[DataFrame, int], float] | None = None, epochs: int | None = None) -> tuple[DataFrame, list[dict]]:
    spark = entries.sparkSession
    ship_package(spark)
    # one folder a sub-step: a sub-step reads its own entries and no others
    entries = lay_waves(entries.withColumn("turn", F.pmod(F.col("rb") - F.col("cb"), F.lit(cfg.D)).cast("int")), ["turn", "cb"], cfg.side)
    entries = Scratch(spark, "entries").keep(entries, ["turn"])
    versions = params.Versions(spark, "state")
    state = versions.commit(state)
    history, began = [], time.perf_counter()
    for t in range(cfg.epochs if epochs is None else epochs):
        for s in range(cfg.D):
            state = substep(entries, state, s, mu, cfg, t, k, freeze_rows, freeze_cols)
        state = versions.commit(state)
        if watch is not None:
            history.append({"epoch": t + 1, "seconds": time.perf_counter() - began, "rmse": watch(state, t)})
            if cfg.target is not None and history[-1]["rmse"] <= cfg.target:
                break
    return state, history


def _train(im: DataFrame, cfg: TrainConfig, top: DataFrame | None, test: DataFrame | None) -> Model:
    spark = im.sparkSession
    scratch = Scratch(spark, "train")
    im = scratch.keep(im.select("i", "j", "r"))
    means = tuple(scratch.keep(m) for m in biases.means(im))
    mu = (means[0].first()["mu"] or 0.0) if cfg.loss == "squared" else 0.0
    k = cfg.K if top is not None else 0
    if top is not None:
        top = scratch.keep(top.select("j", "nbr", "k").where(F.col("k") <= k))
    start = init_state(im, cfg, means, k)
    if cfg.loss == "logistic" or not cfg.use_bias:
        start = start.withColumn("bias", F.lit(0.0))
    types = (im.schema["i"].dataType.simpleString(), im.schema["j"].dataType.simpleString())
    model = Model(cfg, mu, start, types, top, means, im)
    watch = None
    if test is not None:
        test = scratch.keep(with_near(model, test))

        def watch(state, t):
            model.state = state
            return metrics.rmse(score(model, test))

    model.state, model.history = fit(layout(im, cfg, top, means), start, mu, cfg, k, watch=watch)
    return model


def with_near(model: Model, entries: DataFrame) -> DataFrame:
    """entries with the lists of their neighbours, where the model has neighbours; the same in every epoch."""
    x = entries.select("i", "j", "r")
    if model.top is None or not model.cfg.parts & {"explicit", "implicit"}:
        return x
    return neigh.near_lists(x, model.top, model.means, model.rated)


def score(model: Model, entries: DataFrame) -> DataFrame:
    """entries + pred; neighbour residuals are taken at the means, as in training. Entries may come from `with_near`."""
    cfg = model.cfg
    x = entries if "im_k" in entries.columns else with_near(model, entries)
    near = model.top is not None and bool(cfg.parts & {"explicit", "implicit"})
    x = x.join(model.rows(), "i", "left").join(model.cols(near), "j", "left")
    total = F.lit(0.0)
    if "base" in cfg.parts:
        total = total + F.lit(model.mu) + F.coalesce("b", F.lit(0.0)) + F.coalesce("bh", F.lit(0.0))
    if "factor" in cfg.parts:
        total = total + F.coalesce(params.dot("u", "v"), F.lit(0.0))
    at = lambda of, k: F.coalesce(F.get(F.col(of), k - 1), F.lit(0.0))
    add = lambda xs: F.coalesce(F.aggregate(xs, F.lit(0.0), lambda s, v: s + v) / F.sqrt(F.greatest(F.size(xs), F.lit(1)).cast("double")), F.lit(0.0))
    if near and "explicit" in cfg.parts:
        total = total + add(F.zip_with("ex_k", "ex_x", lambda k, v: v * at("w", k)))
    if near and "implicit" in cfg.parts:
        total = total + add(F.transform("im_k", lambda k: at("c", k)))
    return x.select("i", "j", "r", total.alias("pred"))


def resident_sgd(im: DataFrame, cfg: TrainConfig, side: str = "row", test: DataFrame | None = None) -> Model:
    """Factor-only descent: entries ordered by the resident side, the other side's block mutated in place."""
    return _train(im, cfg.but(side=side, parts=frozenset({"factor"}), use_bias=False), None, test)


def factor_bias_sgd(im: DataFrame, cfg: TrainConfig, test: DataFrame | None = None) -> Model:
    """Biases and factors, no neighbours: the blend with its neighbour parts off."""
    return _train(im, cfg.but(parts=frozenset({"base", "factor"})), None, test)


def blend_mf(im: DataFrame, top: DataFrame, cfg: TrainConfig, test: DataFrame | None = None) -> Model:
    """The blended model over the neighbours `top` (j, nbr, k), column-resident; D = 1 is the serial reference."""
    return _train(im, cfg.but(side="col"), top, test)


def rotation(im: DataFrame, cfg: TrainConfig, d: int, model: str = "factor", top: DataFrame | None = None, test: DataFrame | None = None) -> Model:
    cfg = cfg.but(D=d)
    return resident_sgd(im, cfg, test=test) if model == "factor" else blend_mf(im, top, cfg, test)


def until(train: Callable[[], Model], target: float) -> dict:
    """Epochs and seconds to the target, or None for both; train() must watch a test set."""
    h = next((h for h in train().history if h["rmse"] <= target), None)
    return {"epochs": h and h["epoch"], "seconds": h and h["seconds"]}


def entry_sgd(im: DataFrame, cfg: TrainConfig, mode: str = "average", test: DataFrame | None = None) -> Model:
    """Entry-parallel descent that ignores who shares rows and columns.

    average: entries are dealt at random to D parts, each part runs on copies of the parameters it touches, copies
    are averaged after each epoch. minibatch: all gradients of an epoch are averaged by joins and
    aggregates, and the step is `batch_gain` times the rate.
    """
    spark = im.sparkSession
    ship_package(spark)
    cfg = cfg.but(parts=frozenset({"factor"}), use_bias=False)
    scratch, versions = Scratch(spark, "entry"), params.Versions(spark, "entry-state")
    im = scratch.keep(im.select("i", "j", "r"))
    types = (im.schema["i"].dataType.simpleString(), im.schema["j"].dataType.simpleString())
    zero = (spark.range(1).select(F.lit(0.0).alias("mu")), im.select("i").distinct().withColumn("b", F.lit(0.0)), im.select("j").distinct().withColumn("bh", F.lit(0.0)))
    state = versions.commit(init_state(im, cfg, zero, 0))
    model = Model(cfg, 0.0, state, types, rated=im)
    began = time.perf_counter()
    part = md5_int(text("part", F.col("i"), F.col("j")), 8) % cfg.D
    entries = scratch.keep(lay_waves(layout(im, cfg.but(order="hashed")).withColumn("task", part.cast("long")), ["task"], cfg.side))
    touched = scratch.keep(entries.select("task", F.lit("r").alias("side"), F.col("i").alias("id")).union(entries.select("task", F.lit("c"), "j")).groupBy("task", "side", "id").agg(F.count(F.lit(1)).alias("n")))
    for t in range(cfg.epochs):
        if mode == "average":
            copies = state.join(touched.select("task", "side", "id"), ["side", "id"])
            moved = entries.groupBy("task").cogroup(copies.groupBy("task")).applyInArrow(_worker(0.0, cfg, t, 0), STATE)
            mean = [F.avg(F.get(F.col("vec"), F.lit(x))) for x in range(cfg.F)]
            none = F.array_repeat(F.lit(0.0), 0)
            state = moved.groupBy("side", "id").agg(F.avg("bias").alias("bias"), F.array(*mean).alias("vec")).select("side", "id", "bias", "vec", none.alias("w"), none.alias("c"))
        else:
            rows, cols = model.rows(), model.cols()
            x = im.join(rows.select("i", "u"), "i").join(cols.select("j", "v"), "j").withColumn("pred", params.dot("u", "v"))
            err = steps.with_error(x, cfg.loss)
            many = cfg.but(alpha=type(cfg.alpha)(0, 0, cfg.alpha.u * cfg.batch_gain, cfg.alpha.v * cfg.batch_gain, 0, 0))
            u, v = steps.step_u(err, rows, many, t), steps.step_v(err, cols, many, t)
            none = F.array_repeat(F.lit(0.0), 0)
            state = u.select(F.lit("r").alias("side"), F.col("i").cast("string").alias("id"), F.lit(0.0).alias("bias"), F.col("u").alias("vec"), none.alias("w"), none.alias("c")).union(v.select(F.lit("c"), F.col("j").cast("string"), F.lit(0.0), "v", none, none))
        state = model.state = versions.commit(state)
        if test is not None:
            model.history.append({"epoch": t + 1, "seconds": time.perf_counter() - began, "rmse": metrics.rmse(score(model, test))})
            if cfg.target is not None and model.history[-1]["rmse"] <= cfg.target:
                break
    return model


def _solve_side(im: DataFrame, other: DataFrame, key: str, other_key: str, vec: str, out: str, lam: float, weighted: bool, buckets: int) -> DataFrame:
    """Normal equations of one side, solved per hash bucket of owners: nothing of size F^2 leaves a task."""
    kt = im.schema[key].dataType
    x = im.join(other.select(other_key, vec), other_key).select(F.pmod(F.xxhash64(key), F.lit(buckets)).alias("task"), F.col(key).alias("id"), "r", F.col(vec).alias("vec"))

    def run(t: pa.Table) -> pa.Table:
        ids = t.column("id").to_pylist()
        names = {v: n for n, v in enumerate(dict.fromkeys(ids))}
        f = len(t.column("vec")[0].as_py())
        owners, sol = kernel.ridge_rows(np.array([names[v] for v in ids]), t.column("r").to_numpy(), _matrix(t.column("vec"), f, t.num_rows), lam, weighted)
        back = list(names)
        return pa.table({key: pa.array([back[o] for o in owners], t.schema.field("id").type), out: pa.array(list(sol), pa.list_(pa.float64()))})

    return x.groupBy("task").applyInArrow(run, f"{key} {kt.simpleString()}, {out} array<double>")


def als(im: DataFrame, rank: int = 8, reg: float = 0.05, iters: int = 10, weighted: bool = True, buckets: int | None = None, test: DataFrame | None = None, target: float | None = None) -> tuple[DataFrame, DataFrame, list[dict]]:
    """(rows, cols, history) by alternating least squares.

    Owners are dealt to buckets of about ENTRIES_A_BUCKET entries (or the number given).
    """
    spark = im.sparkSession
    ship_package(spark)
    scratch, versions = Scratch(spark, "als"), params.Versions(spark, "als-side", 4)
    im = scratch.keep(im.select("i", "j", "r"))
    buckets = buckets or max(8, -(-im.count() // ENTRIES_A_BUCKET))
    cols, rows, history, began = params.init_cols(im, rank), None, [], time.perf_counter()
    cols = versions.commit(cols.select("j", F.transform("v", lambda x: x + 0.5).alias("v")))
    for t in range(iters):
        rows = versions.commit(_solve_side(im, cols, "i", "j", "v", "u", reg, weighted, buckets))
        cols = versions.commit(_solve_side(im, rows, "j", "i", "u", "v", reg, weighted, buckets))
        if test is not None:
            p = test.join(rows, "i").join(cols, "j").withColumn("pred", params.dot("u", "v"))
            history.append({"epoch": t + 1, "seconds": time.perf_counter() - began, "rmse": metrics.rmse(p)})
            if target is not None and history[-1]["rmse"] <= target:
                break
    return rows, cols, history


def als_library(im: DataFrame, rank: int = 8, reg: float = 0.05, iters: int = 10, seed: int = 7):
    """The library's ALS on integer ids, fitted: the cross-check."""
    from pyspark.ml.recommendation import ALS

    x = im.select(F.col("i").cast("int").alias("i"), F.col("j").cast("int").alias("j"), F.col("r").cast("float").alias("r"))
    return ALS(rank=rank, regParam=reg, maxIter=iters, userCol="i", itemCol="j", ratingCol="r", seed=seed, coldStartStrategy="drop").fit(x)


def ccd(im: DataFrame, rank: int = 4, lam: float = 0.05, sweeps: int = 2) -> tuple[DataFrame, DataFrame]:
    """Cyclic coordinate descent, one rank after another on the residual: aggregates and joins only."""
    scratch = Scratch(im.sparkSession, "ccd")
    left = scratch.keep(im.select("i", "j", "r"))
    us, vs = [], []
    for k in range(rank):
        v = left.select("j").distinct().withColumn("v", F.get(params.vector(f"ccd{k}", F.col("j"), 1), F.lit(0)) / 2 + 1)
        for _ in range(sweeps):
            u, v = steps.ccd_rank_one(left, v, lam)
            u, v = scratch.keep(u), scratch.keep(v)
        us.append(u.withColumn("k", F.lit(k)))
        vs.append(v.withColumn("k", F.lit(k)))
        left = scratch.keep(left.join(u, "i").join(v, "j").select("i", "j", (F.col("r") - F.col("u") * F.col("v")).alias("r")))
    join = lambda parts, key, c: _stack(parts).groupBy(key).agg(F.transform(F.array_sort(F.collect_list(F.struct("k", c))), lambda s: s[c]).alias(c))
    return join(us, "i", "u"), join(vs, "j", "v")


def _stack(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def nmf(im: DataFrame, f: int = 4, iters: int = 3) -> tuple[DataFrame, DataFrame]:
    """Non-negative factors by multiplicative steps."""
    scratch = Scratch(im.sparkSession, "nmf")
    im = scratch.keep(im.select("i", "j", "r"))
    rows = scratch.keep(params.init_rows(im, f).select("i", F.transform("u", lambda x: F.abs(x) + 0.1).alias("u")))
    cols = scratch.keep(params.init_cols(im, f).select("j", F.transform("v", lambda x: F.abs(x) + 0.1).alias("v")))
    for _ in range(iters):
        x = im.join(rows, "i").join(cols, "j").withColumn("pred", params.dot("u", "v"))
        rows = scratch.keep(steps.nmf_rows(x, rows, f))
        y = im.join(rows, "i").join(cols, "j").withColumn("pred", params.dot("u", "v"))
        flipped = y.select(F.col("j").alias("i"), "r", "pred", F.col("u").alias("v"))
        cols = scratch.keep(steps.nmf_rows(flipped, cols.select(F.col("j").alias("i"), F.col("v").alias("u")), f).select(F.col("i").alias("j"), F.col("u").alias("v")))
    return rows, cols
