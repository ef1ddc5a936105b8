"""Online learning: merge hash sums, search for new columns only, train new parameters only."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lowrank_spark.config import HashConfig, TrainConfig
from lowrank_spark.operators import metrics, signhash, train


def merge_sums(saved: DataFrame, delta: DataFrame, g: int = 8) -> DataFrame:
    """(j, rep, s0..): saved sums plus the sums of new entries; a column unknown so far starts at 0."""
    lanes = [f"s{k}" for k in range(g)]
    return saved.select("j", "rep", *lanes).unionByName(delta.select("j", "rep", *lanes)).groupBy("j", "rep").agg(*[F.sum(s).alias(s) for s in lanes])


def update_codes(saved: DataFrame, new_entries: DataFrame, cfg: HashConfig) -> tuple[DataFrame, DataFrame]:
    """(merged sums, their codes) after new entries: additions for the delta only, whatever the history's size."""
    merged = merge_sums(saved, signhash.accumulate(new_entries, cfg), cfg.G)
    return merged, signhash.codes(merged, cfg.G)


def search_new(key_rows: DataFrame, new_columns: DataFrame, k: int) -> DataFrame:
    """(j, nbr, freq, k) for new columns over all columns; old columns keep the neighbours they have.

    Only buckets of new columns are looked up; Catalyst broadcasts the new keys where they are small.
    """
    new = key_rows.join(new_columns.select("j").distinct(), "j", "left_semi").select("grp", "key", F.col("j"))
    hits = new.join(key_rows.select("grp", "key", F.col("j").alias("nbr")), ["grp", "key"]).where("j != nbr")
    freq = hits.groupBy("j", "nbr").agg(F.count(F.lit(1)).alias("freq"))
    pairs = freq.select(F.col("j").alias("j1"), F.col("nbr").alias("j2"), "freq")
    from pyspark.sql import Window

    w = Window.partitionBy("j1").orderBy(F.col("freq").desc(), "j2")
    top = pairs.withColumn("k", F.row_number().over(w)).where(F.col("k") <= k)
    return top.select(F.col("j1").alias("j"), F.col("j2").alias("nbr"), "freq", F.col("k").cast("long").alias("k"))


def _new_state(model: train.Model, new_entries: DataFrame, k: int) -> DataFrame:
    """Old state plus zero-bias, hashed-vector state of unknown ids."""
    ids = lambda ax: new_entries.select(ax).distinct()
    zero = (None, ids("i").withColumn("b", F.lit(0.0)), ids("j").withColumn("bh", F.lit(0.0)))
    fresh = train.init_state(new_entries, model.cfg, zero, k)
    return model.state.unionByName(fresh.join(model.state.select("side", "id"), ["side", "id"], "left_anti"))


def online_update(model: train.Model, new_entries: DataFrame, new_top: DataFrame | None = None, cfg: TrainConfig | None = None) -> train.Model:
    """Trains the biases and vectors of new rows against frozen columns, then everything of new columns against
    frozen rows. Parameters of ids known before are not touched."""
    cfg = cfg or model.cfg
    k = cfg.K if model.top is not None else 0
    old = model.state.select("side", "id")
    state = _new_state(model, new_entries, k)
    known = lambda s: old.where(F.col("side") == s).select("id")
    # new rows are fitted against columns that have been trained, never against fresh ones
    rows_only = new_entries.join(known("r"), new_entries["i"].cast("string") == F.col("id"), "left_anti")
    rows_only = rows_only.join(known("c"), rows_only["j"].cast("string") == F.col("id"), "left_semi")
    cols_only = new_entries.join(known("c"), new_entries["j"].cast("string") == F.col("id"), "left_anti")
    top, rated = model.top, model.rated
    if top is not None:
        if new_top is not None:
            top = top.select("j", "nbr", "k").unionByName(new_top.select("j", "nbr", "k"))
        rated = rated.select("i", "j", "r").unionByName(new_entries.select("i", "j", "r"))
    lay = lambda e: train.layout(e, cfg, top, model.means, rated)
    state, _ = train.fit(lay(rows_only), state, model.mu, cfg, k, freeze_cols=True)
    state, _ = train.fit(lay(cols_only), state, model.mu, cfg, k, freeze_rows=True)
    return train.Model(cfg, model.mu, state, model.types, top, model.means, rated, model.history)


def online_gap(full: train.Model, updated: train.Model, test: DataFrame) -> float:
    """RMSE increase of the updated model over training on everything."""
    return metrics.rmse(train.score(updated, test)) - metrics.rmse(train.score(full, test))


__all__ = ["merge_sums", "online_gap", "online_update", "search_new", "update_codes"]
