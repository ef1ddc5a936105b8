"""AND/OR banding of codes and the hashed top-K search.

p codes must agree for two columns to meet in a group (AND); meeting in any of q groups makes them candidates (OR);
the K columns met most often are the neighbours; columns with fewer get hashed random ones.
"""

from __future__ import annotations

import math
from itertools import combinations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from lowrank_spark.config import HashConfig
from lowrank_spark.functions.blocks import dealt_sides
from lowrank_spark.functions.hashing import md5_int, text
from lowrank_spark.operators import signhash
from lowrank_spark.runtime import Scratch, ship_package

#: Groups up to which the top-K search goes by sets of groups (2^groups - 1 of them) instead of pairs.
FEW_GROUPS = 6
#: Columns that a task of `topk_by_blocks` holds of either side.
COLUMN_BLOCK = 1 << 16
#: Bytes of a pair on its way to the sum of its meetings.
PAIR_BYTES = 24


def keys(code_rows: DataFrame, p: int, g: int = 8) -> DataFrame:
    """(grp, key, j): p codes as one number, or a 64-bit hash of them where they need more than 62 bits."""
    x = code_rows.select("j", F.floor(F.col("rep") / p).cast("long").alias("grp"), (F.col("rep") % p).alias("at"), "code")
    if p * g <= 62:
        key = F.sum(F.col("code") * F.pow(F.lit(2.0), F.col("at") * g).cast("long"))
    else:
        key = F.xxhash64(F.transform(F.array_sort(F.collect_list(F.struct("at", "code"))), lambda s: s["code"]))
    return x.groupBy("j", "grp").agg(key.cast("long").alias("key")).select("grp", "key", "j")


def oversized(key_rows: DataFrame, max_bucket: int) -> DataFrame:
    """One row: buckets above the bound, and the pairs in them."""
    n = key_rows.groupBy("grp", "key").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > max_bucket)
    return n.agg(F.count(F.lit(1)).alias("buckets"), F.coalesce(F.sum(F.col("n") * (F.col("n") - 1) / 2), F.lit(0.0)).cast("long").alias("pairs"))


def pairs(key_rows: DataFrame, max_bucket: int | None = None) -> DataFrame:
    """(j1, j2, freq), j1 < j2: in how many groups two columns meet. Buckets above max_bucket are joined block by block."""
    x, y, on = dealt_sides(key_rows.select("grp", "key", "j"), ["grp", "key"], "j", max_bucket)
    a, b = x.withColumnRenamed("j", "j1"), y.withColumnRenamed("j", "j2")
    return a.join(b, on).where("j1 < j2").groupBy("j1", "j2").agg(F.count(F.lit(1)).alias("freq"))


def topk(pair_rows: DataFrame, k: int) -> DataFrame:
    """(j, nbr, freq, k): the k partners met most often; ties by partner."""
    both = pair_rows.select(F.col("j1").alias("j"), F.col("j2").alias("nbr"), "freq").union(pair_rows.select(F.col("j2"), F.col("j1"), "freq"))
    w = Window.partitionBy("j").orderBy(F.col("freq").desc(), "nbr")
    return both.withColumn("k", F.row_number().over(w)).where(F.col("k") <= k).select("j", "nbr", "freq", F.col("k").cast("long").alias("k"))


def topk_few_groups(key_rows: DataFrame, k: int, groups: int) -> DataFrame:
    """What topk(pairs(key_rows), k) gives, without the pairs; for few groups, whose buckets are large.

    Take a partner nbr of j that meets j in exactly the set S of groups. All columns that share j's keys in S meet j at
    least as often, so if k of them were smaller than nbr, nbr would not be among the k best. Hence the k + 1 smallest
    columns of the bucket of every set S hold all partners that count. Sets are taken from the largest down, for columns
    that have fewer than k partners yet; a pair comes up in one set only.
    """
    scratch = Scratch(key_rows.sparkSession, "few")
    names = [f"g{g}" for g in range(groups)]
    cols = key_rows.groupBy("j").agg(*[F.max(F.when(F.col("grp") == g, F.col("key"))).alias(n) for g, n in enumerate(names)])
    cols = scratch.keep(cols)
    every, found, todo = F.struct("j", *names), None, cols
    low = Window.partitionBy("s", "at").orderBy("j")
    for m in range(groups, 0, -1):
        sets = list(combinations(range(groups), m))
        one = lambda i, s: F.struct(F.lit(i).alias("s"), F.array(*[F.col(names[g]) for g in s]).alias("at"))  # noqa: B023, E731
        places = lambda d, v: d.select(v, F.inline(F.array(*[one(i, s) for i, s in enumerate(sets)]))).where("not exists(at, x -> x is null)")  # noqa: B023, E731
        first = places(cols, every.alias("b")).select("b.*", "s", "at").withColumn("n", F.row_number().over(low)).where(F.col("n") <= k + 1)
        first = first.groupBy("s", "at").agg(F.collect_list(every).alias("bs")).where(F.size("bs") > 1)
        c = places(todo, every.alias("a")).join(first, ["s", "at"]).select("a", F.explode("bs").alias("b"))
        agree = sum((F.coalesce((F.col(f"a.{n}") == F.col(f"b.{n}")).cast("int"), F.lit(0)) for n in names), F.lit(0))
        c = c.where((F.col("a.j") != F.col("b.j")) & (agree == m)).select(F.col("a.j").alias("j"), F.col("b.j").alias("nbr"), F.lit(m).cast("long").alias("freq"))
        w = Window.partitionBy("j").orderBy("nbr")
        c = scratch.keep(c.withColumn("n", F.row_number().over(w)).where(F.col("n") <= k).drop("n"))
        found = c if found is None else found.union(c)
        if m > 1:
            full = found.groupBy("j").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= k).select("j")
            todo = scratch.keep(cols.join(full, "j", "left_anti"))
            if todo.limit(1).count() == 0:
                break
    w = Window.partitionBy("j").orderBy(F.col("freq").desc(), "nbr")
    return found.withColumn("k", F.row_number().over(w)).where(F.col("k") <= k).select("j", "nbr", "freq", F.col("k").cast("long").alias("k"))


def best_partners(a_keys: np.ndarray, a_has: np.ndarray, b_keys: np.ndarray, b_has: np.ndarray, own: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(place in a, place in b, meetings): for every column of a the k of b met most often, ties by place in b.

    Keys are columns x groups, `has` says which are there; own is a column's own place in b, or -1.
    """
    n, groups = a_keys.shape
    members, lo, hi = [], np.zeros((n, groups), np.int64), np.zeros((n, groups), np.int64)
    for g in range(groups):
        there = np.flatnonzero(b_has[:, g])
        order = there[np.argsort(b_keys[there, g], kind="stable")]
        members.append(order)
        key = b_keys[order, g]
        lo[:, g] = np.searchsorted(key, a_keys[:, g], "left")
        hi[:, g] = np.where(a_has[:, g], np.searchsorted(key, a_keys[:, g], "right"), lo[:, g])
    out_a, out_b, out_n = [], [], []
    for x in range(n):
        met = np.bincount(np.concatenate([m[s:e] for m, s, e in zip(members, lo[x].tolist(), hi[x].tolist(), strict=True)]), minlength=len(b_keys))
        if own[x] >= 0:
            met[own[x]] = 0
        least = int(met.max()) if len(met) else 0
        while least > 1 and np.count_nonzero(met >= least) < k:
            least -= 1
        if least < 1:
            continue
        best = np.flatnonzero(met >= least)
        best = best[np.argsort(-met[best], kind="stable")[:k]]
        out_a.append(np.full(len(best), x))
        out_b.append(best)
        out_n.append(met[best])
    return tuple(np.concatenate(o) if o else np.zeros(0, np.int64) for o in (out_a, out_b, out_n))


def _key_matrix(t: pa.Table, groups: int) -> tuple[np.ndarray, np.ndarray]:
    flat = t.column("ks").combine_chunks().flatten()
    has = pc.is_valid(flat).to_numpy(zero_copy_only=False).reshape(-1, groups)
    return pc.fill_null(flat, 0).to_numpy(zero_copy_only=False).reshape(-1, groups), has


def topk_by_blocks(key_rows: DataFrame, k: int, groups: int, block: int = COLUMN_BLOCK) -> DataFrame:
    """What topk(pairs(key_rows), k) gives, without the pairs: every block of columns is counted against every other one.

    A task counts one column's meetings at a time and hands on the k best of its block, so what is shuffled is the keys, once
    a block, and k rows a column and block.
    """
    spark = key_rows.sparkSession
    ship_package(spark)
    scratch = Scratch(spark, "blocks")
    one = [F.max(F.when(F.col("grp") == g, F.col("key"))) for g in range(groups)]
    cols = scratch.keep(key_rows.where(F.col("j").isNotNull()).groupBy("j").agg(F.array(*one).alias("ks")))
    n = max(1, -(-cols.count() // block))
    mine, every = F.pmod(F.xxhash64("j"), F.lit(n)).cast("int"), F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    a = cols.select("j", "ks", mine.alias("x")).withColumn("y", every)
    b = cols.select("j", "ks", mine.alias("y")).withColumn("x", every)

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        kind = left.schema.field("j").type
        right = right.take(pc.sort_indices(right.column("j")))
        theirs = right.column("j").combine_chunks()
        own = pc.fill_null(pc.index_in(left.column("j"), value_set=theirs), -1).to_numpy()
        at, nbr, freq = best_partners(*_key_matrix(left, groups), *_key_matrix(right, groups), own, k)
        return pa.table({"j": left.column("j").combine_chunks().take(pa.array(at)).cast(kind), "nbr": theirs.take(pa.array(nbr)).cast(kind), "freq": pa.array(freq, pa.int64())})

    jt = cols.schema["j"].dataType.simpleString()
    # a partition a pair of blocks: few bytes, but long to count
    parts = min(4096, n * n)
    a, b = (d.repartition(parts, "x", "y") for d in (a, b))
    part = a.groupBy("x", "y").cogroup(b.groupBy("x", "y")).applyInArrow(run, f"j {jt}, nbr {jt}, freq bigint")
    w = Window.partitionBy("j").orderBy(F.col("freq").desc(), "nbr")
    return scratch.keep(part).withColumn("k", F.row_number().over(w)).where(F.col("k") <= k).select("j", "nbr", "freq", F.col("k").cast("long").alias("k"))


def topk_of_keys(key_rows: DataFrame, k: int, groups: int, max_bucket: int | None = None) -> DataFrame:
    """topk(pairs(key_rows), k), by whichever form moves fewer bytes: the pairs of all buckets, or the keys block against block."""
    met = key_rows.groupBy("grp", "key").agg(F.count(F.lit(1)).alias("n")).agg(F.sum(F.col("n").cast("double") * (F.col("n") - 1) / 2).alias("pairs"), F.sum("n").alias("n")).first()
    columns = (met["n"] or 0) / max(1, groups)
    if (met["pairs"] or 0) * PAIR_BYTES <= 2 * columns * max(1, math.ceil(columns / COLUMN_BLOCK)) * 8 * groups:
        return topk(pairs(key_rows, max_bucket), k)
    return topk_by_blocks(key_rows, k, groups)


def prime_from(n: int) -> int:
    """The smallest prime that is at least n (and 2)."""
    p = max(2, n)
    while any(p % f == 0 for f in range(2, math.isqrt(p) + 1)):
        p += 1
    return p


def fill_random(top: DataFrame, universe: DataFrame, k: int, seed: int = 7) -> DataFrame:
    """top completed to k neighbours a column, or to all others where there are fewer.

    universe: (j, id) with dense ids below n. Column j walks the ids in an order of its own: from a hashed start by a
    hashed step modulo the smallest prime from n on, which comes past every id once. k + 1 steps and one for each number
    that is no id are enough, whatever the column already has. No random order, no per-row random access: one equi-join.
    """
    top = Scratch(top.sparkSession, "top").keep(top.select("j", "nbr", "freq", "k"))
    n = universe.count()
    p = prime_from(n)
    have = top.groupBy("j").agg(F.count(F.lit(1)).alias("have"))
    need = universe.select("j").join(have, "j", "left").select("j", F.coalesce("have", F.lit(0)).alias("have")).where(F.col("have") < k)
    draw = lambda what, m: md5_int(text("fill", seed, F.col("j"), what), 14) % m
    need = need.select("j", "have", draw("start", p).alias("at"), (draw("step", max(1, p - 1)) + 1).alias("by"))
    c = need.select("j", "have", "at", "by", F.explode(F.sequence(F.lit(0), F.lit(min(p - 1, k + p - n)))).alias("t"))
    c = c.select("j", "have", "t", ((F.col("at") + F.col("t").cast("long") * F.col("by")) % p).alias("id")).where(F.col("id") < n)
    c = c.join(universe.select(F.col("j").alias("nbr"), "id"), "id").where(F.col("nbr") != F.col("j"))
    c = c.join(top.select("j", "nbr"), ["j", "nbr"], "left_anti")
    w = Window.partitionBy("j").orderBy("t")
    c = c.withColumn("k", F.row_number().over(w) + F.col("have")).where(F.col("k") <= k)
    return top.select("j", "nbr", "freq", "k").union(c.select("j", "nbr", F.lit(0).cast("long").alias("freq"), F.col("k").cast("long").alias("k")))


def universe_of(im: DataFrame) -> DataFrame:
    from lowrank_spark.sources.prep import index_ids

    return index_ids(im, "j").select("j", "id")


def search_codes(code_rows: DataFrame, cfg: HashConfig) -> DataFrame:
    kept = Scratch(code_rows.sparkSession, "band").keep(keys(code_rows, cfg.p, cfg.G))
    if cfg.q <= FEW_GROUPS:
        return topk_few_groups(kept, cfg.K, cfg.q)
    return topk_of_keys(kept, cfg.K, cfg.q, cfg.max_bucket)


def band_search(im: DataFrame, cfg: HashConfig, fill: str = "random") -> DataFrame:
    """(j, nbr, freq, k): hashed top-K neighbours of every column. fill: random, none or popular."""
    top = search_codes(signhash.code_table(im, cfg), cfg)
    if fill == "random":
        return fill_random(top, universe_of(im), cfg.K, cfg.seed)
    if fill == "popular":
        return fill_popular(top, im, cfg.K)
    return top


def fill_popular(top: DataFrame, im: DataFrame, k: int) -> DataFrame:
    """Missing neighbours are the columns with most entries (2k + 1 of them are enough)."""
    top = Scratch(top.sparkSession, "top").keep(top.select("j", "nbr", "freq", "k"))
    size = Scratch(top.sparkSession, "sizes").keep(im.groupBy("j").agg(F.count(F.lit(1)).alias("d")))
    pop = size.orderBy(F.col("d").desc(), "j").limit(2 * k + 1).select(F.col("j").alias("nbr"), "d")
    have = top.groupBy("j").agg(F.count(F.lit(1)).alias("have"))
    need = size.select("j").join(have, "j", "left").select("j", F.coalesce("have", F.lit(0)).alias("have")).where(F.col("have") < k)
    c = need.crossJoin(F.broadcast(pop)).where(F.col("nbr") != F.col("j")).join(top.select("j", "nbr"), ["j", "nbr"], "left_anti")
    w = Window.partitionBy("j").orderBy(F.col("d").desc(), "nbr")
    c = c.withColumn("k", F.row_number().over(w) + F.col("have")).where(F.col("k") <= k)
    return top.select("j", "nbr", "freq", "k").union(c.select("j", "nbr", F.lit(0).cast("long"), F.col("k").cast("long")))
