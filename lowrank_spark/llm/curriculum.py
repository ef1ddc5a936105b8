"""Mixing sources to target weights along a time-varying curriculum.

Each source gets a target number of words: its weight's part of all words, never above `cap` times what it has, the
excess shared among the rest by weight. A source offers its documents in a fixed pseudo-random order, again and
again, until the target is met. Its weight over training time is piecewise linear; the integral, scaled to the
target, is the cumulative demand, and inverting the demand at a copy's place in the offer gives the copy's training
position in [0, 1]. Documents are range-sorted by position.

A place in the offer is a prefix sum. It is formed in two levels, so no task sees a whole source: documents fall
into ordered buckets of about `BUCKET_ROWS` by their hash, bucket sums are added up within the source, and a window
runs inside one bucket.

Native: DataFrame functions only. Defined cases: null text has size 0; null source is a source of its own, after all
others; size-0 documents take 0 words; null doc_ids order as the empty string; repeated rows are offered one after
the other; an empty table gives an empty result; other columns do not matter.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from lowrank_spark.functions.staging import once
from lowrank_spark.llm.columns import shield, unshield
from lowrank_spark.llm.quality_rules import words_of
from lowrank_spark.runtime import Scratch, maybe_broadcast

WEIGHTS = (5, 2, 1)
CAP = 3
BUCKET_ROWS = 4096
#: Relative weight at the knots 0, 1/2 and 1 of training time, by place in WEIGHTS: early, steady and late sources.
KNOTS = (0.0, 0.5, 1.0)
SCHEDULES = ((1.5, 1.0, 0.5), (1.0, 1.0, 1.0), (0.5, 1.0, 1.5))


def order_key(doc_id: Column, text: Column) -> Column:
    return F.md5(F.concat(F.coalesce(doc_id.cast("string"), F.lit("")), F.lit(":"), F.md5(F.coalesce(text, F.lit("")))))


def _bucket(key: Column, n: Column) -> Column:
    """Bucket of a hex key among n, in the key's order."""
    return F.floor(F.conv(F.substring(key, 1, 8), 16, 10).cast("double") * n / F.lit(float(1 << 32))).cast("long")


def source_plan(sized: DataFrame, weights: tuple = WEIGHTS, cap: int = CAP, schedules: tuple = SCHEDULES, knots: tuple = KNOTS) -> DataFrame:
    """One row a source: source_size, weight, target, full passes and the words of the last partial pass, segments.

    The windows below run over one row a source.
    """
    s = sized.groupBy("source").agg(F.sum("size").alias("source_size"), F.count(F.lit(1)).alias("n_docs"))
    place = (F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1) % len(weights)
    s = s.withColumn("_k", place).withColumn("weight", F.element_at(F.array(*[F.lit(w) for w in weights]), (F.col("_k") + 1).cast("int")).cast("long"))
    every = Window.partitionBy()
    by_fill = Window.orderBy((F.col("source_size") / F.col("weight")).asc(), F.col("source").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, -1)
    s = s.withColumns(
        {
            "_T": F.sum("source_size").over(every),
            "_W": F.sum("weight").over(every),
            "_c": cap * F.col("source_size"),
            "_pc": F.coalesce(F.sum(cap * F.col("source_size")).over(by_fill), F.lit(0)),
            "_pw": F.coalesce(F.sum("weight").over(by_fill), F.lit(0)),
        }
    )
    s = s.withColumn("_full", (F.col("_T") - F.col("_pc")) * F.col("weight") >= F.col("_c") * (F.col("_W") - F.col("_pw")))
    s = s.withColumns({"_sc": F.sum(F.when(F.col("_full"), F.col("_c")).otherwise(0)).over(every), "_sw": F.sum(F.when(F.col("_full"), F.col("weight")).otherwise(0)).over(every)})
    free = F.col("weight") * ((F.col("_T") - F.col("_sc")).cast("double") / F.nullif(F.col("_W") - F.col("_sw"), F.lit(0)))
    s = s.withColumn("target", F.when(F.col("_full"), F.col("_c").cast("double")).otherwise(free))
    passes = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0)
    s = s.withColumn("passes", passes.cast("long")).withColumn("part", F.col("target") - F.col("passes") * F.col("source_size"))
    segs = F.array(*[_segments(knots, w) for w in schedules])
    return s.select("source", "source_size", "n_docs", "weight", "target", "passes", "part", F.ceil(F.col("n_docs") / BUCKET_ROWS).cast("long").alias("n_buckets"), F.element_at(segs, (F.col("_k") + 1).cast("int")).alias("segments"))


def _segments(knots: tuple, w: tuple) -> Column:
    """Pieces of a schedule: start, length, weight at both ends, area before; scaled to area 1."""
    area = [(knots[i + 1] - knots[i]) * (w[i] + w[i + 1]) / 2 for i in range(len(knots) - 1)]
    out, before, total = [], 0.0, sum(area)
    for i, a in enumerate(area):
        vals = {"t": knots[i], "d": knots[i + 1] - knots[i], "w0": w[i] / total, "w1": w[i + 1] / total, "before": before}
        out.append(F.struct(*[F.lit(float(v)).alias(k) for k, v in vals.items()]))
        before += a / total
    return F.array(*out)


def demand_inverse(q: Column, segments: Column) -> Column:
    """Time at which the share q of the demand is met."""
    seg = F.coalesce(F.element_at(F.filter(segments, lambda s: s["before"] <= q), -1), F.element_at(segments, 1))
    y = q - seg["before"]
    slope = (seg["w1"] - seg["w0"]) / seg["d"]
    root = F.sqrt(F.greatest(seg["w0"] * seg["w0"] + 2 * slope * y, F.lit(0.0)))
    x = F.when(y <= 0, 0.0).otherwise(2 * y / (seg["w0"] + root))
    return F.least(F.lit(1.0), seg["t"] + x)


def mix(docs: DataFrame, carry: list[str] = ("doc_id",), text_col: str = "text", source_col: str = "source", id_col: str = "doc_id", **plan_options) -> DataFrame:
    """carry + size, source_size, target, taken, n_copies, places (training position of each copy)."""
    spark = docs.sparkSession
    scratch = Scratch(spark, "mix")
    d = docs.select(*[F.col(c).alias(f"c_{c}") for c in carry], F.col(source_col).alias("source"), F.col(text_col).alias("_text"), F.col(id_col).alias("_id"))
    d = once(d, {"size": F.size(words_of(F.coalesce("_text", F.lit("")))).cast("long"), "key": order_key(F.col("_id"), F.col("_text"))}, [*[f"c_{c}" for c in carry], "source"])
    slim = scratch.keep(d.select("source", "size", "key"))
    plan = scratch.keep(source_plan(slim, **plan_options))
    n_sources = plan.count()
    plan_b = maybe_broadcast(plan, n_sources, 400)
    same = lambda a, b: a["source"].eqNullSafe(b["source"])
    with_bucket = lambda x: x.join(plan_b, same(x, plan_b), "left").drop(plan_b["source"]).withColumn("bucket", _bucket(F.col("key"), F.col("n_buckets")))
    sums = with_bucket(slim).groupBy("source", "bucket").agg(F.sum("size").alias("n"))
    before = F.coalesce(F.sum("n").over(Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    offsets = scratch.keep(sums.select("source", "bucket", before.alias("offset")))
    offsets = maybe_broadcast(offsets, offsets.count(), 64)
    d = with_bucket(d)
    w = Window.partitionBy("source", "bucket").orderBy("key").rowsBetween(Window.unboundedPreceding, 0)
    d = d.withColumn("_to", F.sum("size").over(w))
    d = d.join(offsets, same(d, offsets) & (d["bucket"] == offsets["bucket"]), "left").drop(offsets["source"]).drop(offsets["bucket"])
    mid = F.col("offset") + F.col("_to") - F.col("size") / 2
    d = d.withColumn("_mid", mid).withColumn("n_copies", (F.col("passes") + F.when((F.col("size") > 0) & (F.col("_mid") <= F.col("part")), 1).otherwise(0)).cast("int"))
    d = d.withColumn("taken", F.col("size") * F.col("n_copies"))
    at = F.transform(F.sequence(F.lit(0), F.col("n_copies") - 1), lambda m: demand_inverse((m * F.col("source_size") + F.col("_mid")) / F.col("target"), F.col("segments")))
    d = d.withColumn("places", F.when((F.col("n_copies") > 0) & (F.col("target") > 0), at).otherwise(F.array().cast("array<double>")))
    return d.select(*[F.col(f"c_{c}").alias(c) for c in carry], "size", "source_size", "target", "taken", "n_copies", "places")


def training_order(mixed: DataFrame) -> DataFrame:
    """One row a taken copy, range-sorted by position over all partitions."""
    out = mixed.select(*[c for c in mixed.columns if c != "places"], F.posexplode("places").alias("copy", "position"))
    return out.orderBy("position", "copy")


def mixing_stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The taken copies in training order, with the columns of documents."""
    d = shield(docs, ("doc_id", "text", "source"))
    return unshield(training_order(mix(d, carry=list(d.columns))), docs)


def op8_mixing(spark, sf_dir: str) -> DataFrame:
    d = mix(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "source"))
    first = F.try_element_at("places", F.lit(1))
    return d.select("doc_id", "size", "source_size", "target", "taken", "n_copies", F.round(first, 6).alias("first_position")).orderBy("first_position", "doc_id")


SQL = rf"""
with d as (select doc_id, source, len(list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> ''))::bigint as size,
             md5(concat(coalesce(doc_id::varchar, ''), ':', md5(coalesce(text, '')))) as key from documents),
g as (select source, sum(size)::bigint as source_size from d group by source),
k as (select *, (row_number() over (order by source nulls last) - 1) % 3 as k from g),
s as (select *, case k when 0 then {WEIGHTS[0]} when 1 then {WEIGHTS[1]} else {WEIGHTS[2]} end as weight from k),
c as (select *, sum(source_size) over () as t_all, sum(weight) over () as w_all, {CAP} * source_size as cap,
        coalesce(sum({CAP} * source_size) over f, 0) as pc, coalesce(sum(weight) over f, 0) as pw
      from s window f as (order by source_size / weight, source nulls last rows between unbounded preceding and 1 preceding)),
f as (select *, (t_all - pc) * weight >= cap * (w_all - pw) as sat from c),
e as (select *, sum(case when sat then cap else 0 end) over () as sc, sum(case when sat then weight else 0 end) over () as sw from f),
p as (select source, source_size, k, case when sat then cap::double else weight * ((t_all - sc)::double / nullif(w_all - sw, 0)) end as target from e),
q as (select *, case when source_size > 0 then floor(target / source_size)::bigint else 0 end as passes from p),
m as (select d.doc_id, d.size, q.source_size, q.target, q.passes, q.k, q.target - q.passes * q.source_size as part,
        sum(d.size) over (partition by d.source order by d.key rows unbounded preceding) - d.size / 2 as mid
      from d join q on d.source is not distinct from q.source),
n as (select *, passes + case when size > 0 and mid <= part then 1 else 0 end as copies, mid / target as y from m),
z as (select *, case k when 0 then 1.5e0 when 1 then 1e0 else 0.5e0 end as a0, case k when 0 then -1e0 when 1 then 0e0 else 1e0 end as sl from n)
select doc_id, size, source_size, target, (size * copies)::bigint as taken, copies::int as n_copies,
  case when copies > 0 then round(least(1e0, 2 * y / (a0 + sqrt(greatest(a0 * a0 + 2 * sl * y, 0e0)))), 6) end as first_position from z
"""
