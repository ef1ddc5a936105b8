"""Structured Streaming forms over the events table: hash sums, windows, joins, state.

Every query reads the events as a file stream with availableNow and writes what the sink receives to the shared
scratch folder; the last complete result (or the last update of each key) is returned as a table, so a stream can be
compared with its batch form.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from lowrank_spark.config import HashConfig
from lowrank_spark.operators import signhash
from lowrank_spark.runtime import Scratch

DELAY = "1 day"


def events_stream(spark: SparkSession, sf_dir: str, delay: str | None = DELAY) -> DataFrame:
    """The events in arrival order, with event time as a timestamp and a watermark."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    e = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").option("maxFilesPerTrigger", 1).parquet(sf_dir)
    e = e.withColumn("ts", F.col("ts").cast("timestamp"))
    return e.withWatermark("ts", delay) if delay else e


def run(df: DataFrame, mode: str, keys: list[str] | None = None) -> DataFrame:
    """Runs the stream to the end of its input. complete: the last batch; update: the last row of each key; append: all."""
    spark = df.sparkSession
    base = Scratch(spark, "stream").base
    schema = df.schema

    def sink(batch: DataFrame, n: int) -> None:
        # a batch that is run again after a failure replaces its own folder
        batch.withColumn("_n", F.lit(n)).write.mode("overwrite").parquet(f"{base}/out/batch={n}")

    q = df.writeStream.outputMode(mode).foreachBatch(sink).option("checkpointLocation", f"{base}/checkpoint").trigger(availableNow=True).start()
    q.awaitTermination()
    out = spark.read.schema(T.StructType([*schema.fields, T.StructField("_n", T.IntegerType())])).parquet(f"{base}/out/batch=*")
    if mode == "complete":
        last = out.agg(F.max("_n").alias("m"))
        return out.join(F.broadcast(last), F.col("_n") == F.col("m")).drop("_n", "m")
    if mode == "update":
        names = [c for c in out.columns if c not in ("_n", *keys)]
        return out.groupBy(*keys).agg(F.max_by(F.struct(*names), "_n").alias("v")).select(*keys, "v.*")
    return out.drop("_n")


def hash_stream(entries: DataFrame, cfg: HashConfig) -> DataFrame:
    """Running sign sums of a stream of entries (i, j, r): the sums commute, so late or reordered entries change nothing."""
    return signhash.accumulate(entries, cfg)


def upsert_stream(entries: DataFrame, apply: Callable[[DataFrame, int], None], checkpoint: str):
    """A stream of new entries handed to an online update, one micro-batch at a time, exactly once per batch id."""
    return entries.writeStream.foreachBatch(apply).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def _entries(e: DataFrame) -> DataFrame:
    return e.select(F.col("user_id").alias("i"), F.get_json_object("props", "$.k").cast("long").alias("j"), F.least(F.lit(5), 1 + F.floor(F.col("value") / 40)).cast("double").alias("r"))


def stream_sums(s, d):
    return run(hash_stream(_entries(events_stream(s, d, None)), HashConfig(p=1, q=2)), "complete")


def _counts(e, window):
    return e.groupBy(window.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))


def _named(df):
    return df.select(F.date_format("w.start", "yyyy-MM-dd HH:mm").alias("start"), *[c for c in df.columns if c != "w"])


def stream_tumbling(s, d):
    return _named(run(_counts(events_stream(s, d), F.window("ts", "1 hour")), "update", ["w", "event_type"]))


def stream_sliding(s, d):
    return _named(run(_counts(events_stream(s, d), F.window("ts", "2 hours", "1 hour")), "update", ["w", "event_type"]))


def stream_session(s, d):
    e = events_stream(s, d).groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return _named(run(e, "complete"))


def stream_dedup(s, d):
    e = events_stream(s, d)
    twice = e.union(e)
    return run(twice.dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "event_type"), "append")


def stream_static_join(s, d):
    c = s.read.parquet(f"{d}/customer.parquet").select("c_custkey", "c_mktsegment")
    e = events_stream(s, d).join(c, F.col("user_id") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n"))
    return run(e, "complete")


def stream_interval_join(s, d):
    e = events_stream(s, d)
    a = e.where("event_type = 'click'").select(F.col("event_id").alias("e1"), F.col("user_id").alias("u1"), F.col("ts").alias("t1"))
    b = events_stream(s, d).where("event_type = 'purchase'").select(F.col("event_id").alias("e2"), F.col("user_id").alias("u2"), F.col("ts").alias("t2"))
    j = a.join(b, F.expr("u1 = u2 and t2 > t1 and t2 <= t1 + interval 6 hours"))
    return run(j.select("e1", "e2"), "append")


def stream_state(s, d):
    """Custom state per user: how many events, and the largest value so far."""

    def step(key, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n, top = state.get if state.exists else (0, 0.0)
        for b in batches:
            n, top = n + len(b), max(top, float(b["value"].max()))
        state.update((n, top))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "top": [top]})

    e = events_stream(s, d, None).groupBy("user_id").applyInPandasWithState(step, "user_id long, n long, top double", "n long, top double", "update", "NoTimeout")
    return run(e, "update", ["user_id"])


def _lane(g: int) -> str:
    return f"sum(case when (b >> {g}) & 1 = 1 then r * r else -r * r end) as s{g}"


_ENT = "select user_id as i, json_extract_string(props, '$.k')::bigint as j, least(5, 1 + floor(value / 40))::double as r from events"
_SUMS = f"select j, rep, {', '.join(_lane(g) for g in range(8))} from (select j, rep, r, concat('0x', substr(md5(concat('7:', i, ':', rep // 16)), (2 * (rep % 16) + 1)::bigint, 2))::bigint as b from ({_ENT}), range(2) t(rep)) group by j, rep"
_FMT = "strftime({}, '%Y-%m-%d %H:%M') as start"


def entries() -> list:
    hour = "date_trunc('hour', ts)"
    tumbling = f"select {_FMT.format(hour)}, event_type, count(*) as n from events group by {hour}, event_type"
    return [
        ("stream_sums", stream_sums, _SUMS),
        ("stream_tumbling", stream_tumbling, tumbling),
        ("stream_session", stream_session, f"select {_FMT.format('min(ts)')}, user_id, count(*) as n from (select *, sum(fresh) over (partition by user_id order by ts, event_id rows unbounded preceding) as g from (select *, case when ts - lag(ts) over (partition by user_id order by ts, event_id) < interval 30 minute then 0 else 1 end as fresh from events)) group by user_id, g"),
        ("op_stream_tumbling", stream_tumbling, tumbling),
        ("op_stream_sliding", stream_sliding, f"select {_FMT.format('h')}, event_type, count(*) as n from (select event_type, unnest([{hour}, {hour} - interval 1 hour]) as h from events) group by h, event_type"),
        ("op_stream_session", stream_session, None),
        ("op_stream_dedup", stream_dedup, "select event_id, event_type from events"),
        ("op_stream_static_join", stream_static_join, "select c_mktsegment, count(*) as n from events join customer on user_id = c_custkey group by 1"),
        ("op_stream_interval_join", stream_interval_join, "select a.event_id as e1, b.event_id as e2 from events a join events b on a.user_id = b.user_id and b.ts > a.ts and b.ts <= a.ts + interval 6 hour where a.event_type = 'click' and b.event_type = 'purchase'"),
        ("op_stream_late", stream_tumbling, tumbling),
        ("op_stream_state", stream_state, "select user_id, count(*) as n, max(value) as top from events group by 1"),
    ]
