"""Interaction matrices (i, j, r) from the given tables, with their DuckDB forms."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lowrank_spark.functions.hashing import md5_byte, text


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _sold(spark, d):
    li = table(spark, d, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_quantity", "l_discount")
    return li.join(table(spark, d, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))


def _stars(x):
    return F.least(F.lit(5), 1 + F.floor((x - 1) / 10)).cast("double")


def cust_part(spark, d):
    return _sold(spark, d).groupBy(F.col("o_custkey").alias("i"), F.col("l_partkey").alias("j")).agg(_stars(F.max("l_quantity")).alias("r"))


def supp_part(spark, d):
    """Dealt by part once: what is summed by column afterwards needs no shuffle of its own."""
    li = table(spark, d, "lineitem").select("l_suppkey", "l_partkey", "l_quantity").repartition("l_partkey")
    return li.groupBy(F.col("l_suppkey").alias("i"), F.col("l_partkey").alias("j")).agg(_stars(F.max("l_quantity")).alias("r"))


def user_key(spark, d):
    e = table(spark, d, "events").select("user_id", F.get_json_object("props", "$.k").cast("long").alias("k"), "value", "ts")
    return e.groupBy(F.col("user_id").alias("i"), F.col("k").alias("j")).agg(F.least(F.lit(5), 1 + F.floor(F.max("value") / 40)).cast("double").alias("r"), F.max("ts").alias("ts"))


def term_counts(spark, d):
    """(w, doc_id, n) of words of two letters or more."""
    words = F.explode(F.split(F.lower("text"), "[^a-zà-öø-ÿ]+")).alias("w")
    t = table(spark, d, "documents").select("doc_id", words)
    return t.where(F.length("w") >= 2).groupBy("doc_id", "w").agg(F.count(F.lit(1)).alias("n"))


def term_doc(spark, d):
    """Term by document; terms in at least five documents. The vocabulary grows with the text: no broadcast is forced."""
    tf = term_counts(spark, d)
    vocab = tf.groupBy("w").agg(F.count(F.lit(1)).alias("df")).where("df >= 5").select("w")
    return tf.join(vocab, "w").select(F.col("w").alias("i"), F.col("doc_id").alias("j"), F.least(F.col("n"), F.lit(5)).cast("double").alias("r"))


def _shift(e):
    return F.when(e < 26, -1).when(e >= 230, 1).otherwise(0)


def planted(spark, d):
    s = _sold(spark, d).select(F.col("o_custkey").alias("i"), F.col("l_partkey").alias("j")).distinct()
    g = md5_byte(F.concat(F.lit("gi:"), (F.col("i") % 8).cast("string"), F.lit(":"), (F.col("j") % 10).cast("string")))
    e = md5_byte(text("e", F.col("i"), F.col("j")))
    return s.select("i", "j", F.greatest(F.lit(1), F.least(F.lit(5), 1 + g % 5 + _shift(e))).cast("double").alias("r"))


def dim_vec(spark, d):
    e = table(spark, d, "embeddings")
    return e.select(F.posexplode("embedding").alias("pos", "x"), "vec_id").select(F.col("pos").cast("long").alias("i"), F.col("vec_id").alias("j"), F.col("x").cast("double").alias("r"))


def discount(spark, d):
    top = F.max(F.round(F.col("l_discount") * 1000))
    return _sold(spark, d).groupBy(F.col("o_custkey").alias("i"), F.col("l_partkey").alias("j")).agg(F.when(top == 0, 0.5).otherwise(top.cast("double")).alias("r"))


def cust_brand(spark, d):
    p = table(spark, d, "part").select("p_partkey", "p_brand")
    s = _sold(spark, d).join(p, F.col("p_partkey") == F.col("l_partkey"))
    return s.groupBy(F.col("o_custkey").alias("i"), F.col("p_brand").alias("j")).agg(F.least(F.lit(5), F.count(F.lit(1))).cast("double").alias("r"))


def planted_groups(spark, d):
    s = _sold(spark, d).select(F.floor(F.col("o_custkey") / 10).cast("long").alias("i"), F.floor(F.col("l_partkey") / 5).cast("long").alias("j")).distinct()
    part = lambda c, n: (c % n).cast("string")
    kp, e = md5_byte(text("keep", F.col("i"), F.col("j"))), md5_byte(text("e", F.col("i"), F.col("j")))
    g = md5_byte(F.concat_ws(":", F.lit("g"), part(F.col("i"), 5), part(F.col("j"), 5), part(F.floor(F.col("j") / 5).cast("long"), 4)))
    s = s.where((F.col("i") % 5 == F.col("j") % 5) | (kp < 26))
    return s.select("i", "j", F.greatest(F.lit(1), F.least(F.lit(5), 1 + g % 5 + _shift(e))).cast("double").alias("r"))


WORKLOADS = {f.__name__: f for f in (cust_part, supp_part, user_key, term_doc, planted, dim_vec, discount, cust_brand, planted_groups)}


def load_interactions(spark: SparkSession, sf_dir: str, workload: str) -> DataFrame:
    return WORKLOADS[workload](spark, sf_dir)


_HB = lambda s: f"concat('0x', substr(md5({s}), 1, 2))::int"
_JOIN = "lineitem join orders on l_orderkey = o_orderkey"
_NOISE = "case when e < 26 then -1 when e >= 230 then 1 else 0 end"
DUCK = {
    "cust_part": f"select o_custkey as i, l_partkey as j, least(5, 1 + floor((max(l_quantity) - 1) / 10))::double as r from {_JOIN} group by o_custkey, l_partkey",
    "supp_part": "select l_suppkey as i, l_partkey as j, least(5, 1 + floor((max(l_quantity) - 1) / 10))::double as r from lineitem group by l_suppkey, l_partkey",
    "user_key": "select user_id as i, k as j, least(5, 1 + floor(max(value) / 40))::double as r, max(ts) as ts from (select user_id, json_extract_string(props, '$.k')::bigint as k, value, ts from events) group by user_id, k",
    "term_doc": "select tf.w as i, tf.doc_id as j, least(n, 5)::double as r from (select doc_id, w, count(*) as n from (select doc_id, unnest(string_split_regex(lower(text), '[^a-zà-öø-ÿ]+')) as w from documents) where length(w) >= 2 group by doc_id, w) tf"
    " join (select w from (select distinct doc_id, w from (select doc_id, unnest(string_split_regex(lower(text), '[^a-zà-öø-ÿ]+')) as w from documents) where length(w) >= 2) group by w having count(*) >= 5) v on tf.w = v.w",
    "planted": f"select i, j, greatest(1, least(5, 1 + (g % 5) + ({_NOISE})))::double as r from (select i, j, {_HB("concat('gi:', i % 8, ':', j % 10)")} as g, {_HB("concat('e:', i, ':', j)")} as e from (select distinct o_custkey as i, l_partkey as j from {_JOIN}))",
    "dim_vec": "select (generate_subscripts(embedding, 1) - 1)::bigint as i, vec_id as j, unnest(embedding)::double as r from embeddings",
    "discount": f"select o_custkey as i, l_partkey as j, case when max(round(l_discount * 1000)) = 0 then 0.5e0 else max(round(l_discount * 1000))::double end as r from {_JOIN} group by o_custkey, l_partkey",
    "cust_brand": f"select o_custkey as i, p_brand as j, least(5, count(*))::double as r from {_JOIN} join part on p_partkey = l_partkey group by o_custkey, p_brand",
    "planted_groups": f"select i, j, greatest(1, least(5, 1 + (g % 5) + ({_NOISE})))::double as r from (select i, j, {_HB("concat('keep:', i, ':', j)")} as kp, {_HB("concat('e:', i, ':', j)")} as e, {_HB("concat('g:', i % 5, ':', j % 5, ':', floor(j / 5)::bigint % 4)")} as g"
    f" from (select distinct floor(o_custkey / 10)::bigint as i, floor(l_partkey / 5)::bigint as j from {_JOIN})) where i % 5 = j % 5 or kp < 26",
}
