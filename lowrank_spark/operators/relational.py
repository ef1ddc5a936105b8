"""Relational, scalar and reshaping operators over the given tables, each with its SQL form."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from lowrank_spark.runtime import Scratch, shared_dir

_ENTRIES: list = []


class Tables:
    """Lazy access to the tables of a folder: t.orders, t.lineitem, ..."""

    def __init__(self, spark: SparkSession, sf_dir: str):
        self.spark, self.dir = spark, sf_dir

    def __getattr__(self, name: str) -> DataFrame:
        return self.spark.read.parquet(f"{self.dir}/{name}.parquet")


def op(sql: str | None):
    def wrap(fn):
        _ENTRIES.append((fn.__name__, lambda s, d: fn(Tables(s, d)), sql))
        return fn

    return wrap


def entries() -> list:
    return list(_ENTRIES)


def _r(c, n: int = 6):
    return F.round(c, n)


def n_rows():
    return F.count(F.lit(1))


_ORD = "o_orderkey, o_custkey, o_orderstatus, round(o_totalprice, 2) as price"


# ---- scans, sinks, sources
def _orders(t):
    return t.orders.select("o_orderkey", "o_custkey", "o_orderstatus", _r("o_totalprice", 2).alias("price"))


@op(f"select {_ORD} from orders")
def op_scan_parquet(t):
    return _orders(t)


def _round_trip(t, fmt: str, **options):
    path = f"{Scratch(t.spark, fmt).base}/files"
    df = _orders(t)
    df.write.format(fmt).options(**options).save(path)
    return t.spark.read.format(fmt).options(**options).schema(df.schema).load(path)


@op(f"select {_ORD} from orders")
def op_scan_csv_roundtrip(t):
    return _round_trip(t, "csv", header="true")


@op(f"select {_ORD} from orders")
def op_scan_json_roundtrip(t):
    return _round_trip(t, "json")


@op(f"select {_ORD} from orders")
def op_scan_orc_roundtrip(t):
    return _round_trip(t, "orc")


@op("select o_orderpriority, count(*) as n from orders where o_orderpriority = '1-URGENT' group by o_orderpriority")
def op_sink_partitioned(t):
    path = f"{Scratch(t.spark, 'parts').base}/by_priority"
    t.orders.select("o_orderkey", "o_orderpriority").repartition("o_orderpriority").write.partitionBy("o_orderpriority").parquet(path)
    return t.spark.read.parquet(path).where("o_orderpriority = '1-URGENT'").groupBy("o_orderpriority").agg(n_rows().alias("n"))


@op(None)
def op_sink_bucketed(t):
    name = "lowrank_bucketed_orders_" + shared_dir(t.spark).replace("/", "_").replace(":", "_").replace("-", "_").replace(".", "_")[-40:]
    t.spark.sql(f"drop table if exists {name}")
    t.orders.select("o_orderkey", "o_custkey").write.bucketBy(8, "o_custkey").sortBy("o_custkey").format("parquet").option("path", f"{Scratch(t.spark, 'bucket').base}/orders").saveAsTable(name)
    return t.spark.table(name).groupBy("o_custkey").agg(n_rows().alias("n"))


@op("select o_custkey as i, o_orderkey as j, round(o_totalprice, 2) as r from orders")
def op_source_interactions(t):
    from lowrank_spark.sources.coo_source import register

    path = f"{Scratch(t.spark, 'coo').base}/text"
    t.orders.select(F.concat_ws("\t", "o_custkey", "o_orderkey", _r("o_totalprice", 2).cast("string")).alias("value")).write.text(path)
    register(t.spark)
    files = [r["p"] for r in t.spark.read.text(path).select(F.input_file_name().alias("p")).distinct().collect()]
    return t.spark.read.format("coo_text").option("paths", "\n".join(files)).load()


# ---- filters and projections
@op("select count(*) as n, round(sum(l_extendedprice), 2) as total from lineitem where l_shipdate >= timestamp '1995-01-01' and l_discount between 0.05 and 0.07 and l_quantity < 24")
def op_filter_pushdown(t):
    x = t.lineitem.where((F.col("l_shipdate") >= F.lit("1995-01-01").cast("timestamp_ntz")) & F.col("l_discount").between(0.05, 0.07) & (F.col("l_quantity") < 24))
    return x.agg(n_rows().alias("n"), _r(F.sum("l_extendedprice"), 2).alias("total"))


@op("select c_custkey, c_name from customer where c_mktsegment in ('BUILDING', 'AUTOMOBILE') and c_name like '%1' and c_acctbal is not null")
def op_filter_in_like_null(t):
    return t.customer.where(F.col("c_mktsegment").isin("BUILDING", "AUTOMOBILE") & F.col("c_name").like("%1") & F.col("c_acctbal").isNotNull()).select("c_custkey", "c_name")


@op("select l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount) * (1 + l_tax), 6) as charge, greatest(l_quantity, 10) as q from lineitem")
def op_project_expr(t):
    return t.lineitem.select("l_orderkey", "l_linenumber", _r(F.col("l_extendedprice") * (1 - F.col("l_discount")) * (1 + F.col("l_tax")), 6).alias("charge"), F.greatest("l_quantity", F.lit(10.0)).alias("q"))


# ---- joins
_J3 = "select c_mktsegment, count(*) as n, round(sum(l_quantity), 2) as q from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey group by c_mktsegment"


def _three(t, how: str):
    li, o, c = t.lineitem.select("l_orderkey", "l_quantity"), t.orders.select("o_orderkey", "o_custkey"), t.customer.select("c_custkey", "c_mktsegment")
    x = li.join(o.hint(how) if how else o, F.col("l_orderkey") == F.col("o_orderkey"))
    return x.join(c, F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(n_rows().alias("n"), _r(F.sum("l_quantity"), 2).alias("q"))


@op(_J3)
def op_join_inner_hash(t):
    return _three(t, "shuffle_hash")


@op(_J3)
def op_join_sortmerge(t):
    return _three(t, "merge")


@op("select n_name, count(*) as n from customer join nation on c_nationkey = n_nationkey group by n_name")
def op_join_broadcast(t):
    return t.customer.join(F.broadcast(t.nation), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(n_rows().alias("n"))


@op("select c_custkey, count(o_orderkey) as n from customer left join orders on c_custkey = o_custkey and o_orderstatus = 'F' group by c_custkey")
def op_join_left(t):
    o = t.orders.where("o_orderstatus = 'F'").select("o_custkey", "o_orderkey")
    return t.customer.join(o, F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))


@op("select coalesce(a.k, b.k) as k, coalesce(a.n, 0) as n_old, coalesce(b.n, 0) as n_new from (select l_suppkey as k, count(*) as n from lineitem where l_linenumber <= 1 group by 1) a full join (select l_suppkey as k, count(*) as n from lineitem where l_linenumber >= 6 group by 1) b on a.k = b.k")
def op_join_full_outer(t):
    one = lambda c, n: t.lineitem.where(c).groupBy(F.col("l_suppkey").alias("k")).agg(n_rows().alias(n))
    return one("l_linenumber <= 1", "n_old").join(one("l_linenumber >= 6", "n_new"), "k", "full").na.fill(0)


@op("select c_custkey from customer where exists (select 1 from orders where o_custkey = c_custkey and o_totalprice > 300000)")
def op_join_semi(t):
    return t.customer.join(t.orders.where("o_totalprice > 300000"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@op("select c_custkey from customer where not exists (select 1 from orders where o_custkey = c_custkey)")
def op_join_anti(t):
    return t.customer.join(t.orders, F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@op("select a.p_brand as b1, b.p_brand as b2, count(*) as n from (select distinct p_brand, p_size from part) a join (select distinct p_brand, p_size from part) b on a.p_size = b.p_size and a.p_brand < b.p_brand group by 1, 2")
def op_join_theta_pairs(t):
    x = t.part.select("p_brand", "p_size").distinct()
    y = x.select(F.col("p_brand").alias("b2"), "p_size")
    return x.join(y, "p_size").where("p_brand < b2").groupBy(F.col("p_brand").alias("b1"), "b2").agg(n_rows().alias("n"))


@op("select lo, count(*) as n from orders join (select unnest(range(0, 600000, 50000))::double as lo) r on o_totalprice >= lo and o_totalprice < lo + 50000 group by lo")
def op_join_range_bins(t):
    """A range join as an equality on the bin number, with the range as a residual."""
    bins = t.spark.range(0, 600000, 50000).select(F.col("id").cast("double").alias("lo"), (F.col("id") / 50000).cast("long").alias("bin"))
    o = t.orders.select("o_totalprice", F.floor(F.col("o_totalprice") / 50000).cast("long").alias("bin"))
    return o.join(bins, "bin").where("o_totalprice >= lo and o_totalprice < lo + 50000").groupBy("lo").agg(n_rows().alias("n"))


@op("select a.s_suppkey as s1, b.s_suppkey as s2 from supplier a join supplier b on a.s_nationkey = b.s_nationkey and a.s_suppkey < b.s_suppkey")
def op_join_self(t):
    s = t.supplier.select("s_suppkey", "s_nationkey")
    return s.select(F.col("s_suppkey").alias("s1"), "s_nationkey").join(s.select(F.col("s_suppkey").alias("s2"), "s_nationkey"), "s_nationkey").where("s1 < s2").select("s1", "s2")


@op("select r_name, n_name from region cross join nation")
def op_join_cross_small(t):
    """Both sides have a fixed size."""
    return t.region.select("r_name").crossJoin(F.broadcast(t.nation.select("n_name")))


@op("select count(*) as n from (select nullif(l_linenumber, 3) as k from lineitem) a join (select distinct nullif(l_linenumber, 3) as k from lineitem) b on a.k is not distinct from b.k")
def op_join_nullsafe(t):
    k = F.nullif(F.col("l_linenumber"), F.lit(3))
    a = t.lineitem.select(k.alias("k"))
    b = t.lineitem.select(k.alias("m")).distinct()
    return a.join(b, a["k"].eqNullSafe(b["m"])).agg(n_rows().alias("n"))


_TS = "strftime({c}, '%Y-%m-%d %H:%M:%S')"


@op(f"select e.event_id, coalesce(max(p.event_id), -1) as last_purchase from events e left join (select *, row_number() over (partition by user_id order by ts, event_id) as rn from events where event_type = 'purchase') p on p.user_id = e.user_id and p.ts <= e.ts and not exists (select 1 from events q where q.event_type = 'purchase' and q.user_id = e.user_id and q.ts <= e.ts and (q.ts > p.ts or (q.ts = p.ts and q.event_id > p.event_id))) group by e.event_id")
def op_join_asof(t):
    """As-of join in one pass: both sides in one stream per user, the last purchase carried forward."""
    e = t.events.select("event_id", "user_id", "ts", F.when(F.col("event_type") == "purchase", F.col("event_id")).alias("p"))
    w = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, 0)
    best = F.max(F.when(F.col("p").isNotNull(), F.struct("ts", "p"))).over(w)
    return e.select("event_id", F.coalesce(best["p"], F.lit(-1)).alias("last_purchase"))


@op("select a.event_id as e1, count(*) as n from events a join events b on a.user_id = b.user_id and b.ts > a.ts and b.ts <= a.ts + interval 1 hour group by a.event_id")
def op_join_interval(t):
    """Interval join: equality on user and hour bucket (own and next), the interval as a residual."""
    hour = F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / 3600)
    a = t.events.select(F.col("event_id").alias("e1"), "user_id", F.col("ts").alias("t1"), F.explode(F.array(hour, hour + 1)).alias("h"))
    b = t.events.select("user_id", F.col("ts").alias("t2"), hour.alias("h"))
    x = a.join(b, ["user_id", "h"]).where("t2 > t1 and t2 <= t1 + interval 1 hour")
    return x.groupBy("e1").agg(n_rows().alias("n"))


@op("select c_custkey, o_orderkey, round(o_totalprice, 2) as price from (select c_custkey, o_orderkey, o_totalprice, row_number() over (partition by c_custkey order by o_totalprice desc, o_orderkey) as rn from customer join orders on c_custkey = o_custkey) where rn <= 3")
def op_lateral_topk(t):
    return t.spark.sql(
        "select c_custkey, o_orderkey, round(o_totalprice, 2) as price from {customer}, lateral (select o_orderkey, o_totalprice from (select o_orderkey, o_totalprice, o_custkey, row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) as rn from {orders}) where o_custkey = c_custkey and rn <= 3)",
        customer=t.customer,
        orders=t.orders,
    )


# ---- aggregates
@op("select l_returnflag, l_linestatus, count(*) as n, round(sum(l_quantity), 2) as q, round(avg(l_extendedprice), 4) as p, min(l_tax) as lo, max(l_tax) as hi from lineitem group by 1, 2")
def op_agg_basic(t):
    return t.lineitem.groupBy("l_returnflag", "l_linestatus").agg(n_rows().alias("n"), _r(F.sum("l_quantity"), 2).alias("q"), _r(F.avg("l_extendedprice"), 4).alias("p"), F.min("l_tax").alias("lo"), F.max("l_tax").alias("hi"))


@op("select l_suppkey, count(distinct l_partkey) as parts, count(distinct l_orderkey) as orders from lineitem group by 1")
def op_agg_distinct(t):
    return t.lineitem.groupBy("l_suppkey").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_orderkey").alias("orders"))


@op("select l_shipmode_n, count(*) filter (l_returnflag = 'R') as r, round(coalesce(sum(l_quantity) filter (l_discount > 0.05), 0), 2) as q from (select *, l_linenumber as l_shipmode_n from lineitem) group by 1")
def op_agg_filter(t):
    return t.lineitem.groupBy(F.col("l_linenumber").alias("l_shipmode_n")).agg(F.count_if(F.col("l_returnflag") == "R").alias("r"), _r(F.coalesce(F.sum(F.when(F.col("l_discount") > 0.05, F.col("l_quantity"))), F.lit(0.0)), 2).alias("q"))


@op("select o_custkey, count(*) as n from orders group by 1 having count(*) > 12")
def op_agg_having(t):
    return t.orders.groupBy("o_custkey").agg(n_rows().alias("n")).where("n > 12")


_CB = "(select o_custkey % 10 as i, l_partkey % 7 as j, l_quantity as r from lineitem join orders on l_orderkey = o_orderkey)"


def _small(t):
    return t.lineitem.join(t.orders, F.col("l_orderkey") == F.col("o_orderkey")).select((F.col("o_custkey") % 10).alias("i"), (F.col("l_partkey") % 7).alias("j"), F.col("l_quantity").alias("r"))


@op(f"select coalesce(i, -1) as i, coalesce(j, -1) as j, grouping(i, j)::bigint as g, round(avg(r), 6) as m from {_CB} group by grouping sets ((), (i), (j))")
def op_agg_grouping_sets(t):
    return _small(t).groupingSets([[], ["i"], ["j"]], "i", "j").agg(F.grouping_id().cast("long").alias("g"), _r(F.avg("r")).alias("m")).na.fill(-1, ["i", "j"])


@op("select n_name, c_mktsegment, count(*) as n from customer join nation on c_nationkey = n_nationkey group by rollup (n_name, c_mktsegment)")
def op_agg_rollup(t):
    x = t.customer.join(F.broadcast(t.nation), F.col("c_nationkey") == F.col("n_nationkey"))
    return x.rollup("n_name", "c_mktsegment").agg(n_rows().alias("n"))


@op("select l_returnflag, l_linestatus, count(*) as n from lineitem group by cube (l_returnflag, l_linestatus)")
def op_agg_cube(t):
    return t.lineitem.cube("l_returnflag", "l_linestatus").agg(n_rows().alias("n"))


@op("select l_linenumber, round(stddev_samp(l_quantity), 6) as sd, round(var_pop(l_quantity), 6) as vp, round(avg(l_discount), 6) as a, round(median(l_quantity), 6) as md from lineitem group by 1")
def op_agg_stats(t):
    return t.lineitem.groupBy("l_linenumber").agg(_r(F.stddev_samp("l_quantity")).alias("sd"), _r(F.var_pop("l_quantity")).alias("vp"), _r(F.avg("l_discount")).alias("a"), _r(F.median("l_quantity")).alias("md"))


@op("select round(corr(l_quantity, l_extendedprice), 6) as c, round(covar_pop(l_quantity, l_discount), 6) + 0e0 as cv, round(regr_slope(l_extendedprice, l_quantity), 4) as sl, round(regr_r2(l_extendedprice, l_quantity), 6) as r2 from lineitem")
def op_agg_corr_regr(t):
    return t.lineitem.agg(_r(F.corr("l_quantity", "l_extendedprice")).alias("c"), (_r(F.covar_pop("l_quantity", "l_discount")) + 0.0).alias("cv"), _r(F.regr_slope("l_extendedprice", "l_quantity"), 4).alias("sl"), _r(F.regr_r2("l_extendedprice", "l_quantity")).alias("r2"))


@op("select user_id, array_to_string(list_sort(list(event_id)), ',') as ids from events group by 1")
def op_agg_collect_sorted(t):
    return t.events.groupBy("user_id").agg(F.array_join(F.array_sort(F.collect_list("event_id")).cast("array<string>"), ",").alias("ids"))


@op("select o_custkey, arg_max(o_orderkey, o_totalprice) as hi, arg_min(o_orderkey, o_totalprice) as lo from orders group by 1")
def op_agg_maxby(t):
    return t.orders.groupBy("o_custkey").agg(F.max_by("o_orderkey", "o_totalprice").alias("hi"), F.min_by("o_orderkey", "o_totalprice").alias("lo"))


@op("select user_id, bit_xor(event_id) as x, bit_or(event_id) as o, bit_and(event_id) as a from events group by 1")
def op_agg_bit(t):
    return t.events.groupBy("user_id").agg(F.bit_xor("event_id").alias("x"), F.bit_or("event_id").alias("o"), F.bit_and("event_id").alias("a"))


@op(None)
def op_agg_approx(t):
    return t.lineitem.agg(F.approx_count_distinct("l_partkey").alias("parts"), F.approx_percentile("l_quantity", F.array(F.lit(0.5), F.lit(0.9)), F.lit(1000)).alias("q"), F.hll_sketch_estimate(F.hll_sketch_agg("l_orderkey")).alias("orders"))


@op("select user_id, count(*) filter (event_type = 'click') as click, count(*) filter (event_type = 'purchase') as purchase, count(*) filter (event_type = 'view') as view from events group by 1")
def op_pivot(t):
    return t.events.groupBy("user_id").pivot("event_type", ["click", "purchase", "view"]).agg(n_rows()).na.fill(0)


@op("select l_linenumber, 'q' as what, round(sum(l_quantity), 2) as v from lineitem group by 1 union all select l_linenumber, 'd', round(sum(l_discount), 2) from lineitem group by 1")
def op_unpivot(t):
    x = t.lineitem.groupBy("l_linenumber").agg(_r(F.sum("l_quantity"), 2).alias("q"), _r(F.sum("l_discount"), 2).alias("d"))
    return x.unpivot("l_linenumber", ["q", "d"], "what", "v")


# ---- windows
_W = "over (partition by user_id order by ts, event_id)"


def _by_user():
    return Window.partitionBy("user_id").orderBy("ts", "event_id")


@op(f"select event_id, row_number() {_W} as rn, rank() over (partition by user_id order by event_type) as rk, dense_rank() over (partition by user_id order by event_type) as dr from events")
def op_win_ranking(t):
    kind = Window.partitionBy("user_id").orderBy("event_type")
    big = lambda c: c.cast("long")
    return t.events.select("event_id", big(F.row_number().over(_by_user())).alias("rn"), big(F.rank().over(kind)).alias("rk"), big(F.dense_rank().over(kind)).alias("dr"))


@op(f"select event_id, lag(event_id, 1, -1) {_W} as prev, lead(event_id, 2, -1) {_W} as nxt, first_value(event_id) {_W} as fst, coalesce(nth_value(event_id, 2) {_W}, -1) as sec from events")
def op_win_analytic(t):
    w = _by_user()
    return t.events.select("event_id", F.lag("event_id", 1, -1).over(w).alias("prev"), F.lead("event_id", 2, -1).over(w).alias("nxt"), F.first("event_id").over(w).alias("fst"), F.coalesce(F.nth_value("event_id", 2).over(w), F.lit(-1)).alias("sec"))


@op("select event_id, round(avg(value) over (partition by user_id order by ts, event_id rows between 2 preceding and current row), 6) as m, count(*) over (partition by user_id order by ts, event_id rows unbounded preceding) as n from events")
def op_win_rows_frame(t):
    w = _by_user()
    return t.events.select("event_id", _r(F.avg("value").over(w.rowsBetween(-2, 0))).alias("m"), F.count(F.lit(1)).over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("n"))


@op("select o_orderkey, count(*) over (partition by o_custkey order by o_totalprice range between 10000 preceding and 10000 following) as near from orders")
def op_win_range_frame(t):
    w = Window.partitionBy("o_custkey").orderBy("o_totalprice").rangeBetween(-10000, 10000)
    return t.orders.select("o_orderkey", F.count(F.lit(1)).over(w).alias("near"))


@op("select event_id, ntile(4) over (partition by user_id order by ts, event_id) as q, round(percent_rank() over (partition by user_id order by ts, event_id), 6) as pr, round(cume_dist() over (partition by user_id order by ts, event_id), 6) as cd from events")
def op_win_ntile_dist(t):
    w = _by_user()
    return t.events.select("event_id", F.ntile(4).over(w).cast("long").alias("q"), _r(F.percent_rank().over(w)).alias("pr"), _r(F.cume_dist().over(w)).alias("cd"))


# ---- order and limits
@op("select o_custkey, o_orderkey from orders order by o_custkey desc nulls last, o_orderkey")
def op_sort_multi(t):
    return t.orders.select("o_custkey", "o_orderkey").orderBy(F.col("o_custkey").desc_nulls_last(), "o_orderkey")


@op("select o_orderkey from orders order by o_orderkey limit 50 offset 20")
def op_limit_offset(t):
    return t.orders.select("o_orderkey").orderBy("o_orderkey").offset(20).limit(50)


@op("select o_orderkey, round(o_totalprice, 2) as price from orders order by o_totalprice desc, o_orderkey limit 25")
def op_topk_global(t):
    return t.orders.orderBy(F.col("o_totalprice").desc(), "o_orderkey").limit(25).select("o_orderkey", _r("o_totalprice", 2).alias("price"))


@op("select o_orderpriority, o_orderkey from (select *, row_number() over (partition by o_orderpriority order by o_totalprice desc, o_orderkey) as rn from orders) where rn <= 5")
def op_topk_group(t):
    w = Window.partitionBy("o_orderpriority").orderBy(F.col("o_totalprice").desc(), "o_orderkey")
    return t.orders.withColumn("rn", F.row_number().over(w)).where("rn <= 5").select("o_orderpriority", "o_orderkey")


# ---- set operations on the supports of two halves
_A, _B = "select l_suppkey as i, l_partkey as j from lineitem where l_linenumber % 2 = 0", "select l_suppkey as i, l_partkey as j from lineitem where l_linenumber % 2 = 1"


def _half(t, odd: int):
    return t.lineitem.where(F.col("l_linenumber") % 2 == odd).select(F.col("l_suppkey").alias("i"), F.col("l_partkey").alias("j"))


@op(f"{_A} union all {_B}")
def op_union_all(t):
    return _half(t, 0).union(_half(t, 1))


@op(f"{_A} union {_B}")
def op_union_distinct(t):
    return _half(t, 0).unionByName(_half(t, 1)).distinct()


@op(f"{_A} intersect {_B}")
def op_intersect(t):
    return _half(t, 0).intersect(_half(t, 1))


@op(f"{_A} except {_B}")
def op_except(t):
    return _half(t, 0).subtract(_half(t, 1))


@op(f"{_A} intersect all {_B}")
def op_intersect_all(t):
    return _half(t, 0).intersectAll(_half(t, 1))


@op(f"{_A} except all {_B}")
def op_except_all(t):
    return _half(t, 0).exceptAll(_half(t, 1))


# ---- scalars
@op("select doc_id, length(trim(regexp_replace(lower(text), '\\s+', ' ', 'g')))::bigint as n, lower(substr(text, 1, 3)) as head, concat(lang, '-', source) as tag from documents")
def op_str_clean(t):
    return t.documents.select("doc_id", F.length(F.trim(F.regexp_replace(F.lower("text"), r"\s+", " "))).cast("long").alias("n"), F.lower(F.substring("text", 1, 3)).alias("head"), F.concat("lang", F.lit("-"), "source").alias("tag"))


@op("select doc_id, regexp_matches(text, '[0-9]{4}') as has, regexp_extract(text, '([0-9]+)', 1) as num from documents")
def op_str_regex(t):
    return t.documents.select("doc_id", F.col("text").rlike("[0-9]{4}").alias("has"), F.regexp_extract("text", "([0-9]+)", 1).alias("num"))


@op("select w, count(*) as n from (select unnest(string_split(lower(text), ' ')) as w from documents) where length(w) >= 3 group by w having count(*) >= 20")
def op_str_split_agg(t):
    x = t.documents.select(F.explode(F.split(F.lower("text"), " ")).alias("w")).where(F.length("w") >= 3)
    return x.groupBy("w").agg(n_rows().alias("n")).where("n >= 20")


@op("select page_id, regexp_extract(url, '^https?://([^/?#]+)', 1) as host, regexp_extract(url, '^https?://[^/?#]+([^?#]*)', 1) as path from pages")
def op_url_parts(t):
    return t.pages.select("page_id", F.parse_url("url", F.lit("HOST")).alias("host"), F.parse_url("url", F.lit("PATH")).alias("path"))


@op("select o_orderkey, year(o_orderdate)::int as y, month(o_orderdate)::int as m, dayofweek(o_orderdate)::int + 1 as dw, quarter(o_orderdate)::int as q from orders")
def op_date_parts(t):
    d = "o_orderdate"
    return t.orders.select("o_orderkey", F.year(d).alias("y"), F.month(d).alias("m"), F.dayofweek(d).alias("dw"), F.quarter(d).alias("q"))


@op("select strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') as m, count(*) as n from orders group by 1")
def op_date_trunc(t):
    return t.orders.groupBy(F.date_format(F.date_trunc("month", F.col("o_orderdate").cast("timestamp")), "yyyy-MM-dd").alias("m")).agg(n_rows().alias("n"))


@op("select l_orderkey, l_linenumber, date_diff('day', o_orderdate::date, l_shipdate::date)::int as days from lineitem join orders on l_orderkey = o_orderkey")
def op_date_diff(t):
    x = t.lineitem.join(t.orders, F.col("l_orderkey") == F.col("o_orderkey"))
    return x.select("l_orderkey", "l_linenumber", F.datediff(F.col("l_shipdate").cast("date"), F.col("o_orderdate").cast("date")).alias("days"))


@op("select o_orderkey, strftime(o_orderdate + interval 30 day, '%Y-%m-%d') as due from orders")
def op_interval_add(t):
    return t.orders.select("o_orderkey", F.date_format(F.expr("o_orderdate + interval 30 days").cast("timestamp"), "yyyy-MM-dd").alias("due"))


@op("select l_orderkey, l_linenumber, round(sqrt(l_quantity), 6) as s, round(ln(l_extendedprice), 6) as l, round(pow(l_tax, 2), 8) as p, floor(l_quantity / 7)::bigint as f from lineitem")
def op_math(t):
    return t.lineitem.select("l_orderkey", "l_linenumber", _r(F.sqrt("l_quantity")).alias("s"), _r(F.ln("l_extendedprice")).alias("l"), _r(F.pow("l_tax", F.lit(2.0)), 8).alias("p"), F.floor(F.col("l_quantity") / 7).cast("long").alias("f"))


@op("select p_partkey, bit_count(xor(p_partkey, p_size::bigint))::int as h, (p_partkey >> 3) & 7 as b from part")
def op_bits_hamming(t):
    return t.part.select("p_partkey", F.bit_count(F.col("p_partkey").bitwiseXOR(F.col("p_size").cast("long"))).alias("h"), F.shiftright("p_partkey", 3).bitwiseAND(F.lit(7)).alias("b"))


@op("select doc_id, md5(text) as m, sha256(text) as s from documents")
def op_hash_md5(t):
    return t.documents.select("doc_id", F.md5("text").alias("m"), F.sha2("text", 256).alias("s"))


@op("select o_orderkey, case when o_totalprice > 200000 then 'high' when o_totalprice > 50000 then 'mid' else 'low' end as c, coalesce(nullif(o_orderstatus, 'O'), 'open') as st from orders")
def op_conditional(t):
    p = F.col("o_totalprice")
    return t.orders.select("o_orderkey", F.when(p > 200000, "high").when(p > 50000, "mid").otherwise("low").alias("c"), F.coalesce(F.nullif("o_orderstatus", F.lit("O")), F.lit("open")).alias("st"))


@op("select c_custkey, coalesce(try_cast(substr(c_name, 10) as bigint), -1) as n, coalesce(try_cast(c_mktsegment as int), -1) as bad from customer")
def op_try_cast(t):
    return t.customer.select("c_custkey", F.coalesce(F.substring("c_name", 10, 100).try_cast("long"), F.lit(-1)).alias("n"), F.coalesce(F.col("c_mktsegment").try_cast("int"), F.lit(-1)).alias("bad"))


# ---- nested values
@op("select vec_id, round(list_sum(list_transform(embedding, lambda x: abs(x)::double)), 4) as l1, len(list_filter(embedding, lambda x: x > 0))::int as pos from embeddings")
def op_array_hof(t):
    return t.embeddings.select("vec_id", _r(F.aggregate("embedding", F.lit(0.0), lambda s, x: s + F.abs(x.cast("double"))), 4).alias("l1"), F.size(F.filter("embedding", lambda x: x > 0)).alias("pos"))


@op("select k, len(list_intersect(a, b))::int as both, len(list_distinct(list_concat(a, b)))::int as any from (select l_suppkey as k, list(distinct l_partkey) filter (l_linenumber = 1) as a, list(distinct l_partkey) filter (l_linenumber <> 1) as b from lineitem group by 1) where a is not null and b is not null")
def op_array_setops(t):
    one = F.col("l_linenumber") == 1
    g = t.lineitem.groupBy(F.col("l_suppkey").alias("k")).agg(F.collect_set(F.when(one, F.col("l_partkey"))).alias("a"), F.collect_set(F.when(~one, F.col("l_partkey"))).alias("b"))
    return g.where("size(a) > 0 and size(b) > 0").select("k", F.size(F.array_intersect("a", "b")).alias("both"), F.size(F.array_union("a", "b")).alias("any"))


@op("select c_custkey, o from (select c_custkey, unnest(case when len(o) = 0 then [null] else o end) as o from (select c_custkey, coalesce(list(o_orderkey) filter (o_orderkey is not null), []) as o from customer left join orders on c_custkey = o_custkey group by 1))")
def op_explode_outer(t):
    x = t.customer.join(t.orders, F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.collect_list("o_orderkey").alias("o"))
    return x.select("c_custkey", F.explode_outer("o").alias("o"))


@op("select user_id, coalesce(click, 0) as clicks, n as kinds from (select user_id, count(*) filter (event_type = 'click') as click, count(distinct event_type)::int as n from events group by 1)")
def op_map_ops(t):
    m = t.events.groupBy("user_id", "event_type").agg(n_rows().alias("n")).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.coalesce(F.try_element_at("m", F.lit("click")), F.lit(0)).alias("clicks"), F.size(F.map_keys("m")).alias("kinds"))


@op("select o_orderkey, s.a as a, s.b as b from (select o_orderkey, {'a': o_custkey, 'b': o_orderstatus} as s from orders)")
def op_struct(t):
    return t.orders.select("o_orderkey", F.struct(F.col("o_custkey").alias("a"), F.col("o_orderstatus").alias("b")).alias("s")).select("o_orderkey", "s.a", "s.b")


@op("select event_id, json_extract_string(props, '$.k')::bigint as k from events")
def op_json_extract(t):
    return t.events.select("event_id", F.from_json("props", "k long")["k"].alias("k"))


@op("select o_orderkey, concat('{\"k\":', o_custkey, ',\"s\":\"', o_orderstatus, '\"}') as js from orders")
def op_json_build(t):
    return t.orders.select("o_orderkey", F.to_json(F.struct(F.col("o_custkey").alias("k"), F.col("o_orderstatus").alias("s"))).alias("js"))


@op("select vec_id, round(list_sum(list_transform(list_zip(embedding, e0), lambda p: p[1]::double * p[2]::double)), 5) + 0e0 as d from embeddings, (select embedding as e0 from embeddings order by vec_id limit 1)")
def op_vector_dot(t):
    first = t.embeddings.orderBy("vec_id").limit(1).select(F.col("embedding").alias("e0"))
    return t.embeddings.crossJoin(F.broadcast(first)).select("vec_id", (_r(F.aggregate(F.zip_with("embedding", "e0", lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x), 5) + 0.0).alias("d"))


@op("select vec_id, round(list_cosine_similarity(embedding::double[], e0::double[]), 5) + 0e0 as c from embeddings, (select embedding as e0 from embeddings order by vec_id limit 1)")
def op_vector_cosine(t):
    first = t.embeddings.orderBy("vec_id").limit(1).select(F.col("embedding").alias("e0"))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)
    return t.embeddings.crossJoin(F.broadcast(first)).select("vec_id", (_r(dot("embedding", "e0") / F.sqrt(dot("embedding", "embedding") * dot("e0", "e0")), 5) + 0.0).alias("c"))


# ---- subqueries
@op("select o_orderkey from orders where o_totalprice > (select avg(o_totalprice) * 1.5e0 from orders)")
def op_subquery_scalar(t):
    return t.spark.sql("select o_orderkey from {o} where o_totalprice > (select avg(o_totalprice) * 1.5D from {o})", o=t.orders)


@op("select o_orderkey from orders o where exists (select 1 from lineitem where l_orderkey = o.o_orderkey and l_quantity > 49)")
def op_subquery_exists(t):
    return t.spark.sql("select o_orderkey from {o} o where exists (select 1 from {li} where l_orderkey = o.o_orderkey and l_quantity > 49)", o=t.orders, li=t.lineitem)


@op("with c as (select o_custkey, sum(o_totalprice) as s from orders group by 1) select count(*) as n from c where s > (select avg(s) from c)")
def op_cte_reuse(t):
    return t.spark.sql("with c as (select o_custkey, sum(o_totalprice) as s from {o} group by 1) select count(*) as n from c where s > (select avg(s) from c)", o=t.orders)


@op("select l_orderkey, l_linenumber from lineitem where concat('0x', substr(md5(concat('smp:', l_orderkey, ':', l_linenumber)), 1, 2))::int < 26")
def op_sample_hash(t):
    from lowrank_spark.functions.hashing import md5_byte, text

    return t.lineitem.where(md5_byte(text("smp", F.col("l_orderkey"), F.col("l_linenumber"))) < 26).select("l_orderkey", "l_linenumber")


# ---- user functions
@op("select vec_id, round(list_sum(list_transform(embedding, lambda x: x::double * x::double)), 4) as d from embeddings")
def op_udf_arrow(t):
    from lowrank_spark.functions.sqlext import norm_udf
    from lowrank_spark.runtime import ship_package

    ship_package(t.spark)
    return t.embeddings.select("vec_id", _r(norm_udf()("embedding"), 4).alias("d"))


@op("select l_linenumber, round(sqrt(avg((l_quantity - 25) * (l_quantity - 25))), 6) as rmse from lineitem group by 1")
def op_udaf_grouped(t):
    from lowrank_spark.functions.sqlext import rmse_udaf
    from lowrank_spark.runtime import ship_package

    ship_package(t.spark)
    return t.lineitem.groupBy("l_linenumber").agg(_r(rmse_udaf()("l_quantity", F.lit(25.0)), 6).alias("rmse"))


@op("select s_suppkey, g::int as grp, (s_suppkey * (g + 1))::bigint as key from supplier, range(2) x(g)")
def op_udtf_bands(t):
    from lowrank_spark.functions.sqlext import register
    from lowrank_spark.runtime import ship_package

    ship_package(t.spark)
    register(t.spark)
    return t.spark.sql("select s_suppkey, grp, key from {s}, lateral band_keys(array(s_suppkey, s_suppkey * 2))", s=t.supplier)


@op("select n_nationkey, round(0.04e0 / (1 + 0.3e0 * pow(n_nationkey, 1.5)), 9) as gamma, bit_count(xor(n_nationkey::bigint, 5))::int as h from nation")
def op_sql_functions(t):
    from lowrank_spark.functions.sqlext import register_sql

    register_sql(t.spark)
    return t.spark.sql("select n_nationkey, round(step_size(0.04D, 0.3D, n_nationkey), 9) as gamma, hamming(cast(n_nationkey as bigint), 5L) as h from {n}", n=t.nation)
