"""One registry of every query: name -> (callable, DuckDB SQL or None). Small parameters keep both engines' forms exact."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lowrank_spark import config as C
from lowrank_spark.functions.hashing import duck_int, text, uniform
from lowrank_spark.operators import band, baselines, biases, cost, graph, loss, metrics, neigh, neural, online, params, predict, relational, signhash, steps, theory, train
from lowrank_spark.plans import experiments
from lowrank_spark.runtime import Scratch
from lowrank_spark.sources import interactions as W
from lowrank_spark.sources import prep
from lowrank_spark.streaming import streams

REGISTRY: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str | None]] = {}


def add(name: str, fn, sql: str | None = None) -> None:
    if name in REGISTRY:
        raise ValueError(name)
    REGISTRY[name] = (fn, sql)


def query(sql: str | None = None, name: str | None = None):
    def wrap(fn):
        add(name or fn.__name__, fn, sql)
        return fn

    return wrap


SEED, G = 7, 8
HASH = C.HashConfig(G=G, p=2, q=2, K=4, seed=SEED, max_bucket=None)
CFG = C.TrainConfig(F=4, K=4, alpha=C.Rates(0.02, 0.02, 0.02, 0.02, 0.01, 0.01), lam=C.Rates(0.01, 0.01, 0.02, 0.02, 0.05, 0.05), beta=0.3)
SPREAD = 0.2


def r6(df: DataFrame, *cols: str, digits: int = 6) -> DataFrame:
    """Rounded, with a negative zero made a plain one."""
    return df.withColumns({c: F.round(F.col(c), digits) + F.lit(0.0) for c in cols})


def d6(*cols: str, digits: int = 6) -> str:
    return ", ".join(f"round({c}, {digits}) + 0e0 as {c}" for c in cols)


# ---- interaction matrices
for _n in W.WORKLOADS:
    _cols = "i, j, r" if _n != "dim_vec" else "i, j, round(r, 6) as r"
    _fix = {"discount": "discount_clean"}.get(_n, _n)
    add(f"r_{_fix}", (lambda n: lambda s, d: (lambda x: r6(x, "r") if n == "dim_vec" else x.select("i", "j", "r"))(W.load_interactions(s, d, n)))(_n), f"select {_cols} from ({W.DUCK[_n]})")


def duck(w: str, select: str, extra: str = "") -> str:
    """SQL over the common chain of a workload: entries, graph, neighbours, parameters, prediction."""
    f, s = CFG.F, 2 / CFG.F**0.5
    hashed = lambda t, *c: f"({duck_int('concat(' + repr(t + ':') + ', ' + ", ':', ".join(c) + ')')} / 4294967296e0 - 0.5e0)"
    return f"""
with im as (select i, j, r from ({W.DUCK[w]})),
pr as (select a.j as j1, b.j as j2, a.r as x, b.r as y from im a join im b on a.i = b.i and a.j < b.j),
ps as (select j1, j2, count(*)::double as n, sum(x) as sx, sum(y) as sy, sum(x * x) as sxx, sum(y * y) as syy, sum(x * y) as sxy from pr group by j1, j2),
pe as (select j1, j2, n::bigint as n, case when n * sxx - sx * sx > 0 and n * syy - sy * sy > 0 then (n * sxy - sx * sy) / sqrt((n * sxx - sx * sx) * (n * syy - sy * sy)) else 0e0 end as rho from ps),
gr as (select *, n / (n + {C.LAMBDA_RHO}e0) * rho as s from pe),
bo as (select j1 as j, j2 as nbr, s from gr union all select j2, j1, s from gr),
tp as (select * from (select j, nbr, s, row_number() over (partition by j order by s desc, nbr) as k from bo) where k <= {CFG.K}),
mu as (select avg(r) as mu from im),
b as (select i, avg(r) - (select mu from mu) as b from im group by i),
bh as (select j, avg(r) - (select mu from mu) as bh from im group by j),
uf as (select i, f, {hashed("u", "i", "f")} * {s}e0 as u from (select distinct i from im), range({f}) t(f)),
vf as (select j, f, {hashed("v", "j", "f")} * {s}e0 as v from (select distinct j from im), range({f}) t(f)),
wc as (select j, k, {hashed("w", "j", "k")} * {SPREAD}e0 as w, {hashed("c", "j", "k")} * {SPREAD}e0 as c from tp),
an as (select im.i, im.j, im.r, tp.k, tp.nbr, o.r as rn, case when o.r is not null then 'explicit' else 'implicit' end as kind from im join tp on im.j = tp.j left join im o on o.i = im.i and o.j = tp.nbr),
nr as (select an.*, rn - ((select mu from mu) + b.b + bh.bh) as res, w, c from an join wc on an.j = wc.j and an.k = wc.k join b on an.i = b.i join bh on bh.j = an.nbr),
nt as (select i, j, coalesce(sum(case when kind = 'explicit' then res * w end), 0e0) as sx, coalesce(sum(case when kind = 'implicit' then c end), 0e0) as si, count(*) filter (kind = 'explicit') as n_ex, count(*) filter (kind = 'implicit') as n_im from nr group by i, j),
fa as (select im.i, im.j, sum(u * v) as d from im join uf on im.i = uf.i join vf on im.j = vf.j and uf.f = vf.f group by im.i, im.j),
ba as (select im.i, im.j, im.r, (select mu from mu) + b.b + bh.bh as base from im join b on im.i = b.i join bh on im.j = bh.j),
sc as (select ba.i, ba.j, ba.r, base, fa.d, coalesce(case when n_ex > 0 then sx / sqrt(n_ex) end, 0e0) as ex, coalesce(case when n_im > 0 then si / sqrt(n_im) end, 0e0) as imp, coalesce(n_ex, 0) as n_ex, coalesce(n_im, 0) as n_im from ba join fa on ba.i = fa.i and ba.j = fa.j left join nt on ba.i = nt.i and ba.j = nt.j),
er as (select *, base + ex + imp + d as pred, r - (base + ex + imp + d) as e from sc)
{extra} {select}"""


# ---- preparation
@query(f"select count(distinct i) as m, count(distinct j) as n, count(*) as entries, max(r) as max_r, min(r) as min_r from ({W.DUCK['cust_part']})")
def profile(s, d):
    return prep.profile(W.cust_part(s, d))


@query(f"select i, j, r, {duck_int("concat('split:', i, ':', j)", 2)} < 26 as is_test from ({W.DUCK['cust_part']})")
def split_train_test(s, d):
    return W.cust_part(s, d).withColumn("is_test", prep.in_test())


@query(f"select i, j, r, row_number() over (partition by i order by md5(concat('loo:', i, ':', j)) desc, j desc) = 1 as held from ({W.DUCK['user_key']})")
def leave_one_out(s, d):
    return prep.leave_one_out(W.user_key(s, d).select("i", "j", "r"))


_NEG = f"select distinct i, {duck_int("concat('neg:', i, ':', t)", 14)} % 100 as j from (select distinct i from ({W.DUCK['user_key']})), range(20) x(t)"


@query(f"with im as ({W.DUCK['user_key']}), c as ({_NEG}) select i, j from c where not exists (select 1 from im where im.i = c.i and im.j = c.j)")
def negatives(s, d):
    im = W.user_key(s, d)
    return prep.negatives(im.select("i").distinct(), im, 100, 20)


@query(f"select i, j, case when {duck_int("concat('noise:', i, ':', j)")} < {int(0.01 * 2**32)} then (1 + {duck_int("concat('nv:', i, ':', j)", 2)} % 5)::double else r end as r from ({W.DUCK['planted']})")
def noise_inject(s, d):
    return prep.inject_noise(W.planted(s, d), 0.01)


@query(f"select i, j, r, {duck_int("concat('newi:', i)")} < {int(0.01 * 2**32)} or {duck_int("concat('newj:', j)")} < {int(0.01 * 2**32)} as is_new from ({W.DUCK['planted']})")
def online_split(s, d):
    old, new = prep.online_split(W.planted(s, d))
    return old.withColumn("is_new", F.lit(False)).union(new.withColumn("is_new", F.lit(True)))


@query(f"select i, degree, place, case when floor(place / 4)::bigint % 2 = 0 then place % 4 else 3 - place % 4 end as block from (select i, degree, row_number() over (order by degree desc, i) - 1 as place from (select i, count(*) as degree from ({W.DUCK['cust_part']}) group by i))")
def degree_order(s, d):
    return prep.degree_order(W.cust_part(s, d), "i", 4)


@query(f"select i, row_number() over (order by i) - 1 as id from (select distinct i from ({W.DUCK['term_doc']}))")
def dense_ids(s, d):
    return prep.index_ids(W.term_doc(s, d), "i")


@query(f"select i, j, r / 20 as r from ({W.DUCK['discount']})")
def lift_and_rescale(s, d):
    raw = W.discount(s, d).withColumn("r", F.when(F.col("r") == 0.5, 0.0).otherwise(F.col("r")))
    return prep.rescale(prep.lift_zeros(raw), 20)


@query("select o_custkey as i, l_partkey as j, avg(l_quantity) as r from lineitem join orders on l_orderkey = o_orderkey group by o_custkey, l_partkey")
def validated_mean(s, d):
    raw = W._sold(s, d).select(F.col("o_custkey").alias("i"), F.col("l_partkey").alias("j"), F.col("l_quantity").alias("r"))
    dirty = raw.union(raw.limit(1).select("i", "j", F.lit(None).cast("double"))).union(raw.limit(1).select(F.lit(None).cast("long"), "j", "r"))
    return prep.validate_interactions(dirty, "mean")


# ---- exact graph
@query(duck("cust_brand", "select j1, j2, count(*) as n from pr group by j1, j2"))
def co_counts(s, d):
    return graph.co_counts(W.cust_brand(s, d))


@query(duck("cust_brand", f"select j1, j2, n, {d6('rho')} from pe"))
def pearson(s, d):
    return r6(graph.pearson(W.cust_brand(s, d)), "rho")


@query(duck("cust_brand", f"select j1, j2, n, {d6('rho', 's')} from gr"))
def shrunk_graph(s, d):
    return r6(graph.similarity_graph(W.cust_brand(s, d)), "rho", "s")


@query(duck("planted_groups", f"select j, nbr, {d6('s')}, k from tp"))
def exact_topk(s, d):
    return r6(graph.topk(graph.similarity_graph(W.planted_groups(s, d)), CFG.K), "s")


@query(duck("cust_brand", "select j, nbr, round(s, 6) + 0e0 as s, k from (select j, nbr, s, row_number() over (partition by j order by s, nbr) as k from bo) where k <= 4"))
def farthest_topk(s, d):
    return r6(graph.topk(graph.similarity_graph(W.cust_brand(s, d)), 4, largest=False), "s")


@query(duck("cust_brand", "select j1, j2, p.n::bigint as n, round(p.n / (a.d + b.d - p.n), 6) + 0e0 as rho from ps p join dg a on a.j = j1 join dg b on b.j = j2", ", dg as (select j, count(*) as d from im group by j)"))
def jaccard_graph(s, d):
    return r6(graph.jaccard(W.cust_brand(s, d)), "rho")


@query(duck("cust_brand", "select j1, j2, p.n::bigint as n, round(p.sxy / (a.d * b.d), 6) + 0e0 as rho from ps p join dg a on a.j = j1 join dg b on b.j = j2", ", dg as (select j, sqrt(sum(r * r)) as d from im group by j)"))
def cosine_graph(s, d):
    return r6(graph.cosine(W.cust_brand(s, d)), "rho")


@query(duck("cust_brand", """select j1, j2, p.n::bigint as n, round((sxy - a.m * sy - b.m * sx + p.n * a.m * b.m) / sqrt((sxx - 2 * a.m * sx + p.n * a.m * a.m) * (syy - 2 * b.m * sy + p.n * b.m * b.m)), 6) + 0e0 as rho
from ps p join cm a on a.j = j1 join cm b on b.j = j2""", ", cm as (select j, avg(r) as m from im group by j)"))
def pearson_column_centre(s, d):
    return r6(graph.pearson(W.cust_brand(s, d), centre="column"), "rho")


# ---- sign hashing
def _byte(i: str, rep: str) -> str:
    return f"concat('0x', substr(md5(concat('{SEED}:', {i}, ':', {rep} // 16)), (2 * ({rep} % 16) + 1)::bigint, 2))::bigint"


def sums_sql(w: str, reps: int, psi: str = "r * r", where: str = "true") -> str:
    lanes = ", ".join(f"sum(case when (b >> {g}) & 1 = 1 then p else -p end) as s{g}" for g in range(G))
    return f"select j, rep, {lanes} from (select j, rep, {psi} as p, {_byte('i', 'rep')} as b from ({W.DUCK[w]}), range({reps}) t(rep) where {where}) group by j, rep"


def codes_sql(sums: str, bits: int = G) -> str:
    return f"select j, rep, ({' + '.join(f'case when s{g} >= 0 then {1 << g} else 0 end' for g in range(bits))})::bigint as code from ({sums})"


def keys_sql(codes: str, p: int = HASH.p) -> str:
    return f"select rep // {p} as grp, sum(code * (1::bigint << ((rep % {p}) * {G})))::bigint as key, j from ({codes}) group by j, rep // {p}"


def pairs_sql(keys: str) -> str:
    return f"select a.j as j1, b.j as j2, count(*) as freq from ({keys}) a join ({keys}) b on a.grp = b.grp and a.key = b.key and a.j < b.j group by a.j, b.j"


def top_sql(pairs: str, k: int = HASH.K) -> str:
    return f"select * from (select j, nbr, freq, row_number() over (partition by j order by freq desc, nbr) as k from (select j1 as j, j2 as nbr, freq from ({pairs}) union all select j2, j1, freq from ({pairs}))) where k <= {k}"


def fill_sql(w: str, top: str, k: int = HASH.K) -> str:
    draw = lambda what, m: f"{duck_int(f"concat('fill:{SEED}:', hv.j, ':{what}')", 14)} % ({m})"
    return f"""with im as ({W.DUCK[w]}), tp as ({top}), un as (select j, row_number() over (order by j) - 1 as id from (select distinct j from im)),
nn as (select count(*) as n from un),
pp as (select min(p) as p from (select n + x as p from nn, range(2000) r(x)) where p >= 2 and not exists (select 1 from range(2, 2000) q(f) where f < p and p % f = 0)),
hv as (select un.j, count(tp.j) as have from un left join tp on un.j = tp.j group by un.j),
dr as (select hv.j, have, p, n, {draw("start", "p")} as a0, {draw("step", "greatest(1, p - 1)")} + 1 as hop from hv, pp, nn where have < {k}),
ca as (select j, have, t, (a0 + t * hop) % p as id from dr, range(2000 + {k}) x(t) where t < p and t <= {k} + p - n),
cb as (select ca.j, un.j as nbr, t, have from ca join un on ca.id = un.id where un.j <> ca.j),
cc as (select * from cb where not exists (select 1 from tp where tp.j = cb.j and tp.nbr = cb.nbr)),
cd as (select j, nbr, 0::bigint as freq, row_number() over (partition by j order by t) + have as k from cc)
select j, nbr, freq, k from tp union all select j, nbr, freq, k from cd where k <= {k}"""


_REPS = HASH.reps
_ONE = C.HashConfig(G=G, p=1, q=8, K=4, seed=SEED, max_bucket=None)


@query(f"select i, rep, {_byte('i', 'rep')} as code from (select distinct i from ({W.DUCK['supp_part']})), range({_REPS}) t(rep)")
def row_signs(s, d):
    return signhash.row_signs(W.supp_part(s, d).select("i").distinct(), HASH)


@query(sums_sql("supp_part", _REPS))
def sign_sums(s, d):
    return signhash.accumulate(W.supp_part(s, d), HASH)


@query(codes_sql(sums_sql("cust_part", _REPS)))
def sign_codes(s, d):
    return signhash.codes(signhash.accumulate(W.cust_part(s, d), HASH))


@query(codes_sql(sums_sql("discount", _REPS, "r * r * r * r")))
def sign_codes_fourth(s, d):
    return signhash.codes(signhash.accumulate(W.discount(s, d), replace(HASH, psi="fourth")))


@query(codes_sql(sums_sql("supp_part", 32)))
def sign_codes_gathered(s, d):
    return signhash.code_table(W.supp_part(s, d), C.HashConfig(G=G, p=2, q=16, seed=SEED))


@query(codes_sql(sums_sql("term_doc", 2, "1e0")))
def simhash_counts(s, d):
    return signhash.codes(signhash.accumulate(W.term_doc(s, d), replace(HASH, psi="ones", p=1, q=2)))


@query(keys_sql(codes_sql(sums_sql("term_doc", _REPS))))
def band_keys(s, d):
    return band.keys(signhash.codes(signhash.accumulate(W.term_doc(s, d), HASH)), HASH.p)


_P1 = pairs_sql(keys_sql(codes_sql(sums_sql("planted_groups", _ONE.reps)), 1))


@query(_P1)
def band_pairs(s, d):
    return band.pairs(band.keys(signhash.code_table(W.planted_groups(s, d), _ONE), 1))


@query(top_sql(_P1))
def band_topk(s, d):
    return band.band_search(W.planted_groups(s, d), _ONE, fill="none")


@query(fill_sql("planted_groups", top_sql(_P1)))
def band_topk_filled(s, d):
    return band.band_search(W.planted_groups(s, d), _ONE)


@query(top_sql(_P1))
def band_topk_dealt(s, d):
    """Buckets of more than 20 columns, joined block by block."""
    return band.band_search(W.planted_groups(s, d), replace(_ONE, max_bucket=20), fill="none")


@query(fill_sql("cust_brand", top_sql(pairs_sql(keys_sql(codes_sql(sums_sql("cust_brand", 4)), 1)), 23), 23))
def band_topk_of_few(s, d):
    """K = 23 of 25 columns."""
    return band.band_search(W.cust_brand(s, d), C.HashConfig(G=G, p=1, q=4, K=23, seed=SEED))


@query(fill_sql("supp_part", "select ''::bigint as j, 0::bigint as nbr, 0::bigint as freq, 0::bigint as k where false".replace("''", "0")))
def random_k(s, d):
    return baselines.random_k(W.supp_part(s, d), HASH.K, SEED)


def _min_sql(w: str, reps: int) -> str:
    return f"select j, rep, min({duck_int(f"concat('{SEED}:', rep, ':', i)", 15)}) as code from ({W.DUCK[w]}), range({reps}) t(rep) group by j, rep"


@query(_min_sql("cust_brand", 4))
def minhash_sig(s, d):
    return baselines.min_signatures(W.cust_brand(s, d), 4, SEED)


@query(top_sql(pairs_sql(f"select rep as grp, code as key, j from ({_min_sql('planted_groups', 4)})")))
def minhash_topk(s, d):
    return baselines.min_hash(W.planted_groups(s, d), C.HashConfig(p=1, q=4, K=4, seed=SEED, max_bucket=None), fill=False)


_U = lambda t, lane: f"({duck_int(f"concat('{SEED}:{t}:', i, ':', {lane})")} / 4294967296e0)"



def _cos_sql(w: str, reps: int) -> str:
    return "select j, rep, " + ", ".join(f"sum(r * sqrt(-2 * ln(greatest({_U('g1', f'rep * 4 + {k}')}, pow(2e0, -33)))) * cos(2 * pi() * {_U('g2', f'rep * 4 + {k}')})) as s{k}" for k in range(4)) + f" from ({W.DUCK[w]}), range({reps}) t(rep) group by j, rep"


_COS = _cos_sql("cust_brand", 2)


@query(f"select j, rep, ({' + '.join(f'case when s{k} >= 0 then {1 << k} else 0 end' for k in range(4))})::bigint as code from ({_COS})")
def cosine_codes(s, d):
    return signhash.codes(baselines.cosine_sums(W.cust_brand(s, d), 2, 4, SEED), 4)


_COS_CODES = codes_sql(_cos_sql("planted_groups", 6), 4)
add("cosine_hash_topk", lambda s, d: baselines.cosine_hash(W.planted_groups(s, d), C.HashConfig(G=4, p=1, q=6, K=4, seed=SEED)), fill_sql("planted_groups", top_sql(pairs_sql(f"select rep as grp, code as key, j from ({_COS_CODES})"))))
add("text_sign_topk", lambda s, d: baselines.text_sign_hash(W.term_doc(s, d), C.HashConfig(p=2, q=10, K=4, seed=SEED)), fill_sql("term_doc", top_sql(pairs_sql(keys_sql(codes_sql(sums_sql("term_doc", 20, "1e0")))))))
_POP = top_sql(pairs_sql(keys_sql(codes_sql(sums_sql("supp_part", 4)), 1)))
add(
    "popular_fill_topk",
    lambda s, d: band.band_search(W.supp_part(s, d), C.HashConfig(p=1, q=4, K=4, seed=SEED), fill="popular"),
    f"with im as ({W.DUCK['supp_part']}), tp as ({_POP}), po as (select j as nbr, count(*) as d from im group by j order by d desc, nbr limit 9),"
    " hv as (select a.j, count(tp.j) as have from (select distinct j from im) a left join tp on a.j = tp.j group by a.j),"
    " cc as (select hv.j, po.nbr, 0::bigint as freq, row_number() over (partition by hv.j order by d desc, po.nbr) + have as k from hv, po where have < 4 and po.nbr <> hv.j and not exists (select 1 from tp where tp.j = hv.j and tp.nbr = po.nbr))"
    " select j, nbr, freq, k from tp union all select j, nbr, freq, k from cc where k <= 4",
)

_PS, _QS = [1, 2, 3, 4], [25, 50, 100, 200]


@query(duck("cust_brand", f"select j1, j2, g.p, g.q, round(pow(prob, g.p), 9) as and_prob, round(1 - pow(1 - pow(prob, g.p), g.q), 9) as or_prob from jc, (select * from (select unnest({_PS})::int as p), (select unnest({_QS})::int as q)) g", ", dg as (select j, count(*) as d from im group by j), jc as (select j1, j2, ps.n / (a.d + b.d - ps.n) as prob from ps join dg a on a.j = j1 join dg b on b.j = j2)"))
def collision_theory(s, d):
    """Two columns' minima agree with a chance of their Jaccard similarity."""
    return theory.collision(graph.jaccard(W.cust_brand(s, d)).select("j1", "j2", "rho"), "rho", _PS, _QS)


@query(duck("cust_brand", f"select least(9, floor(s * 10))::bigint as bin, count(distinct j1 || '|' || j2) as n_pairs, count(*) filter (a.code = b.code) as n_agree, count(*) as n_codes from gr join cd a on a.j = j1 join cd b on b.j = j2 and a.rep = b.rep group by bin", f", cd as ({codes_sql(sums_sql('cust_brand', 8))})"))
def collision_empirical(s, d):
    im = W.cust_brand(s, d)
    return theory.empirical_curve(signhash.code_table(im, _ONE), graph.similarity_graph(im))


# ---- prediction, objective, steps
def setting(s, d, w: str = "planted_groups"):
    """(entries, neighbours, means, rows, columns, neighbour weights) with hashed starting values."""
    im = W.load_interactions(s, d, w).select("i", "j", "r")
    top = Scratch(s, "setting").keep(graph.topk(graph.similarity_graph(im), CFG.K))
    return im, top, biases.means(im), params.init_rows(im, CFG.F), params.init_cols(im, CFG.F), params.init_neighbours(top, SPREAD)


def _scored(s, d, parts=predict.PARTS):
    im, top, m, u, v, w = setting(s, d)
    return (im, top, m, u, v, w), predict.score(im, *m, u, v, top, w, parts)


@query(duck("planted", "select i as id, 'row' as side, round(b, 6) + 0e0 as dev from b union all select j, 'col', round(bh, 6) + 0e0 from bh union all select -1, 'mu', round(mu, 6) from mu"))
def baseline_means(s, d):
    mu, b, bh = biases.means(W.planted(s, d))
    x = b.select(F.col("i").alias("id"), F.lit("row").alias("side"), F.col("b").alias("dev")).union(bh.select("j", F.lit("col"), "bh")).union(mu.select(F.lit(-1).cast("long"), F.lit("mu"), "mu"))
    return r6(x, "dev")


def _split_sql(w: str) -> str:
    t = duck_int("concat('split:', i, ':', j)", 2)
    return f"with im as ({W.DUCK[w]}), tr as (select * from im where {t} >= 26), te as (select * from im where {t} < 26), mu as (select avg(r) as mu from tr), b as (select i, avg(r) - (select mu from mu) as b from tr group by i), bh as (select j, avg(r) - (select mu from mu) as bh from tr group by j), p as (select r, (select mu from mu) + coalesce(b, 0) + coalesce(bh, 0) as pred from te left join b using (i) left join bh using (j))"


@query(_split_sql("planted") + " select count(*) as n, round(sqrt(avg((r - pred) * (r - pred))), 6) as rmse, round(avg(abs(r - pred)), 6) as mae from p")
def baseline_rmse(s, d):
    tr, te = prep.split(W.planted(s, d))
    return r6(metrics.errors(biases.score(te, *biases.means(tr))), "rmse", "mae")


@query(duck("planted_groups", "select i, j, count(*) filter (kind = 'explicit') as n_explicit, count(*) filter (kind = 'implicit') as n_implicit from an group by i, j"))
def neighbour_sets(s, d):
    im, top, *_ = setting(s, d)
    return neigh.counts(neigh.attach(im, top))


@query(duck("planted_groups", f"select i, j, r, {d6('pred')}, n_ex, n_im from er"))
def predict_blend_init(s, d):
    return r6(_scored(s, d)[1].select("i", "j", "r", "pred", F.coalesce("n_ex", F.lit(0)).alias("n_ex"), F.coalesce("n_im", F.lit(0)).alias("n_im")), "pred")


_PARTS = {"base": "base", "explicit": "ex", "implicit": "imp", "factor": "d"}


@query(duck("planted_groups", " union all ".join(f"select '{k}' as part, round(sum({c}), 4) + 0e0 as total, round(sqrt(avg((r - {c}) * (r - {c}))), 6) as rmse from er" for k, c in _PARTS.items())))
def predict_parts_ablation(s, d):
    out = None
    (im, top, m, u, v, w), _ = _scored(s, d)
    for part in _PARTS:
        x = predict.score(im, *m, u, v, top, w, frozenset({part}))
        row = x.agg(F.lit(part).alias("part"), (F.round(F.sum("pred"), 4) + F.lit(0.0)).alias("total"), F.round(F.sqrt(F.avg((F.col("r") - F.col("pred")) ** 2)), 6).alias("rmse")).select("part", "total", "rmse")
        out = row if out is None else out.union(row)
    return out


_L = CFG.lam


@query(
    duck(
        "planted_groups",
        f"select {d6('data', 'pb', 'pbh', 'pu', 'pv', 'pw', 'pc', digits=4)}, round(data + pb + pbh + pu + pv + pw + pc, 4) as total from (select (select sum(e * e) from er) as data, (select sum(b * b) * {_L.b}e0 from b) as pb, (select sum(bh * bh) * {_L.bh}e0 from bh) as pbh, (select sum(u * u) * {_L.u}e0 from uf) as pu, (select sum(v * v) * {_L.v}e0 from vf) as pv,"
        f" (select sum(case when kind = 'explicit' then w * w else 0 end) * {_L.w}e0 from nr) as pw, (select sum(case when kind = 'implicit' then c * c else 0 end) * {_L.c}e0 from nr) as pc)",
    )
)
def objective_terms(s, d):
    (im, top, m, u, v, w), x = _scored(s, d)
    return r6(loss.objective(x, m[1], m[2], u, v, neigh.attach(im, top), w, _L), "data", "pb", "pbh", "pu", "pv", "pw", "pc", "total", digits=4)


@query(duck("planted_groups", f"select i, round(sum(e * e), 6) as data, any_value(round(pen, 6)) as penalty from er join (select i, sum(u * u) * {_L.u}e0 as pen from uf group by i) using (i) group by i"))
def objective_partial_u(s, d):
    (im, top, m, u, v, w), x = _scored(s, d)
    return r6(loss.partial(x, "u", u, _L), "data", "penalty")


@query(f"select t, count(*) as n_rows, round(0.04e0 / (1 + 0.3e0 * pow(t, 1.5e0)), 9) as gamma from (select count(*) - 1 as t from ({W.DUCK['planted']}) group by i) group by t")
def step_sizes(s, d):
    """The step size at the last entry of a row, its entries taken one after the other from t = 0 on."""
    last = W.planted(s, d).groupBy("i").agg((F.count(F.lit(1)) - 1).alias("t")).groupBy("t").agg(F.count(F.lit(1)).alias("n_rows"))
    return steps.rates_table(last, 0.04, 0.3)


def _step(mine: str, g: str, a: float, lam: float) -> str:
    return f"round({mine} + {a}e0 * ({g} - {lam}e0 * {mine}), 8) + 0e0"


_A = CFG.alpha


@query(duck("planted_groups", f"select i as id, 'b' as side, {_step('any_value(b)', 'avg(e)', _A.b, _L.b)} as val from er join b using (i) group by i union all select j, 'bh', {_step('any_value(bh)', 'avg(e)', _A.bh, _L.bh)} from er join bh using (j) group by j"))
def batch_step_bias(s, d):
    (im, top, m, u, v, w), x = _scored(s, d)
    e = steps.with_error(x).select("i", "j", "e")
    a = steps.step_b(e, m[1], CFG).select(F.col("i").alias("id"), F.lit("b").alias("side"), F.col("b").alias("val"))
    return r6(a.union(steps.step_bh(e, m[2], CFG).select("j", F.lit("bh"), "bh")), "val", digits=8)


@query(duck("planted_groups", f"select er.i, uf.f, {_step('any_value(uf.u)', 'avg(e * v)', _A.u, _L.u)} as u from er join uf on er.i = uf.i join vf on er.j = vf.j and uf.f = vf.f group by er.i, uf.f"))
def batch_step_u(s, d):
    (im, top, m, u, v, w), x = _scored(s, d)
    return r6(steps.step_u(steps.with_error(x), u, CFG).select("i", F.posexplode("u").alias("f", "u")).withColumn("f", F.col("f").cast("long")), "u", digits=8)


@query(duck("planted_groups", f"select er.j, vf.f, {_step('any_value(vf.v)', 'avg(e * u)', _A.v, _L.v)} as v from er join vf on er.j = vf.j join uf on er.i = uf.i and uf.f = vf.f group by er.j, vf.f"))
def batch_step_v(s, d):
    (im, top, m, u, v, w), x = _scored(s, d)
    return r6(steps.step_v(steps.with_error(x), v, CFG).select("j", F.posexplode("v").alias("f", "v")).withColumn("f", F.col("f").cast("long")), "v", digits=8)


@query(duck("planted_groups", f"select nr.j, nr.k, {_step('any_value(w)', 'avg(e * res / sqrt(n_ex))', _A.w, _L.w)} as w from nr join er on nr.i = er.i and nr.j = er.j where kind = 'explicit' group by nr.j, nr.k"))
def batch_step_w(s, d):
    (im, top, m, u, v, w), x = _scored(s, d)
    return r6(steps.step_w(steps.with_error(x), neigh.attach(im, top), *m, w, CFG), "w", digits=8)


@query(duck("planted_groups", f"select nr.j, nr.k, {_step('any_value(c)', 'avg(e / sqrt(n_im))', _A.c, _L.c)} as c from nr join er on nr.i = er.i and nr.j = er.j where kind = 'implicit' group by nr.j, nr.k"))
def batch_step_c(s, d):
    (im, top, m, u, v, w), x = _scored(s, d)
    return r6(steps.step_c(steps.with_error(x), neigh.attach(im, top), w, CFG), "c", digits=8)


@query(duck("planted_groups", f"select lo.i, uf.f, {_step('any_value(uf.u)', 'avg(e * v)', _A.u, _L.u)} as u from lo join uf on lo.i = uf.i join vf on lo.j = vf.j and uf.f = vf.f group by lo.i, uf.f", ", lo as (select i, j, case when r >= 4 then 1e0 else 0e0 end - 1 / (1 + exp(-d)) as e from er)"))
def logistic_step(s, d):
    im, top, m, u, v, w = setting(s, d)
    y = im.withColumn("r", F.when(F.col("r") >= 4, 1.0).otherwise(0.0))
    x = predict.score(y, *m, u, v, parts=frozenset({"factor"}))
    out = steps.step_u(steps.with_error(x, "logistic"), u, CFG.but(loss="logistic"))
    return r6(out.select("i", F.posexplode("u").alias("f", "u")).withColumn("f", F.col("f").cast("long")), "u", digits=8)


_V0 = f"(1 + {duck_int("concat('v0:', j)")} / 4294967296e0)"


def _rank_one(pen_u: str, pen_v: str) -> str:
    return f"with im as ({W.DUCK['cust_brand']}), v0 as (select j, {_V0} as v from (select distinct j from im)), u as (select i, sum(r * v) / ({pen_u} + sum(v * v)) as u from im join v0 using (j) group by i), v as (select j, sum(r * u) / ({pen_v} + sum(u * u)) as v from im join u using (i) group by j) select i::varchar as id, 'u' as side, round(u, 8) as val from u union all select j, 'v', round(v, 8) from v"


def _start_v(im):
    return im.select("j").distinct().withColumn("v", 1 + uniform(text("v0", F.col("j"))))


def _both_sides(u, v):
    return r6(u.select(F.col("i").cast("string").alias("id"), F.lit("u").alias("side"), F.col("u").alias("val")).union(v.select(F.col("j").cast("string"), F.lit("v"), "v")), "val", digits=8)


@query(_rank_one("0.05e0 * count(*)", "0.05e0 * count(*)"))
def ccd_sweep(s, d):
    im = W.cust_brand(s, d)
    return _both_sides(*steps.ccd_rank_one(im, _start_v(im), 0.05))


@query(_rank_one("0.1e0", "0.1e0"))
def als_rank1_sweep(s, d):
    im = W.cust_brand(s, d)
    return _both_sides(*steps.als_rank_one(im, _start_v(im), 0.1))


@query(duck("planted_groups", "select nm.i, nm.f, round(any_value(nm.u) * sum(r * v) / sum(p * v), 8) as u from fb join nm on fb.i = nm.i join vm on fb.j = vm.j and nm.f = vm.f group by nm.i, nm.f", ", nm as (select i, f, abs(u) + 0.1e0 as u from uf), vm as (select j, f, abs(v) + 0.1e0 as v from vf), fb as (select im.i, im.j, any_value(im.r) as r, sum(u * v) as p from im join nm on im.i = nm.i join vm on im.j = vm.j and nm.f = vm.f group by im.i, im.j)"))
def nmf_step(s, d):
    im = W.planted_groups(s, d)
    pos = lambda c: F.transform(c, lambda x: F.abs(x) + 0.1)
    u, v = params.init_rows(im, CFG.F).select("i", pos("u").alias("u")), params.init_cols(im, CFG.F).select("j", pos("v").alias("v"))
    x = im.join(u, "i").join(v, "j").withColumn("pred", params.dot("u", "v"))
    return r6(steps.nmf_rows(x, u, CFG.F).select("i", F.posexplode("u").alias("f", "u")).withColumn("f", F.col("f").cast("long")), "u", digits=8)


# ---- blocks
def _hash24(axis: str) -> str:
    return duck_int(f"concat('blk:{axis}:', {axis})") + " % 24"


@query(
    f"with h as (select {_hash24('i')} as a, {_hash24('j')} as b, count(*) as n from ({W.DUCK['planted']}) group by 1, 2),"
    " p as (select d, s as step, w as worker, (w + s - 2) % d + 1 as row_block, w as col_block from (select unnest([1, 2, 3, 4, 8])::bigint as d), range(1, 9) a(s), range(1, 9) b(w) where s <= d and w <= d)"
    " select d, step, worker, row_block, col_block, coalesce(sum(n), 0)::bigint as entries from p left join h on a % d = row_block - 1 and b % d = col_block - 1 group by all"
)
def rotation_plan(s, d):
    """The rotation by number of blocks, with the entries that a worker has in a step."""
    ds = (1, 2, 3, 4, 8)
    plan = s.createDataFrame([(n, *p) for n in ds for p in train.plan(n)], "d long, step long, worker long, row_block long, col_block long")
    # a block of 24 lies in one block of every d, so entries are hashed and counted once
    fine = W.planted(s, d).groupBy(train.block_of("i", F.col("i"), 24).alias("a"), train.block_of("j", F.col("j"), 24).alias("b")).agg(F.count(F.lit(1)).alias("n"))
    x = fine.withColumn("d", F.explode(F.array(*[F.lit(n).cast("long") for n in ds])))
    x = x.groupBy("d", (F.col("a") % F.col("d") + 1).alias("row_block"), (F.col("b") % F.col("d") + 1).alias("col_block")).agg(F.sum("n").alias("entries"))
    return plan.join(x, ["d", "row_block", "col_block"], "left").select(*plan.columns, F.coalesce("entries", F.lit(0)).cast("long").alias("entries"))


def _blk(axis: str) -> str:
    return duck_int(f"concat('blk:{axis}:', {axis})") + " % 4"


@query(f"select 'i' as axis, i as id, {_blk('i')} as block from (select distinct i from ({W.DUCK['planted']})) union all select 'j', j, {_blk('j')} from (select distinct j from ({W.DUCK['planted']}))")
def block_assign(s, d):
    im = W.planted(s, d)
    one = lambda a: im.select(a).distinct().select(F.lit(a).alias("axis"), F.col(a).alias("id"), train.block_of(a, F.col(a), 4).alias("block"))
    return one("i").union(one("j"))


@query(f"select {_blk('i')} as row_block, {_blk('j')} as col_block, count(*) as n from ({W.DUCK['planted']}) group by 1, 2")
def block_counts(s, d):
    x = W.planted(s, d).select(train.block_of("i", F.col("i"), 4).alias("row_block"), train.block_of("j", F.col("j"), 4).alias("col_block"))
    return x.groupBy("row_block", "col_block").agg(F.count(F.lit(1)).alias("n"))


# ---- measures
@query(duck("planted_groups", "select count(*) as n, round(sqrt(avg((r - pred) * (r - pred) * 400)), 6) as rmse, round(avg(abs((r - pred) * 20)), 6) as mae from er"))
def rmse_eval(s, d):
    return r6(metrics.errors(_scored(s, d)[1], 20.0), "rmse", "mae")


@query(
    f"with im as ({W.DUCK['user_key']}), h as (select i, j from (select i, j, row_number() over (partition by i order by md5(concat('loo:', i, ':', j)) desc, j desc) as p from im) where p = 1), c as ({_NEG}),"
    " n as (select i, j from c where not exists (select 1 from im where im.i = c.i and im.j = c.j)), pop as (select j, count(*)::double as score from im group by j),"
    " x as (select i, j, 1 as y from h union all select i, j, 0 from n), z as (select i, j, y, coalesce(score, 0) as score from x left join pop using (j)), r as (select *, row_number() over (partition by i order by score desc, j) as place from z)"
    " select (select count(distinct i) from x where y = 1) as n, round(count(*) / (select count(distinct i) from x where y = 1), 6) as hr, round(sum(1 / log2(place + 1)) / (select count(distinct i) from x where y = 1), 6) as ndcg from r where y = 1 and place <= 10"
)
def hit_ratio(s, d):
    im = W.user_key(s, d).select("i", "j", "r")
    held = prep.leave_one_out(im).where("held").select("i", "j", F.lit(1).alias("y"))
    neg = prep.negatives(im.select("i").distinct(), im, 100, 20).select("i", "j", F.lit(0).alias("y"))
    pop = im.groupBy("j").agg(F.count(F.lit(1)).cast("double").alias("score"))
    x = held.union(neg).join(pop, "j", "left").select("i", "j", "y", F.coalesce("score", F.lit(0.0)).alias("score"))
    return r6(metrics.hit_ratio(x), "hr", "ndcg")


@query(duck("planted_groups", "select (select count(*) from tp) as n_exact, (select count(*) from ap) as n_approx, count(*) as n_common, round(count(*) / (select count(*) from tp), 6) as recall, round(count(*) / (select count(*) from ap), 6) as precision from tp join ap using (j, nbr)", f", ap as ({top_sql(_P1)})"))
def topk_recall(s, d):
    im = W.planted_groups(s, d)
    return r6(metrics.topk_recall(band.band_search(im, _ONE, fill="none"), graph.topk(graph.similarity_graph(im), 4)), "recall", "precision")


@query(f"select round(avg(case when j % 5 = nbr % 5 then 1e0 else 0e0 end), 6) as purity from ({top_sql(_P1)})")
def group_purity(s, d):
    return r6(metrics.group_purity(band.band_search(W.planted_groups(s, d), _ONE, fill="none"), lambda c: c % 5), "purity")


_NS = {"A": 17770, "B": 10677, "C": 12658}


_NS_OF = ("planted", "planted_groups", "user_key")
_NS_SQL = " union all ".join(f"select '{w}' as name, count(distinct j) as n from ({W.DUCK[w]})" for w in _NS_OF)


def _ns(s, d) -> DataFrame:
    """(name, n): the columns of three workloads."""
    one = [W.load_interactions(s, d, w).agg(F.count_distinct("j").alias("n")).select(F.lit(w).alias("name"), "n") for w in _NS_OF]
    return one[0].union(one[1]).union(one[2])


@query(f"select name, method, n, bytes, round(bytes / 1048576e0, 3) as mib from (select name, method, n, (case method when 'random' then 0 when 'graph' then 4 * n * n when 'hash100' then 4 * n * 300 else 4 * n * 600 end)::bigint as bytes from ({_NS_SQL}), (select unnest(['random', 'graph', 'hash100', 'hash200']) as method))")
def space_table(s, d):
    n = F.col("n")
    sizes = {"random": F.lit(0), "graph": cost.space_bytes("graph", n), "hash100": cost.space_bytes("hash", n, 3, 100), "hash200": cost.space_bytes("hash", n, 3, 200)}
    one = [F.struct(F.lit(m).alias("method"), "n", b.cast("long").alias("bytes")) for m, b in sizes.items()]
    return _ns(s, d).select("name", F.inline(F.array(*one))).withColumn("mib", F.round(F.col("bytes") / 2**20, 3))


@query(f"select name, n, n * (n - 1) as build, 2 * n * 32 - 1024 + 32 as query, n * (2 * n * 32 - 1024 + 32) as all_queries, n * (n - 1) + n * (2 * n * 32 - 1024 + 32) as total from ({_NS_SQL})")
def graph_ops(s, d):
    return _ns(s, d).withColumns(cost.graph_ops(F.col("n"), 32))


@query(f"select n, q, 3 * q * n as codes, 3 * q * 8 * (select count(*) from ({W.DUCK['planted']})) as additions from (select unnest({list(_NS.values())})::bigint as n), (select unnest([100, 200])::bigint as q)")
def hash_ops(s, d):
    e = W.planted(s, d).agg(F.count(F.lit(1)).alias("e"))
    grid = s.createDataFrame([(n, q) for n in _NS.values() for q in (100, 200)], "n long, q long")
    return grid.crossJoin(F.broadcast(e)).select("n", "q", (3 * F.col("q") * F.col("n")).alias("codes"), (24 * F.col("q") * F.col("e")).alias("additions"))


@query(f"select count(*) as entries, count(distinct i) as m, count(distinct j) as n, count(*) + 32 * count(distinct i) + 32 * count(distinct j) + 96 * count(distinct j) as cells from ({W.DUCK['planted']})")
def model_cells(s, d):
    p = W.planted(s, d).agg(F.count(F.lit(1)).alias("entries"), F.count_distinct("i").alias("m"), F.count_distinct("j").alias("n"))
    return p.withColumn("cells", F.col("entries") + F.col("m") * 32 + F.col("n") * 32 + 3 * F.col("n") * 32)


@query(f"select model, case model when 'factor' then (m + n) * 8 when 'blend' then m * 9 + n * (9 + 16) when 'net_product' then (m + n) * 8 + 9 when 'net_mlp' then (m + n) * 8 + 17 * 16 + 17 * 8 + 9 else 2 * (m + n) * 8 + 17 * 16 + 17 * 8 + 17 end as params from (select count(distinct i) as m, count(distinct j) as n from ({W.DUCK['planted']})), (select unnest(['factor', 'blend', 'net_product', 'net_mlp', 'net_fused']) as model)")
def model_params(s, d):
    x = W.planted(s, d).agg(F.count_distinct("i").alias("m"), F.count_distinct("j").alias("n"))
    one = lambda m: F.struct(F.lit(m).alias("model"), cost.model_params(m, F.col("m"), F.col("n"), 8, 8, (16, 8)).alias("params"))
    return x.select(F.inline(F.array(*[one(m) for m in ("factor", "blend", "net_product", "net_mlp", "net_fused")])))


@query(duck("planted_groups", "select i, j, round(score, 6) + 0e0 as score, place from (select uf.i, vf.j, sum(u * v) as score, row_number() over (partition by uf.i order by sum(u * v) desc, vf.j) as place from uf join vf using (f) where uf.i % 100 = 0 group by uf.i, vf.j) where place <= 3"))
def recommend_topn(s, d):
    im = W.planted_groups(s, d)
    rows = params.init_rows(im, CFG.F).where("i % 100 = 0")  # the query set of a search: ids divisible by 100, against all columns
    return r6(predict.recommend(rows, params.init_cols(im, CFG.F), 3), "score")


# ---- online
_NEW_I = f"{duck_int("concat('newi:', i)")} < {int(0.05 * 2**32)}"


@query(sums_sql("cust_brand", 2))
def merge_sums(s, d):
    im, c = W.cust_brand(s, d), C.HashConfig(p=1, q=2, seed=SEED)
    return online.merge_sums(signhash.accumulate(im.where(~prep.is_new("i", 0.05)), c), signhash.accumulate(im.where(prep.is_new("i", 0.05)), c))


@query(codes_sql(sums_sql("cust_brand", 2)))
def online_codes(s, d):
    im, c = W.cust_brand(s, d), C.HashConfig(p=1, q=2, seed=SEED)
    return online.update_codes(signhash.accumulate(im.where(~prep.is_new("i", 0.05)), c), im.where(prep.is_new("i", 0.05)), c)[1]


_KEYS1 = keys_sql(codes_sql(sums_sql("planted_groups", _ONE.reps)), 1)


@query(f"with k as ({_KEYS1}) select j, nbr, freq, k from (select a.j, b.j as nbr, count(*) as freq, row_number() over (partition by a.j order by count(*) desc, b.j) as k from k a join k b on a.grp = b.grp and a.key = b.key and a.j <> b.j where {duck_int("concat('newj:', a.j)")} < {int(0.05 * 2**32)} group by a.j, b.j) where k <= 4")
def online_new_topk(s, d):
    im = W.planted_groups(s, d)
    keys = band.keys(signhash.code_table(im, _ONE), 1)
    return online.search_new(keys, im.select("j").distinct().where(prep.is_new("j", 0.05)), 4)


# ---- training runs (no SQL form: iterative)
def _history(s, model) -> DataFrame:
    return s.createDataFrame([(h["epoch"], round(h["rmse"], 6)) for h in model.history], "epoch int, rmse double")


def _data(s, d, w="planted_groups"):
    return prep.split(W.load_interactions(s, d, w).select("i", "j", "r"))


def _factor(**k):
    return C.FACTOR_PRESETS["stars"].but(F=8, epochs=3, D=2, **k)


def _blend(**k):
    return C.BLEND_PRESETS["stars"].but(F=8, K=8, epochs=3, D=2, **k)


def _hash_top(tr, k=8):
    return band.band_search(tr, C.HashConfig(p=1, q=50, K=k, seed=SEED))


@query()
def train_resident(s, d):
    tr, te = _data(s, d)
    return _history(s, train.resident_sgd(tr, _factor(), test=te))


@query()
def train_resident_columns(s, d):
    tr, te = _data(s, d)
    return _history(s, train.resident_sgd(tr, _factor(), side="col", test=te))


@query()
def train_entry(s, d):
    tr, te = _data(s, d)
    return _history(s, train.entry_sgd(tr, _factor(), test=te))


@query()
def train_entry_minibatch(s, d):
    tr, te = _data(s, d)
    return _history(s, train.entry_sgd(tr, _factor(), mode="minibatch", test=te))


@query()
def train_als(s, d):
    tr, te = _data(s, d)
    h = train.als(tr, 8, 0.1, 3, test=te)[2]
    return s.createDataFrame([(x["epoch"], round(x["rmse"], 6)) for x in h], "epoch int, rmse double")


@query()
def train_als_library(s, d):
    tr, te = _data(s, d)
    m = train.als_library(tr, 8, 0.05, 3)
    p = m.transform(te.select(F.col("i").cast("int").alias("i"), F.col("j").cast("int").alias("j"), "r")).withColumnRenamed("prediction", "pred")
    return metrics.errors(p)


@query()
def train_ccd(s, d):
    tr, te = _data(s, d)
    u, v = train.ccd(tr, 2)
    return metrics.errors(te.join(u, "i").join(v, "j").withColumn("pred", params.dot("u", "v")))


@query()
def train_nmf(s, d):
    tr, te = _data(s, d)
    u, v = train.nmf(tr, 4, 3)
    return metrics.errors(te.join(u, "i").join(v, "j").withColumn("pred", params.dot("u", "v")))


@query()
def train_blend(s, d):
    tr, te = _data(s, d)
    return _history(s, train.blend_mf(tr, _hash_top(tr), _blend(), te))


@query()
def train_blend_exact(s, d):
    tr, te = _data(s, d)
    return _history(s, train.blend_mf(tr, graph.topk(graph.similarity_graph(tr), 8), _blend(), te))


@query()
def train_blend_random(s, d):
    tr, te = _data(s, d)
    return _history(s, train.blend_mf(tr, baselines.random_k(tr, 8, SEED), _blend(), te))


@query()
def train_bias_factor(s, d):
    tr, te = _data(s, d)
    return _history(s, train.factor_bias_sgd(tr, _blend(), te))


@query()
def train_rotation(s, d):
    tr, te = _data(s, d)
    return _history(s, train.rotation(tr, _factor(), 4, test=te))


@query()
def train_logistic(s, d):
    im = W.planted_groups(s, d).select("i", "j", F.when(F.col("r") >= 4, 1.0).otherwise(0.0).alias("r"))
    tr, te = prep.split(im)
    m = train._train(tr, _factor(loss="logistic", parts=frozenset({"base", "factor"})).but(use_bias=True, alpha=C.Rates(0.1, 0.1, 0.1, 0.1, 0, 0)), None, None)
    p = train.score(m, te).withColumn("pred", loss.sigmoid(F.col("pred")))
    return metrics.errors(p)


@query()
def online_train(s, d):
    im = W.planted_groups(s, d).select("i", "j", "r")
    old, new = prep.online_split(im, 0.05, 0.05)
    (otr, _), (ntr, nte) = prep.split(old), prep.split(new)
    m = train.factor_bias_sgd(otr, _blend())
    up = online.online_update(m, ntr)
    before = metrics.errors(train.score(m, nte)).select(F.lit("before").alias("state"), "n", "rmse")
    return before.union(metrics.errors(train.score(up, nte)).select(F.lit("after"), "n", "rmse"))


@query()
def noise_gap(s, d):
    tr, te = _data(s, d)
    clean = train.factor_bias_sgd(tr, _blend(), te).history[-1]["rmse"]
    rows = [(x, round(metrics.noise_gap(clean, train.factor_bias_sgd(prep.inject_noise(tr, x), _blend(), te).history[-1]["rmse"]), 6)) for x in (0.01, 0.1)]
    return s.createDataFrame(rows, "rate double, gap double")


def _net(fn):
    def run(s, d):
        im = W.user_key(s, d).select("i", "j", "r")
        loo = prep.leave_one_out(im)
        held, pos = loo.where("held"), loo.where("not held")
        neg = prep.negatives(held.select("i"), im, 100, 30)
        cand = held.select("i", "j", F.lit(1).alias("y")).union(neg.select("i", "j", F.lit(0).alias("y")))
        net = fn(neural.examples(pos, 2), neural.NetConfig(F=4, layers=(8, 4), epochs=2, D=2))
        return metrics.hit_ratio(neural.score(net, cand))

    return run


add("net_product", _net(neural.net_product))
add("net_mlp", _net(neural.net_mlp))
add("net_fused", _net(neural.net_fused))

for _name, _fn in experiments.ALL.items():
    add(_name, _fn)

for _name, _fn, _sql in [*relational.entries(), *streams.entries()]:
    add(_name, _fn, _sql)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hashed top-K neighbours of documents over their terms."""
    return band.band_search(W.term_doc(spark, sf_dir), C.HashConfig(p=2, q=20, K=8, seed=SEED))


def queries() -> dict:
    return {k: f for k, (f, _) in REGISTRY.items()}


def oracle_sql() -> dict:
    return {k: q for k, (_, q) in REGISTRY.items() if q}


__all__ = ["REGISTRY", "flagship", "oracle_sql", "queries"]
