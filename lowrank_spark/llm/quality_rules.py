"""Quality rules with cross-document line frequency.

A normalised line is boilerplate of a host when it stands in at least `min_docs` different texts of the host and in
at least `share` of all of them (exact copies of a text count once, so copying a page does not turn its prose into
boilerplate). `op2_quality_rules` and its SQL form use SHARE; the pipeline's stage uses the count alone, so a line goes
from a large host as from a small one. Boilerplate is removed; a document that loses words and keeps too few of them is
depleted and rejected. Base rules (word count, repeated 8-word windows) stand beside it.

The list of boilerplate lines is broadcast after its size is measured; where it is too large the lines are joined by
(host, line) instead.

Native: DataFrame functions only. Defined cases: null text counts as the empty text (no words, so base_failed);
null host is the host ''; every input row gives one row, repeated or not, with null or repeated doc_ids; an empty
table gives an empty result; other input columns do not matter, and the stage gives them back as they came, whatever
their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from lowrank_spark.functions.staging import once
from lowrank_spark.llm.columns import shield, unshield
from lowrank_spark.runtime import BROADCAST_BYTES, Scratch

SPACE = r"[\x20\x09-\x0D]+"
WINDOW = 8
MIN_WORDS = 20
MAX_REPEAT_PCT = 30
MIN_DOCS = 10
SHARE = 0.1
MIN_LEFT_PCT = 30
MIN_LEFT_WORDS = 20
_DOC = 0  # stands for the text itself among its line hashes


def words_of(text: Column) -> Column:
    return F.filter(F.split(text, SPACE), lambda w: w != "")


def normal_line(line: Column) -> Column:
    """Lower case, digits as 0, runs of white space as one space, ends trimmed."""
    return F.trim(F.regexp_replace(F.regexp_replace(F.lower(line), r"\d", "0"), r"\s+", " "))


def _line_hash(line: Column) -> Column:
    return F.xxhash64(normal_line(line))


def line_frequencies(docs: DataFrame, text_col: str = "text", host_col: str = "source") -> DataFrame:
    """(host, line, n_docs): distinct texts of the host with the line; line 0 counts all texts of the host.

    Distinct first by (host, line, text), so a hot host or line spreads over all tasks; the counts are then
    combined map-side.
    """
    d = docs.select(F.coalesce(F.col(host_col), F.lit("")).alias("host"), F.coalesce(F.col(text_col), F.lit("")).alias("t"))
    d = d.select("host", F.xxhash64("t").alias("th"), F.filter(F.split("t", "\n", -1), lambda x: F.length(F.trim(x)) > 0).alias("lines"))
    d = d.select("host", "th", F.array_union(F.array(F.lit(_DOC).cast("long")), F.transform("lines", _line_hash)).alias("ls"))
    return d.select("host", "th", F.explode("ls").alias("line")).distinct().groupBy("host", "line").agg(F.count(F.lit(1)).alias("n_docs"))


def boilerplate(freq: DataFrame, min_docs: int = MIN_DOCS, share: float = SHARE) -> DataFrame:
    """(host, line) above both limits."""
    often = freq.where(F.col("n_docs") >= min_docs)
    total = often.where(F.col("line") == _DOC).select("host", F.col("n_docs").alias("of"))
    return often.where(F.col("line") != _DOC).join(total, "host").where(F.col("n_docs") >= F.col("of") * share).select("host", "line")


def base_counts(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """Adds n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words and base_failed."""
    t = F.coalesce(F.col(text_col), F.lit(""))
    d = once(docs, {"_w": words_of(t), "_l": F.filter(F.split(t, "\n", -1), lambda x: x.rlike(r"[^\x20\x09-\x0D]")), "n_symbols": F.length(F.regexp_replace(t, r"[^#*$%&|<>]+", "")).cast("long")})
    windows = F.transform(F.sequence(F.lit(1), F.size("_w") - (WINDOW - 1)), lambda i: F.xxhash64(F.slice(F.col("_w"), i, WINDOW)))
    d = once(
        d,
        {
            "n_words": F.size("_w").cast("long"),
            "word_chars": F.length(F.array_join("_w", "")).cast("long"),
            "n_dup_lines": (F.size("_l") - F.size(F.array_distinct("_l"))).cast("long"),
            "_h": F.when(F.size("_w") >= WINDOW, windows),
        },
        [c for c in d.columns if c != "_l"],
    )
    repeats = F.size("_h") > F.size(F.array_distinct("_h"))
    d = once(d, {"_s": F.when(repeats, F.array_sort(F.transform("_h", lambda x, i: F.struct(x.alias("h"), i.alias("p")))))}, [c for c in d.columns if c not in ("_h", "_w")])

    def same(e: Column, i: Column) -> Column:
        return F.coalesce(F.get(F.col("_s"), i - 1)["h"] == e["h"], F.lit(False)) | F.coalesce(F.get(F.col("_s"), i + 1)["h"] == e["h"], F.lit(False))

    at = F.array_sort(F.transform(F.filter("_s", same), lambda e: e["p"]))
    none = F.struct(F.lit(-WINDOW).alias("last"), F.lit(0).alias("n"))
    cover = F.aggregate(at, none, lambda a, p: F.struct(p.alias("last"), (a["n"] + F.least(F.lit(WINDOW), p - a["last"])).alias("n")), lambda a: a["n"])
    d = once(d, {"n_repeat_words": F.coalesce(cover, F.lit(0)).cast("long")}, [c for c in d.columns if c != "_s"])
    return d.withColumn("base_failed", (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEAT_PCT * F.col("n_words")))


def mark_boilerplate(docs: DataFrame, text_col: str = "text", host_col: str = "source", min_docs: int = MIN_DOCS, share: float = SHARE) -> DataFrame:
    """Adds clean_text (boilerplate lines taken out; null only for a null text) and n_removed_words."""
    spark = docs.sparkSession
    scratch = Scratch(spark, "lines")
    # both sides of the share need the counts: written once, the texts are split and hashed once
    freq = boilerplate(scratch.keep(line_frequencies(docs, text_col, host_col).where(F.col("n_docs") >= min_docs)), min_docs, share)
    listed = scratch.keep(freq.groupBy("host").agg(F.collect_list("line").alias("_freq")))
    size = listed.agg(F.count(F.lit(1)), F.sum(F.size("_freq")), F.sum(F.length("host"))).first()
    small = size[0] * 64 + (size[1] or 0) * 8 + (size[2] or 0) * 4 <= BROADCAST_BYTES
    d = docs.withColumn("_host", F.coalesce(F.col(host_col), F.lit("")))
    if small:
        d = d.join(F.broadcast(listed.withColumnRenamed("host", "_host")), "_host", "left")
    else:  # the join by host would bring a hot host's texts together: only the lists of lines move instead
        key = F.xxhash64("_host", F.coalesce(F.col(text_col), F.lit("")))
        lines = F.explode(F.array_distinct(F.transform(F.split(text_col, "\n", -1), _line_hash)))
        hit = d.select("_host", key.alias("_k"), lines.alias("line")).join(freq.withColumnRenamed("host", "_host"), ["_host", "line"])
        d = d.withColumn("_k", key).join(hit.groupBy("_k").agg(F.collect_set("line").alias("_freq")), "_k", "left").drop("_k")
    is_out = lambda x: F.array_contains(F.col("_freq"), _line_hash(x))
    d = once(d, {"_marks": F.when(F.size("_freq") > 0, F.transform(F.split(text_col, "\n", -1), lambda x: F.struct(x.alias("x"), is_out(x).alias("out"))))})
    pick = lambda out: F.array_join(F.transform(F.filter("_marks", lambda m: m["out"] == F.lit(out)), lambda m: m["x"]), "\n")
    any_out = F.exists("_marks", lambda m: m["out"])
    gone = F.when(any_out, F.size(words_of(pick(True)))).otherwise(0).cast("long")
    return once(d, {"n_removed_words": gone, "clean_text": F.when(any_out, pick(False)).otherwise(F.col(text_col))}, [c for c in d.columns if c not in ("_host", "_freq", "_marks")])


def depleted() -> Column:
    left = F.col("n_words") - F.col("n_removed_words")
    return (F.col("n_removed_words") > 0) & ((left < MIN_LEFT_WORDS) | (100 * left < MIN_LEFT_PCT * F.col("n_words")))


def judge(docs: DataFrame, text_col: str = "text", host_col: str = "source", share: float = SHARE) -> DataFrame:
    """docs with the counts, clean_text, and kept: the rules' verdict."""
    d = base_counts(mark_boilerplate(docs, text_col, host_col, share=share), text_col)
    return d.withColumn("kept", ~F.col("base_failed") & ~depleted())


def quality_stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass, without their hosts' boilerplate lines; same columns as documents."""
    mine = shield(docs, ("doc_id", "text", "source", "n_chars"))
    d = judge(mine, share=0.0).where("kept")
    d = d.withColumn("text", F.col("clean_text")).withColumn("n_chars", F.length("text").cast("long"))
    return unshield(d, docs)


def op2_quality_rules(spark, sf_dir: str) -> DataFrame:
    d = judge(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "source"))
    return d.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "n_removed_words")


SQL = rf"""
with d as (select row_number() over () as rid, doc_id, coalesce(text, '') as t, coalesce(source, '') as host from documents),
w as (select rid, list_filter(string_split_regex(t, '{SPACE}'), lambda x: x <> '') as ws, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) as ls from d),
win as (select rid, p, array_to_string(ws[p:p + 7], ' ') as k from (select rid, ws, unnest(range(1, len(ws) - 6)) as p from w where len(ws) >= 8)),
dup as (select rid, p from (select rid, p, count(*) over (partition by rid, k) as n from win) where n > 1),
cov as (select rid, sum(least(8, coalesce(p - before, 8))) as n from (select rid, p, lag(p) over (partition by rid order by p) as before from dup) group by rid),
li as (select distinct rid, host, md5(t) as th, trim(regexp_replace(regexp_replace(lower(x), '\d', '0', 'g'), '\s+', ' ', 'g')) as line, x
       from (select rid, host, t, unnest(string_split(t, chr(10))) as x from d)),
fr as (select host, line, count(distinct th) as n_docs from li where line <> '' group by host, line having count(distinct th) >= {MIN_DOCS}),
tot as (select host, count(distinct md5(t)) as of from d group by host),
bp as (select host, line from fr join tot using (host) where n_docs >= of * {SHARE}),
allines as (select rid, host, unnest(string_split(t, chr(10))) as x from d),
rem as (select rid, sum(len(list_filter(string_split_regex(x, '{SPACE}'), lambda z: z <> ''))) as n
        from (select rid, host, x, trim(regexp_replace(regexp_replace(lower(x), '\d', '0', 'g'), '\s+', ' ', 'g')) as line from allines) join bp using (host, line) group by rid),
c as (select d.rid, doc_id, len(ws)::bigint as n_words, length(array_to_string(ws, ''))::bigint as word_chars,
        length(regexp_replace(t, '[^#*$%&|<>]+', '', 'g'))::bigint as n_symbols, (len(ls) - len(list_distinct(ls)))::bigint as n_dup_lines,
        coalesce(cov.n, 0)::bigint as n_repeat_words, coalesce(rem.n, 0)::bigint as n_removed_words
      from d join w using (rid) left join cov using (rid) left join rem using (rid)),
b as (select *, n_words < {MIN_WORDS} or 100 * n_repeat_words > {MAX_REPEAT_PCT} * n_words as base_failed from c)
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
  not base_failed and not (n_removed_words > 0 and (n_words - n_removed_words < {MIN_LEFT_WORDS} or 100 * (n_words - n_removed_words) < {MIN_LEFT_PCT} * n_words)) as kept, n_removed_words
from b
"""
