"""Secret scans with corpus-wide ownership.

Each text is searched for base kinds (assignments, access keys, long hexadecimal runs) and for tokens of high entropy.
Every candidate value is hashed; over the corpus the distinct owners and repositories of a hash are counted. A value
that several owners carry is a copied example; a varied value that stays with its owner looks live, and its places
are added as kind `live`. Base places are never taken away.

Counts: rows are made distinct by (hash, owner, repository) with map-side combining before they are counted, so a
value that stands everywhere is no hot spot. Only hashes and offsets are shuffled, never texts.

Defined cases: null text counts as empty; null owners or repositories count as one of their own; repeated rows
(same doc_id and text) give equal results, one per row; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lowrank_spark.runtime import Scratch, ship_package

KINDS = ("assign", "access", "hex", "live")
# The base patterns and the least lengths.
_ASSIGN = re.compile(r"""((?ai:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""")
_ACCESS = re.compile(r"AKIA[A-Z0-9]+")
_HEX = re.compile(r"[0-9a-f]{16,}")
LEAST = {"assign": 12, "access": 18, "hex": 16}

_TOKEN = re.compile(r"[A-Za-z0-9+/_=-]{20,}")
#: Bits a character from which a value counts as varied, and owners from which it counts as a copied example.
ENTROPY = 3.0
EXAMPLE_OWNERS = 3
EXAMPLE_REPOS = 5


def entropy(value: str) -> float:
    n = len(value)
    return -sum(c / n * math.log2(c / n) for c in Counter(value).values())


def base_places(text: str) -> list[tuple[int, int, int, int]]:
    """(start, kind, end, start of the value) by start, then kind."""
    out = [(m.start(), 0, m.end(), m.start(2)) for m in _ASSIGN.finditer(text) if m.end(2) - m.start(2) >= LEAST["assign"]]
    out += [(m.start(), 1, m.end(), m.start()) for m in _ACCESS.finditer(text) if m.end() - m.start() >= LEAST["access"]]
    out += [(m.start(), 2, m.end(), m.start()) for m in _HEX.finditer(text)]
    return sorted(out)


def candidates(text: str, base: list[tuple[int, int, int, int]]) -> list[tuple[int, int]]:
    """(start, end) of values that may be live: varied ones, of base places and of free tokens with letters and digits."""
    out = {(v, e) for _, _, e, v in base if entropy(text[v:e]) >= ENTROPY}
    for m in _TOKEN.finditer(text):
        x = m[0]
        if any(c.isdigit() for c in x) and any(c.isalpha() for c in x) and entropy(x) >= ENTROPY:
            out.add(m.span())
    return sorted(out)


def _hash(value: str) -> int:
    return int.from_bytes(hashlib.blake2b(value.encode("utf-8", "surrogatepass"), digest_size=8).digest(), "big", signed=True)


_CAND = pa.list_(pa.struct([("h", pa.int64()), ("s", pa.int32()), ("e", pa.int32())]))
_BASE = pa.list_(pa.struct([("s", pa.int32()), ("k", pa.int32()), ("e", pa.int32())]))
SCHEMA = "doc_id long, th long, owner string, repo string, n_assign long, n_access long, n_hex long, base_sha256 string, base array<struct<s: int, k: int, e: int>>, cands array<struct<h: long, s: int, e: int>>"


def scan_texts(docs: DataFrame) -> DataFrame:
    """Per row of (doc_id, th, owner, repo, text): base places and candidate hashes."""
    ship_package(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            n, sha, base, cands = ([], [], []), [], [], []
            for t in b.column(4):
                text = t.as_py() or ""
                found = base_places(text)
                for k in range(3):
                    n[k].append(sum(x[1] == k for x in found))
                sha.append(hashlib.sha256(",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e, _ in found).encode()).hexdigest())
                base.append([{"s": s, "k": k, "e": e} for s, k, e, _ in found])
                cands.append([{"h": _hash(text[s:e]), "s": s, "e": e} for s, e in candidates(text, found)])
            cols = [b.column(i) for i in range(4)] + [pa.array(x, pa.int64()) for x in n]
            cols += [pa.array(sha, pa.string()), pa.array(base, _BASE), pa.array(cands, _CAND)]
            yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "th", "owner", "repo", "n_assign", "n_access", "n_hex", "base_sha256", "base", "cands"])

    return docs.mapInArrow(run, SCHEMA)


def ownership(cands: DataFrame) -> DataFrame:
    """(h, owners, repos) of rows (h, owner, repo)."""
    one = cands.select("h", "owner", "repo").distinct()
    return one.groupBy("h", "owner").agg(F.count(F.lit(1)).alias("r")).groupBy("h").agg(F.count(F.lit(1)).alias("owners"), F.sum("r").alias("repos"))


def find_secrets(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", owner_col: str = "source", repo_cols: tuple = ("source", "lang")) -> DataFrame:
    """doc_id, base counts and digest, all places with their kind, and how many values are live or shared."""
    scratch = Scratch(docs.sparkSession, "secrets")
    repo = F.concat_ws("/", *[F.coalesce(F.col(c).cast("string"), F.lit("\x00")) for c in repo_cols])
    src = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(text_col).alias("th"), F.coalesce(F.col(owner_col).cast("string"), F.lit("\x00")).alias("owner"), repo.alias("repo"), F.col(text_col).alias("text"))
    seen = scratch.keep(scan_texts(src))
    each = seen.where(F.size("cands") > 0).select("doc_id", "th", "owner", "repo", F.explode("cands").alias("c")).select("doc_id", "th", "owner", "repo", "c.h", "c.s", "c.e")
    own = scratch.keep(ownership(each).select("h", ((F.col("owners") < EXAMPLE_OWNERS) & (F.col("repos") < EXAMPLE_REPOS)).alias("is_live")))
    judged = each.select("doc_id", "th", "h", "s", "e").distinct().join(own, "h")
    live = judged.groupBy("doc_id", "th").agg(
        F.collect_list(F.when(F.col("is_live"), F.struct("s", F.lit(3).alias("k"), "e"))).alias("live"), F.count_if(~F.col("is_live")).alias("n_shared")
    )
    live = live.select(F.col("doc_id").alias("_id"), F.col("th").alias("_th"), "live", "n_shared")
    j = seen.drop("cands", "owner", "repo").join(live, seen["doc_id"].eqNullSafe(live["_id"]) & (seen["th"] == live["_th"]), "left")
    both = F.array_sort(F.concat("base", F.coalesce("live", F.array().cast("array<struct<s: int, k: int, e: int>>"))))
    names = F.array(*[F.lit(k) for k in KINDS])
    places = F.transform(both, lambda x: F.struct(F.element_at(names, x["k"] + 1).alias("kind"), x["s"].alias("start"), x["e"].alias("end")))
    return j.select("doc_id", "n_assign", "n_access", "n_hex", "base_sha256", places.alias("places"), F.coalesce(F.size("live"), F.lit(0)).cast("long").alias("n_live"), F.coalesce("n_shared", F.lit(0)).cast("long").alias("n_shared"))


def op3_secret_owners(spark, sf_dir: str) -> DataFrame:
    d = find_secrets(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    text = F.array_join(F.transform("places", lambda p: F.concat_ws(":", p["kind"], p["start"].cast("string"), p["end"].cast("string"))), ",")
    return d.select("doc_id", "n_assign", "n_access", "n_hex", "base_sha256", text.alias("spans"), "n_live", "n_shared")
