"""Near-duplicate documents by b-bit MinHash.

Documents are sets of 5-word shingles. BANDS * ROWS minima are taken; a band's key is a hash of its full minima, the
signature keeps only the low BITS of each minimum, packed. Documents that share a band's key are candidates; inside a
candidate group the packed signatures are compared by bit counts, the share of agreeing minima is corrected for
chance collisions of the low bits, and pairs whose corrected estimate is within five standard errors of the limit are
confirmed on their full sets. Linked documents form components; the smallest doc_id of a component stays.

How large groups stay bounded: documents with equal word sequences are one class from the start (classes are keyed by
a 128-bit hash of the sequence); a band's bucket gives star edges only (each member to the smallest), which yield
candidate groups; a group is cut into blocks by measured bytes and every pair of blocks is one task that reads two
blocks of sets, never emits a pair, and returns a spanning forest of its confirmed links. Nothing is capped.

Defined cases: a text without words, or null, has an empty set, is linked with nothing and stays; fewer than 5 words
make one shingle of the whole sequence; equal texts are linked; null doc_ids can be linked but are no component's id
while another id is there; repeated rows give equal results, one per row; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lowrank_spark.llm.columns import shield, unshield
from lowrank_spark.llm.components import connected
from lowrank_spark.runtime import Scratch, maybe_broadcast, ship_package

BANDS = 25
ROWS = 5
BITS = 8
SHINGLE = 5
LIMIT_PCT = 85
#: Bytes of shingle sets in one block of a candidate group.
BLOCK_BYTES = 24 << 20
BLOCK_ROWS = 1500
_WORD = re.compile(rb"[^\x20\x09-\x0D]+")
#: Words whose hashes a worker remembers while a task runs.
_MEMO = 200_000
_MIX = np.uint64(0x9E3779B97F4A7C15)


class _WordHashes(dict):
    """64-bit hash of a word, remembered."""

    def __missing__(self, w: bytes) -> int:
        if len(self) >= _MEMO:
            self.clear()
        h = self[w] = int.from_bytes(hashlib.blake2b(w, digest_size=8).digest(), "little")
        return h


_HASHES = _WordHashes()


def _finish(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit mixer."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def word_hashes(text: str | None) -> np.ndarray:
    words = _WORD.findall((text or "").encode("utf-8", "surrogatepass").lower())
    return np.fromiter(map(_HASHES.__getitem__, words), np.uint64, len(words))


def shingles(h: np.ndarray) -> np.ndarray:
    """Sorted distinct shingle hashes of a word sequence."""
    n = len(h)
    if n == 0:
        return h
    k = min(n, SHINGLE)
    x = np.zeros(n - k + 1, np.uint64)
    for i in range(k):
        x = _finish(x * _MIX + h[i : n - k + 1 + i])
    if n < SHINGLE:
        x = _finish(x + np.uint64(n))
    return np.unique(x)


def class_key(h: np.ndarray) -> bytes:
    return hashlib.blake2b(h.tobytes(), digest_size=16).digest()


def _constants() -> tuple[np.ndarray, np.ndarray]:
    n = BANDS * ROWS
    raw = np.frombuffer(b"".join(hashlib.blake2b(b"minhash:%d" % i, digest_size=16).digest() for i in range(n)), np.uint64).reshape(n, 2)
    return raw[:, 0:1] | np.uint64(1), raw[:, 1:2]


def minima(s: np.ndarray, a: np.ndarray, c: np.ndarray) -> np.ndarray:
    """The minimum of each hash function over the set, by pieces of the set."""
    out = None
    for i in range(0, len(s), 4096):
        m = ((s[None, i : i + 4096] ^ c) * a).min(axis=1)
        out = m if out is None else np.minimum(out, m)
    return out


def signature(m: np.ndarray) -> tuple[bytes, np.ndarray]:
    """(low BITS of the finished minima, packed; one 64-bit key a band)."""
    m = _finish(m)
    low = (m & np.uint64((1 << BITS) - 1)).astype(np.uint8)
    if BITS < 8:
        low = np.packbits(np.unpackbits(low[:, None], axis=1)[:, 8 - BITS :].ravel())
    key = np.arange(1, BANDS + 1, dtype=np.uint64)
    for col in m.reshape(BANDS, ROWS).T:
        key = _finish(key * _MIX + col)
    return low.tobytes(), key.astype(np.int64)


def estimate(row: np.ndarray, others: np.ndarray) -> np.ndarray:
    """Collision-corrected similarity of one packed signature to many, from bit counts of their differences.

    A minimum agrees when none of its BITS bits differ; b low bits agree by chance with probability 2^-b.
    """
    diff = np.bitwise_xor(others, row)
    if BITS == 8:
        same = np.count_nonzero(diff == 0, axis=1)
    else:
        bits = np.unpackbits(diff, axis=1)[:, : BANDS * ROWS * BITS].reshape(len(others), BANDS * ROWS, BITS)
        same = np.count_nonzero(bits.sum(axis=2) == 0, axis=1)
    by_chance = 2.0**-BITS
    return (same / (BANDS * ROWS) - by_chance) / (1 - by_chance)


def estimate_floor(limit: float) -> float:
    """The limit less five standard errors of the estimate."""
    return limit - 5 * (limit * (1 - limit) / (BANDS * ROWS)) ** 0.5


SIGN_SCHEMA = "doc_id long, cls binary, n_shingles long, sig binary, keys array<long>"


def sign_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    ship_package(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a, c = _constants()
        _HASHES.clear()
        for b in batches:
            cls, n, sig, keys = [], [], [], []
            for t in b.column(1):
                h = word_hashes(t.as_py())
                s = shingles(h)
                cls.append(class_key(h))
                n.append(len(s))
                if len(s):
                    packed, k = signature(minima(s, a, c))
                    sig.append(packed)
                    keys.append(k)
                else:
                    sig.append(None)
                    keys.append(None)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(cls, pa.binary()), pa.array(n, pa.int64()), pa.array(sig, pa.binary()), pa.array(keys, pa.list_(pa.int64()))], names=["doc_id", "cls", "n_shingles", "sig", "keys"])
        _HASHES.clear()

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, SIGN_SCHEMA)


def _sets_of(docs: DataFrame) -> DataFrame:
    """(cls, group, blocks, sig, set) of rows (text, cls, group, blocks, sig); the class is checked again."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            t = b.to_pydict()
            out = {"cls": [], "grp": [], "blocks": [], "sig": [], "set": []}
            for text, cls, grp, blocks, sig in zip(t["text"], t["cls"], t["grp"], t["blocks"], t["sig"], strict=True):
                h = word_hashes(text)
                if class_key(h) == cls:
                    for k, v in zip(out, (cls, grp, blocks, sig, shingles(h).tobytes()), strict=True):
                        out[k].append(v)
            types = (pa.binary(), pa.binary(), pa.int64(), pa.binary(), pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array(v, ty) for v, ty in zip(out.values(), types, strict=True)], names=list(out))
        _HASHES.clear()

    return docs.select("text", "cls", "grp", "blocks", "sig").mapInArrow(run, "cls binary, grp binary, blocks long, sig binary, set binary")


class _Forest:
    def __init__(self, n: int):
        self.up = list(range(n))

    def root(self, i: int) -> int:
        while self.up[i] != i:
            self.up[i] = i = self.up[self.up[i]]
        return i

    def join(self, i: int, j: int) -> bool:
        i, j = self.root(i), self.root(j)
        if i == j:
            return False
        self.up[max(i, j)] = min(i, j)
        return True


def confirm_pairs(sets: list[np.ndarray], sigs: np.ndarray, side: np.ndarray, one_block: bool, limit_pct: int = LIMIT_PCT) -> list[tuple[int, int]]:
    """Spanning links of the confirmed pairs, all pairs of a block or all pairs across two blocks.

    For each row: estimates to the later rows by bit counts, then one pass over the concatenated sets of those that
    are near enough and in another tree than the row.
    """
    n = len(sets)
    size = np.array([len(s) for s in sets], np.int64)
    values, flat = np.unique(np.concatenate(sets), return_inverse=True)
    start = np.concatenate([[0], np.cumsum(size)])
    hit = np.zeros(len(values), bool)
    floor = estimate_floor(limit_pct / 100)
    forest, links = _Forest(n), []
    roots = np.arange(n)
    for i in range(n - 1):
        later = np.arange(i + 1, n)
        if not one_block:
            later = later[side[i + 1 :] != side[i]]
        later = later[roots[later] != roots[i]]
        if not len(later):
            continue
        # a set's size bounds the similarity
        lo, hi = np.minimum(size[later], size[i]), np.maximum(size[later], size[i])
        later = later[100 * lo >= limit_pct * hi]
        if not len(later):
            continue
        est = estimate(sigs[i], sigs[later])
        later = later[est >= floor]
        if not len(later):
            continue
        mine = flat[start[i] : start[i + 1]]
        hit[mine] = True
        for j in later:
            if roots[j] == roots[i]:
                continue
            both = int(np.count_nonzero(hit[flat[start[j] : start[j + 1]]]))
            if 100 * both >= limit_pct * (size[i] + size[j] - both):
                forest.join(i, int(j))
                links.append((i, int(j)))
                a, b = roots[i], roots[j]
                roots[roots == max(a, b)] = min(a, b)
        hit[mine] = False
    return links


def _confirm(members: DataFrame, limit_pct: int) -> DataFrame:
    """Star-free spanning links of every (group, block pair)."""

    def run(table: pa.Table) -> pa.Table:
        t = table.to_pydict()
        order = sorted(range(len(t["cls"])), key=lambda i: (t["blk"][i], t["cls"][i]))
        cls = [t["cls"][i] for i in order]
        side = np.array([t["blk"][i] for i in order], np.int64)
        sets = [np.frombuffer(t["set"][i], np.uint64) for i in order]
        sigs = np.frombuffer(b"".join(t["sig"][i] for i in order), np.uint8).reshape(len(order), -1)
        one = t["bi"][0] == t["bj"][0]
        links = confirm_pairs(sets, sigs, side, one, limit_pct) if len(cls) > 1 else []
        return pa.table({"a": pa.array([cls[i] for i, _ in links], pa.binary()), "b": pa.array([cls[j] for _, j in links], pa.binary())})

    return members.groupBy("grp", "bi", "bj").applyInArrow(run, "a binary, b binary")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", limit_pct: int = LIMIT_PCT) -> DataFrame:
    """(doc_id, n_shingles, cls, component_id, kept), one row a document."""
    spark = docs.sparkSession
    scratch = Scratch(spark, "minhash")
    signed = scratch.keep(sign_documents(docs, id_col, text_col))
    classes = signed.where("n_shingles > 0").groupBy("cls").agg(F.min("doc_id").alias("doc_id"), F.first("n_shingles").alias("n"), F.first("sig").alias("sig"), F.first("keys").alias("keys"))
    classes = scratch.keep(classes)
    banded = classes.select("cls", F.explode("keys").alias("key"))
    hubs = banded.groupBy("key").agg(F.min("cls").alias("hub"), F.count(F.lit(1)).alias("m")).where("m > 1").select("key", "hub")
    stars = banded.join(hubs, "key").where("cls != hub").select("cls", "hub")
    groups = scratch.keep(connected(stars, scratch))
    members = scratch.keep(groups.join(classes.drop("keys"), groups["node"] == classes["cls"]).select("cls", F.col("comp").alias("grp"), "doc_id", "n", "sig"))
    blocks = members.groupBy("grp").agg(F.greatest(F.ceil(F.sum(F.col("n") * 8 + 200) / BLOCK_BYTES), F.ceil(F.count(F.lit(1)) / BLOCK_ROWS)).cast("long").alias("blocks"))
    wanted = members.join(blocks, "grp").select(F.col("doc_id").alias("_id"), "cls", "grp", "blocks", "sig")
    text = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    found = wanted.join(text, wanted["_id"].eqNullSafe(text["doc_id"]))
    sets = _sets_of(found).dropDuplicates(["cls"]) if _repeats(signed) else _sets_of(found)
    blk = F.pmod(F.xxhash64("cls"), F.col("blocks"))
    pairs = F.transform(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1), lambda k: F.struct(F.least(k, F.col("blk")).alias("bi"), F.greatest(k, F.col("blk")).alias("bj")))
    dealt = sets.withColumn("blk", blk).withColumn("p", F.explode(pairs)).select("grp", "cls", "sig", "set", "blk", F.col("p.bi").alias("bi"), F.col("p.bj").alias("bj"))
    links = scratch.keep(_confirm(dealt, limit_pct))
    comp = connected(links, scratch)
    by_class = signed.groupBy("cls").agg(F.min("doc_id").alias("low"), F.max("n_shingles").alias("n"))
    known = scratch.keep(by_class.join(comp, by_class["cls"] == comp["node"], "left").select("cls", "low", "n", F.coalesce("comp", "cls").alias("comp")))
    low = known.groupBy("comp").agg(F.min("low").alias("component"))
    final = scratch.keep(known.join(low, "comp").select("cls", "component"))
    out = signed.select("doc_id", "n_shingles", "cls").join(final, "cls", "left")
    component = F.when(F.col("n_shingles") > 0, F.col("component")).otherwise(F.col("doc_id"))
    return out.select("doc_id", "n_shingles", "cls", component.alias("component_id")).withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.col("component_id").isNull()))


def _repeats(signed: DataFrame) -> bool:
    """Whether any doc_id stands in several rows (then a class may be found more than once)."""
    return bool(signed.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1").limit(1).collect())


def minhash_stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group; same columns as documents.

    Only the ids that go are joined (a doc_id goes when none of its rows stays), so the texts are not shuffled while
    those ids are few; rows repeated whole are made one where a doc_id stands in several rows at all.
    """
    ids = near_duplicates(docs).groupBy("doc_id").agg(F.bool_or("kept").alias("stays"), F.count(F.lit(1)).alias("n"))
    ids = Scratch(spark, "minhash-stage").keep(ids.where("not stays or n > 1"))
    out = ids.where("not stays").select(F.col("doc_id").alias("_id"))
    out = maybe_broadcast(out, out.count(), 16)
    mine = shield(docs, ("doc_id", "text"))
    left = mine.join(out, mine["doc_id"].eqNullSafe(out["_id"]), "left_anti")
    return unshield(left.dropDuplicates(["doc_id", "text"]) if ids.where("n > 1").limit(1).collect() else left, docs)


def op1_minhash(spark, sf_dir: str) -> DataFrame:
    d = near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
    return d.select("doc_id", "n_shingles", "component_id", "kept")


SQL = r"""
with w as (select row_number() over () as rid, doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') as ws from documents),
sh as (select distinct rid, md5(array_to_string(ws[p:p + 4], ' ')) as s from (select rid, ws, unnest(range(1, greatest(len(ws) - 3, 2))) as p from w where len(ws) > 0)),
n as (select rid, count(*) as n from sh group by rid),
rare as (select s from sh group by s having count(*) > 1),
pairs as (select a.rid as x, b.rid as y, count(*) as cap_n from sh a join rare using (s) join sh b using (s) where a.rid < b.rid group by a.rid, b.rid),
links as (select x, y from pairs join n a on a.rid = x join n b on b.rid = y where 100 * cap_n >= 85 * (a.n + b.n - cap_n)),
e as (select x, y from links union all select y, x from links),
reach as (with recursive r(a, b) as (select rid, rid from w union select r.a, e.y from r join e on r.b = e.x) select a, b from r),
c as (select a as rid, min(doc_id) as component_id from reach join w on w.rid = b group by a)
select doc_id, coalesce(n, 0)::bigint as n_shingles, component_id, doc_id = component_id as kept from w left join n using (rid) join c using (rid)
"""
