"""Value-weighted sign hashing of sparse columns.

Row i has G pseudo-random signs for every repetition: a pure function of (seed, i, repetition), so no table of codes
is stored, joined or broadcast. A column's sum adds sign * psi(r) over its rows; the code's bit is 1 where the sum is
not negative. Sums are a commutative monoid: partial sums merge in any order, which is what the online form rests on.

Two physical forms give the same numbers: `accumulate` (all JVM; one row a repetition) for few repetitions, and
`accumulate_gathered` (a numpy kernel over streamed batches of a column's rows) for hundreds.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from lowrank_spark.config import HashConfig
from lowrank_spark.functions.hashing import text
from lowrank_spark.runtime import ship_package

PSI = {
    "ones": lambda r: F.lit(1.0) + r * 0,
    "identity": lambda r: r,
    "square": lambda r: r * F.abs(r),
    "fourth": lambda r: r * r * r * F.abs(r),
}


def weight(psi, r: Column) -> Column:
    """psi(r): a named weighting (the sign of r is kept) or any Column -> Column function."""
    return psi(r) if callable(psi) else PSI[psi](r)


def sign_byte(seed: int, i: Column, byte: Column) -> Column:
    """Byte `byte` of row i's stream of bits: md5 of 'seed:i:block', 16 bytes a block."""
    block = F.floor(byte / 16).cast("long")
    at = (2 * (byte % 16) + 1).cast("int")
    return F.conv(F.substr(F.md5(text(seed, i, block)), at, F.lit(2)), 16, 10).cast("int")


def _bit(cfg: HashConfig, i: Column, rep: Column, lane: int) -> Column:
    t = rep * cfg.G + lane
    if cfg.family == "fast":
        h = F.xxhash64(F.lit(cfg.seed), i.cast("string"), F.floor(t / 64).cast("long"))
        return F.getbit(h, (t % 64).cast("int")).cast("int")
    return F.getbit(sign_byte(cfg.seed, i, F.floor(t / 8).cast("long")), (t % 8).cast("int")).cast("int")


def row_signs(rows: DataFrame, cfg: HashConfig, reps: int | None = None) -> DataFrame:
    """(i, rep, code): the G bits of each row and repetition as a number; a set bit is the sign +1."""
    r = rows.select("i", F.explode(F.sequence(F.lit(0), F.lit((reps or cfg.reps) - 1))).alias("rep"))
    code = sum((_bit(cfg, F.col("i"), F.col("rep"), g).cast("long") * F.lit(1 << g) for g in range(cfg.G)), F.lit(0).cast("long"))
    return r.select("i", F.col("rep").cast("long").alias("rep"), code.alias("code"))


def accumulate(im: DataFrame, cfg: HashConfig, reps: int | None = None) -> DataFrame:
    """(j, rep, s0 .. s{G-1}): signed sums, all in the JVM, combined map-side."""
    x = im.select("i", "j", weight(cfg.psi, F.col("r")).alias("w"), F.explode(F.sequence(F.lit(0), F.lit((reps or cfg.reps) - 1))).alias("rep"))
    if cfg.family == "portable" and cfg.G == 8:
        x = x.withColumn("_b", sign_byte(cfg.seed, F.col("i"), F.col("rep").cast("long")))
        bit = lambda g: F.getbit(F.col("_b"), F.lit(g))
    else:
        bit = lambda g: _bit(cfg, F.col("i"), F.col("rep"), g)
    lanes = [F.sum(F.when(bit(g) == 1, F.col("w")).otherwise(-F.col("w"))).alias(f"s{g}") for g in range(cfg.G)]
    return x.groupBy("j", F.col("rep").cast("long").alias("rep")).agg(*lanes)


def codes(acc: DataFrame, g: int = 8) -> DataFrame:
    """(j, rep, code): bit k is 1 where the k-th sum is at least 0."""
    code = sum((F.when(F.col(f"s{k}") >= 0, F.lit(1 << k)).otherwise(F.lit(0)).cast("long") for k in range(g)), F.lit(0).cast("long"))
    return acc.select("j", "rep", code.alias("code"))


class SignStream:
    """Signs of rows as +-1 vectors of n lanes, for both families; remembered per worker up to a bound."""

    def __init__(self, seed: int, lanes: int, keep: int = 20_000):
        self.seed, self.lanes, self.keep, self.memo = seed, lanes, keep, {}

    def of(self, i) -> np.ndarray:
        s = self.memo.get(i)
        if s is None:
            n = (self.lanes + 127) // 128
            raw = b"".join(hashlib.md5(f"{self.seed}:{i}:{b}".encode()).digest() for b in range(n))
            bits = np.unpackbits(np.frombuffer(raw, np.uint8), bitorder="little")[: self.lanes]
            s = bits.astype(np.int8) * 2 - 1
            if len(self.memo) >= self.keep:
                self.memo.clear()
            self.memo[i] = s
        return s


def signed_sums(signs: np.ndarray, weights: np.ndarray) -> np.ndarray:
    """Sums over rows of sign * weight for every lane."""
    return weights @ signs


_STREAMS: dict[tuple[int, int], SignStream] = {}


def _stream(seed: int, lanes: int) -> SignStream:
    if (seed, lanes) not in _STREAMS:
        _STREAMS.clear()
        _STREAMS[seed, lanes] = SignStream(seed, lanes)
    return _STREAMS[seed, lanes]


def pack(sums: np.ndarray, g: int) -> np.ndarray:
    """Codes of g bits from sums (columns x lanes)."""
    bits = (sums >= 0).reshape(len(sums), -1, g)
    return (bits * (1 << np.arange(g, dtype=np.int64))).sum(axis=2)


def accumulate_gathered(im: DataFrame, cfg: HashConfig, out: str = "sums") -> DataFrame:
    """(j, sums array<double>) of p*q*G lanes, or (j, codes array<long>) with out='codes'.

    Entries are dealt by j and stream through in order of j; a column's partial sum is carried from batch to batch, so
    neither a heavy column nor many light ones cost more than the batch in hand.
    """
    if cfg.family != "portable":
        raise ValueError("the gathered form uses the portable family")
    ship_package(im.sparkSession)
    lanes, seed, g = cfg.reps * cfg.G, cfg.seed, cfg.G
    x = im.select("j", F.col("i").cast("string").alias("i"), weight(cfg.psi, F.col("r")).cast("double").alias("w"))
    jt = x.schema["j"].dataType.simpleString()

    def emit(js, sums, jtype):
        for lo in range(0, len(js), 256):  # a batch of many short columns goes out in slices
            m = np.array(sums[lo : lo + 256]).reshape(-1, lanes)
            v = pa.array(list(m), pa.list_(pa.float64())) if out == "sums" else pa.array(list(pack(m, g)), pa.list_(pa.int64()))
            yield pa.RecordBatch.from_arrays([pa.array(js[lo : lo + 256], jtype), v], names=["j", out])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        stream = _stream(seed, lanes)
        now, total, jtype = None, None, None
        for b in batches:
            jtype = b.column(0).type
            js, rows, w = b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_numpy()
            done_j, done_s = [], []
            for lo in range(0, len(js), 1000):
                part = js[lo : lo + 1000]
                signed = np.stack([stream.of(i) for i in rows[lo : lo + 1000]]) * w[lo : lo + 1000, None]
                cuts = [0] + [n for n in range(1, len(part)) if part[n] != part[n - 1]]
                for j, s in zip([part[n] for n in cuts], np.add.reduceat(signed, cuts, axis=0), strict=True):
                    if total is not None and j == now:
                        total = total + s
                        continue
                    if total is not None:
                        done_j.append(now)
                        done_s.append(total)
                    now, total = j, s
            if done_j:
                yield from emit(done_j, done_s, jtype)
        if total is not None:
            yield from emit([now], [total], jtype)

    return x.repartition("j").sortWithinPartitions("j").mapInArrow(run, f"j {jt}, {out} array<{'double' if out == 'sums' else 'bigint'}>")


def code_table(im: DataFrame, cfg: HashConfig) -> DataFrame:
    """(j, rep, code) by the form that fits the number of repetitions."""
    if cfg.reps <= 16 or cfg.family != "portable":
        return codes(accumulate(im, cfg), cfg.G)
    return accumulate_gathered(im, cfg, "codes").select("j", F.posexplode("codes").alias("rep", "code")).select("j", F.col("rep").cast("long").alias("rep"), "code")


def hash_of_example(values, bits) -> tuple[list[float], list[int]]:
    """(sums, code bits) of one column given its rows' bits: the definition, for worked examples."""
    signs = np.array(bits) * 2 - 1
    sums = signed_sums(signs, np.array(values, float))
    return sums.tolist(), [int(s >= 0) for s in sums]


__all__ = ["PSI", "SignStream", "accumulate", "accumulate_gathered", "code_table", "codes", "hash_of_example", "pack", "row_signs", "sign_byte", "signed_sums", "weight"]
