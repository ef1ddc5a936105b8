"""Angles of all pairs of short dense columns beside the agreement of their codes, block by block.

Columns are packed into blocks of BLOCK; every pair of blocks is one row of a product of two scans, and a numpy kernel
adds its pairs up by angle. No pair becomes a row.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lowrank_spark.runtime import Scratch, ship_package

BLOCK = 512


def packed(vectors: DataFrame, codes: DataFrame) -> DataFrame:
    """(id, n, x, d, code): blocks of columns with their values by row number (n x width), norms and codes (n x repetitions)."""

    def row(part: list[tuple]) -> pa.RecordBatch:
        width = 1 + max(e["i"] for _, e_, _ in part for e in e_)
        x, d = np.zeros((len(part), width)), np.zeros(len(part))
        for n, (_, entries, _) in enumerate(part):
            i = np.array([e["i"] for e in entries])
            r = np.array([0.0 if e["r"] is None else e["r"] for e in entries])
            np.add.at(x[n], i, r)
            d[n] = math.sqrt(float((r * r).sum()))
        c = np.array([c for _, _, c in part], np.int64)
        values = [[part[0][0]], [len(part)], [x.tobytes()], [d.tobytes()], [c.tobytes()]]
        types = [pa.int64(), pa.int32(), pa.binary(), pa.binary(), pa.binary()]
        return pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(values, types, strict=True)], names=["id", "n", "x", "d", "code"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        for b in batches:
            for lo in range(0, b.num_rows, BLOCK):
                held += zip(*[c.to_pylist() for c in b.slice(lo, BLOCK).columns], strict=True)
                while len(held) >= BLOCK:
                    yield row(held[:BLOCK])
                    held = held[BLOCK:]
        if held:
            yield row(held)

    ship_package(vectors.sparkSession)
    v = vectors.where("i is not null and j is not null").groupBy("j").agg(F.collect_list(F.struct("i", "r")).alias("e"))
    c = codes.groupBy("j").agg(F.array_sort(F.collect_list(F.struct("rep", "code"))).alias("c")).select("j", F.transform("c", lambda t: t["code"]).alias("c"))
    return v.join(c, "j").select("j", "e", "c").mapInArrow(run, "id long, n int, x binary, d binary, code binary")


def by_angle(vectors: DataFrame, codes: DataFrame) -> DataFrame:
    """(bin, pairs, differ, turn): pairs of columns, code bits that differ and the sum of angle / pi, by angle / pi to one digit.

    vectors: (i, j, r) with few row numbers i from 0 on, codes: (j, rep, code). Columns of length 0 stand at right angles to all.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in batches:
            for r in t.to_pylist():
                side = lambda s: (np.frombuffer(r[f"x_{s}"]).reshape(r[f"n_{s}"], -1), np.frombuffer(r[f"d_{s}"]), np.frombuffer(r[f"code_{s}"], np.int64).reshape(r[f"n_{s}"], -1))  # noqa: B023, E731
                (xa, da, ca), (xb, db, cb) = side("a"), side("b")
                width = min(xa.shape[1], xb.shape[1])
                with np.errstate(all="ignore"):
                    size = da[:, None] * db[None, :]
                    rho = np.where(size == 0, 0.0, (xa[:, :width] @ xb[:, :width].T) / size)
                rho = np.clip(np.where(np.isnan(rho), 1.0, rho), -1.0, 1.0)
                turn = np.arccos(rho) / math.pi
                differ = np.zeros(turn.shape, np.int64)
                for k in range(ca.shape[1]):
                    differ += np.bitwise_count(ca[:, None, k] ^ cb[None, :, k])
                ok = np.triu(np.ones(turn.shape, bool), 1) if r["id_a"] == r["id_b"] else np.ones(turn.shape, bool)
                at = np.floor(turn * 10 + 0.5).astype(np.int64)[ok]
                add = lambda w: np.bincount(at, w, 11)  # noqa: B023, E731
                n = np.bincount(at, minlength=11)
                yield pa.RecordBatch.from_arrays([pa.array(np.arange(11) / 10), pa.array(n), pa.array(add(differ[ok]).astype(np.int64)), pa.array(add(turn[ok]))], names=["bin", "pairs", "differ", "turn"])

    blocks = Scratch(vectors.sparkSession, "angles").keep(packed(vectors, codes))
    side = lambda s: blocks.select(*[F.col(c).alias(f"{c}_{s}") for c in blocks.columns])
    j = side("a").hint("shuffle_replicate_nl").join(side("b"), F.col("id_a") <= F.col("id_b"))
    parts = j.mapInArrow(run, "bin double, pairs long, differ long, turn double").where("pairs > 0")
    return parts.groupBy("bin").agg(F.sum("pairs").alias("pairs"), F.sum("differ").alias("differ"), F.sum("turn").alias("turn"))
