"""Sharding through a permutation-filled lookup table.

Every shard has its own preference order over the slots of a prime-sized table (an offset and a step from its name;
a step coprime to a prime visits every slot). Shards take turns, each claiming the next free slot it prefers, until
the table is full: slots differ by one between shards of equal weight, and losing a shard moves little else. The
table's size is a parameter, not a function of the data, so it is broadcast and a row's shard is one hash and one
lookup, with no shuffle.

Native: DataFrame functions only on the rows. Defined cases: a null key hashes like Spark's hash of null and gets one
fixed slot; repeated keys share a shard; an empty table gives an empty result; keys of any length are hashed whole; other
columns are carried untouched, but columns named slot or shard come back as in_slot and in_shard.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SLOTS = 65_537
MAX_SLOTS = 1_000_003
SHARDS = 64


def _number(text: str) -> int:
    return int.from_bytes(hashlib.md5(text.encode()).digest()[:8], "big")


def fill_table(shards: list[str], slots: int = SLOTS, weights: list[int] | None = None) -> list[int]:
    """Slot -> index of its shard. `weights` are turns in a round (1 each by default)."""
    if not shards:
        raise ValueError("no shards")
    if not len(shards) <= slots <= MAX_SLOTS or any(slots % f == 0 for f in range(2, int(slots**0.5) + 1)):
        raise ValueError(f"slots must be a prime from the number of shards to {MAX_SLOTS}")
    turns = weights or [1] * len(shards)
    if len(turns) != len(shards) or min(turns) < 1:
        raise ValueError("one weight of at least 1 for each shard")
    at = [_number(f"offset:{s}") % slots for s in shards]
    step = [_number(f"step:{s}") % (slots - 1) + 1 for s in shards]
    table, free = [-1] * slots, slots
    while True:
        for k, n in enumerate(turns):
            for _ in range(n):
                p = at[k]
                while table[p] >= 0:
                    p = (p + step[k]) % slots
                table[p] = k
                at[k] = (p + step[k]) % slots
                free -= 1
                if not free:
                    return table


def shard_names(n: int) -> list[str]:
    return [f"shard-{i:05d}" for i in range(n)]


def table_frame(spark, shards: list[str], slots: int = SLOTS, weights: list[int] | None = None) -> DataFrame:
    t = fill_table(shards, slots, weights)
    return spark.createDataFrame([(i, shards[k]) for i, k in enumerate(t)], "slot long, shard string")


def place(docs: DataFrame, key_col: str, shards: list[str], slots: int = SLOTS, weights: list[int] | None = None) -> DataFrame:
    """docs + slot and shard. The broadcast side has `slots` rows (at most MAX_SLOTS)."""
    table = table_frame(docs.sparkSession, shards, slots, weights)
    own = [F.col(f"`{c}`").alias(f"in_{c}" if c in ("slot", "shard") else c) for c in docs.columns]
    x = docs.select(*own, F.pmod(F.xxhash64(F.col(f"`{key_col}`")), F.lit(slots)).alias("slot"))
    return x.join(F.broadcast(table), "slot", "left").select(*x.columns, "shard")


def write_shards(docs: DataFrame, key_col: str, shards: list[str], path: str, files_a_shard: int = 8, **options) -> None:
    """One folder a shard; each shard's rows are dealt over several tasks, so a hot shard is no single task."""
    d = place(docs, key_col, shards, **options)
    key = F.col(f"`in_{key_col}`" if key_col in ("slot", "shard") else f"`{key_col}`")
    d.repartition("shard", F.pmod(F.xxhash64(key, F.lit(1)), F.lit(files_a_shard))).write.partitionBy("shard").parquet(path)


def disruption(before: list[int], after: list[int], old: list[str], new: list[str]) -> float:
    """Share of slots of surviving shards that changed hands between two tables of one size."""
    live = [(old[a], new[b]) for a, b in zip(before, after, strict=True) if old[a] in set(new)]
    return sum(x != y for x, y in live) / max(1, len(live))


def op9_sharding(spark, sf_dir: str) -> DataFrame:
    """Whole documents, each with its slot and shard."""
    return place(spark.read.parquet(f"{sf_dir}/documents.parquet"), "doc_id", shard_names(SHARDS))
