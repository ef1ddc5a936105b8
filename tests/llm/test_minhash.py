import random

import numpy as np
from pyspark.sql import types as T

from lowrank_spark.llm import minhash_dedup as m

S = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("n_shingles", T.StringType())])


def words(t):
    import re

    low = "".join(c.lower() if "A" <= c <= "Z" else c for c in t or "")
    return [w for w in re.split(r"[\x20\x09-\x0D]+", low) if w]


def shingle_set(t):
    w = words(t)
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def brute(rows):
    sets = [shingle_set(t) for _, t in rows]
    up = list(range(len(rows)))

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            a, b = sets[i], sets[j]
            if a and b and 100 * len(a & b) >= 85 * len(a | b):
                up[max(root(i), root(j))] = min(root(i), root(j))
    out = []
    for i, (d, _) in enumerate(rows):
        ids = [rows[j][0] for j in range(len(rows)) if root(j) == root(i)] if sets[i] else [d]
        out.append((d, len(sets[i]), min(ids)))
    return sorted(out)


def test_groups_match_brute_force(spark):
    rng = random.Random(5)
    base = [[f"w{rng.randrange(300)}" for _ in range(rng.randrange(60, 160))] for _ in range(12)]
    rows = []
    for n in range(150):
        w = list(rng.choice(base))
        for _ in range(rng.randrange(0, 4)):
            w[rng.randrange(len(w))] = f"x{rng.randrange(9999)}"
        rows.append((n, " ".join(w)))
    rows += [(900, ""), (901, None), (902, " \t\n"), (903, "one two"), (904, "One  TWO"), (905, "É é"), (906, "é é")]
    df = spark.createDataFrame([(d, t, "x") for d, t in rows], S)
    got = m.near_duplicates(df).collect()
    assert sorted((r.doc_id, r.n_shingles, r.component_id) for r in got) == brute(rows)
    assert all(r.kept == (r.doc_id == r.component_id) for r in got)


def test_odd_tables(spark):
    assert m.near_duplicates(spark.createDataFrame([], S)).count() == 0
    df = spark.createDataFrame([(7, "a b c d e f", "x"), (7, "a b c d e f", "x"), (None, "a b c d e f", "y"), (9, "a b c d e f", "z")], S)
    assert sorted(((r.doc_id or -1), r.component_id) for r in m.near_duplicates(df).collect()) == [(-1, 7), (7, 7), (7, 7), (9, 7)]
    assert m.minhash_stage(spark, df, "").count() == 1


def test_blocks_lose_no_link(spark, monkeypatch):
    rng = random.Random(8)
    w = [f"w{i}" for i in range(200)]
    rows = []
    for n in range(40):
        v = list(w)
        for k in range(rng.randrange(3)):
            v[rng.randrange(200)] = f"q{n}_{k}"
        rows.append((n, " ".join(v)))
    monkeypatch.setattr(m, "BLOCK_ROWS", 7)
    got = m.near_duplicates(spark.createDataFrame([(d, t, "") for d, t in rows], S)).collect()
    assert sorted((r.doc_id, r.n_shingles, r.component_id) for r in got) == brute(rows)


def test_estimate_is_corrected():
    rng = np.random.default_rng(0)
    a = rng.integers(0, 256, (400, m.BANDS * m.ROWS)).astype(np.uint8)
    assert abs(m.estimate(a[0], a[1:]).mean()) < 0.01
    assert m.estimate(a[0], a[:1])[0] == 1.0
