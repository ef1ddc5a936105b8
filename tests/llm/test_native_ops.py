import random

from pyspark.sql import functions as F
from pyspark.sql import types as T

from lowrank_spark.llm import curriculum as cu
from lowrank_spark.llm import fuzzy_lines as fl
from lowrank_spark.llm import quality_rules as qr
from lowrank_spark.llm import shard_table as sh
from lowrank_spark.llm.components import connected
from lowrank_spark.runtime import Scratch

DOCS = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("lang", T.StringType()), T.StructField("source", T.StringType()), T.StructField("n_chars", T.LongType())])


def docs(spark, rows):
    return spark.createDataFrame([(d, t, "en", s, len(t or "")) for d, t, s in rows], DOCS)


def test_repeats_by_hand(spark):
    w = [f"a{i}" for i in range(8)]
    rows = [(1, " ".join(w + ["x"] + w), "s"), (2, "z " * 12, "s"), (3, None, None), (4, "one\ntwo\none\n \n#$", "s")]
    got = {r.doc_id: r for r in qr.base_counts(docs(spark, rows)).collect()}
    assert got[1].n_repeat_words == 16 and got[2].n_repeat_words == 12 and got[3].n_words == 0
    assert got[4].n_dup_lines == 1 and got[4].n_symbols == 2 and got[4].base_failed


def test_boilerplate_goes_and_copies_do_not_count(spark):
    rng = random.Random(1)
    text = lambda n: " ".join(f"w{rng.randrange(10**6)}" for _ in range(n))
    rows = [(n, text(40) + "\nSubscribe to our letter 12", "h") for n in range(30)]
    rows += [(100 + n, rows[0][1], "h") for n in range(60)]  # copies of one text
    rows += [(200, "Subscribe to our letter 7\n" * 3 + "only a few words", "h"), (201, text(30) + "\nSubscribe to our letter 12", "other")]
    got = {r.doc_id: r for r in qr.judge(docs(spark, rows)).collect()}
    assert got[0].n_removed_words == 5 and got[0].kept and "Subscribe" not in got[0].clean_text
    assert all(got[100 + n].kept for n in range(60)) and not got[200].kept and got[201].n_removed_words == 0
    assert qr.judge(docs(spark, rows).limit(0)).count() == 0


def test_fuzzy_lines_match_brute_force(spark):
    rng = random.Random(3)
    base = [" ".join(f"w{rng.randrange(50)}{c}" for c in "abcdefghij" * rng.randrange(1, 9)) for _ in range(25)]
    lines = []
    for n in range(120):
        x = rng.choice(base).split(" ")
        if rng.random() < 0.5:
            x[rng.randrange(len(x))] = f"v{rng.randrange(99)}"
        lines.append(" ".join(x).upper() if n % 3 else " ".join(x) + "!")
    rows = [(n, "\n".join(lines[4 * n : 4 * n + 4]) + "\nshort one", "s") for n in range(30)] + [(77, None, None), (78, "", "s")]
    df = docs(spark, rows)
    occ = fl.occurrences(df)
    full = fl.simhash(occ, ["doc_id", "th", "pos", "lh"]).join(occ.select("doc_id", "th", "pos", "norm"), ["doc_id", "th", "pos"]).collect()
    full.sort(key=lambda r: (r.doc_id, r.th, r.pos))
    up = list(range(len(full)))

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    def edit(a, b):
        row = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            last, row[0] = row[0], i
            for j, y in enumerate(b, 1):
                last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
        return row[-1]

    for i, a in enumerate(full):
        for j, b in enumerate(full[:i]):
            near = bin(a.sh ^ b.sh).count("1") <= fl.MAX_BITS
            if a.norm == b.norm or near and 1 - edit(a.norm, b.norm) / max(len(a.norm), len(b.norm)) >= fl.SIMILAR:
                up[max(root(i), root(j))] = min(root(i), root(j))
    want = {}
    for i, r in enumerate(full):
        if root(i) != i:
            want.setdefault(r.doc_id, []).append(r.pos)
    _, gone = fl.dropped_lines(df)
    assert {r.doc_id: r.gone for r in gone.collect()} == {k: sorted(v) for k, v in want.items()} and want
    out = {r.doc_id: r.text for r in fl.line_stage(spark, df, "").collect()}
    for d, t, _ in rows:
        keep = None if t is None else "\n".join(x for n, x in enumerate(t.split("\n")) if n not in want.get(d, []))
        assert out[d] == keep


def test_blocks_share_two():
    masks = fl.block_masks()
    rng = random.Random(2)
    for _ in range(500):
        x = rng.getrandbits(63)
        y = x ^ (1 << rng.randrange(63)) ^ (1 << rng.randrange(63))
        assert any(x & m == y & m for m in masks)


def test_components(spark):
    rng = random.Random(6)
    e = [(rng.randrange(60), rng.randrange(60)) for _ in range(45)] + [(100 + i, 101 + i) for i in range(40)]
    up = {x: x for p in e for x in p}

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    for a, b in e:
        up[max(root(a), root(b))] = min(root(a), root(b))
    got = {r.node: r.comp for r in connected(spark.createDataFrame(e, "a long, b long"), Scratch(spark, "t")).collect()}
    assert got == {x: root(x) for p in e if p[0] != p[1] for x in p}


def test_mixing_targets(spark):
    rng = random.Random(4)
    rows = [(n, "w " * rng.randrange(0, 60), ["a", "b", "c", None][n % 4]) for n in range(400)] + [(999, None, "a"), (999, None, "a")]
    got = cu.mix(docs(spark, rows)).collect()
    total = sum(r.size for r in got)
    by = {}
    for r in got:
        assert r.taken <= 3 * r.size and len(r.places) == r.n_copies and r.places == sorted(r.places)
        by.setdefault((r.target, r.source_size), []).append(r)
    assert abs(sum(t for t, _ in by) - total) < 1e-6
    for (t, _), rs in by.items():
        assert abs(sum(r.taken for r in rs) - t) <= 60 and t <= 3 * rs[0].source_size
    assert sorted(map(str, got)) == sorted(map(str, cu.mix(docs(spark, rows).repartition(5)).collect()))
    order = [r.position for r in cu.training_order(cu.mix(docs(spark, rows))).collect()]
    assert order == sorted(order) and len(order) == sum(r.n_copies for r in got)
    assert cu.mix(docs(spark, rows).limit(0)).count() == 0


def test_demand_inverse(spark):
    seg = cu._segments(cu.KNOTS, (1.5, 1.0, 0.5))
    got = spark.range(0, 101).select((F.col("id") / 100).alias("q"), cu.demand_inverse(F.col("id") / 100, seg).alias("t")).collect()
    for r in got:
        assert abs(1.5 * r.t - 0.5 * r.t**2 - r.q) < 1e-9


def test_table_fill():
    names = sh.shard_names(7)
    t = sh.fill_table(names, 101)
    counts = [t.count(k) for k in range(7)]
    assert max(counts) - min(counts) <= 1
    # turn by turn, straight from the definition
    pref = {k: [(sh._number(f"offset:{s}") % 101 + i * (sh._number(f"step:{s}") % 100 + 1)) % 101 for i in range(101)] for k, s in enumerate(names)}
    slow, n = [-1] * 101, 0
    while n < 101:
        for k in range(7):
            if n < 101:
                slow[next(p for p in pref[k] if slow[p] < 0)] = k
                n += 1
    assert t == slow
    less = sh.fill_table(names[:-1], 101)
    assert sh.disruption(t, less, names, names[:-1]) < 0.35
    big = sh.fill_table(sh.shard_names(3), 101, [2, 1, 1])
    assert abs(big.count(0) - 2 * big.count(1)) <= 2


def test_placement(spark):
    df = docs(spark, [(1, "a", "s"), (1, "b", "s"), (None, "c", "s")])
    got = sh.place(df, "doc_id", sh.shard_names(4), 101)
    t = sh.fill_table(sh.shard_names(4), 101)
    for r in got.collect():
        assert r.shard == sh.shard_names(4)[t[r.slot]]
    assert got.count() == 3 and sh.place(df.limit(0), "doc_id", sh.shard_names(4), 101).count() == 0
