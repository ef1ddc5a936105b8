import random

import pytest

from lowrank_spark import config as C
from lowrank_spark.operators import band


@pytest.mark.parametrize("k", [1, 3, 50])
def test_few_groups_equal_the_pairs(spark, k):
    """Sets of groups give the partners of all pairs: skewed keys, ties by partner, a column without one group, one alone."""
    rng = random.Random(k)
    rows = [(g, min(rng.randrange(12), rng.randrange(12)), j * 7) for j in range(-20, 60) for g in range(4) if (j, g) != (3, 2)]
    rows += [(g, 1000, 9999) for g in range(4)]
    df = spark.createDataFrame(rows, "grp long, key long, j long")
    want = sorted(map(tuple, band.topk(band.pairs(df), k).collect()))
    assert sorted(map(tuple, band.topk_few_groups(df, k, 4).collect())) == want and want


def test_few_groups_form_no_pairs(spark, monkeypatch):
    """The default search over few groups does not write out a bucket's pairs, which grow with its square."""
    monkeypatch.setattr(band, "pairs", lambda *a: pytest.fail("pairs of a bucket"))
    codes = spark.createDataFrame([(j, r, 5) for j in range(50) for r in range(4)], "j long, rep long, code long")
    got = band.search_codes(codes, C.HashConfig(p=1, q=4, K=2)).collect()
    assert {(r.j, r.nbr, r.freq, r.k) for r in got if r.j < 3} == {(0, 1, 4, 1), (0, 2, 4, 2), (1, 0, 4, 1), (1, 2, 4, 2), (2, 0, 4, 1), (2, 1, 4, 2)}


def test_supplier_sums_are_shuffled_once(spark, sf):
    """Sums by column over supp_part lie where its rows are already: one exchange in the plan, not three."""
    from lowrank_spark.operators import signhash
    from lowrank_spark.sources import interactions as W

    plan = signhash.accumulate(W.supp_part(spark, sf), C.HashConfig(p=1, q=4))._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1
