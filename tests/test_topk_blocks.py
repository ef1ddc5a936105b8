import pytest
from pyspark.sql import functions as F

from lowrank_spark import config as C
from lowrank_spark.operators import band


@pytest.mark.parametrize("kind", ["long", "string"])
@pytest.mark.parametrize("block", [1000, 40])
def test_partners_without_the_pairs(spark, kind, block):
    """The best partners by blocks are those of the spelled-out pairs, ties, null columns and missing groups included."""
    rows = [(g, (j * 7919 + g * g * 31) % (3 + g), j) for j in range(130) for g in range(9) if (j + g) % 11]
    df = spark.createDataFrame(rows, "grp long, key long, j long").union(spark.createDataFrame([(0, 0, None)], "grp long, key long, j long"))
    df = df.withColumn("j", F.col("j").cast(kind)).cache()
    want = sorted(map(tuple, band.topk(band.pairs(df), 4).collect()))
    assert sorted(map(tuple, band.topk_by_blocks(df, 4, 9, block).collect())) == want


def test_the_search_writes_no_pairs(spark, monkeypatch):
    """A search whose buckets are large does not spell their pairs out."""
    codes = spark.range(300).selectExpr("id as j", "explode(sequence(0L, 8L)) as rep").selectExpr("j", "rep", "pmod(xxhash64(j, rep), 2) as code")
    monkeypatch.setattr(band, "pairs", lambda *_: pytest.fail("pairs were formed"))
    assert band.search_codes(codes, C.HashConfig(p=1, q=9, K=2)).count() == 600
