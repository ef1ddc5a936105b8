from pyspark.sql import types as T

from lowrank_spark.llm import quality_rules as qr

DOCS = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("source", T.StringType()), T.StructField("n_chars", T.LongType())])


def test_stage_removes_a_line_of_a_large_host(spark):
    """A line in 12 of 300 texts of a host goes, one in 9 stays."""
    prose = lambda n: " ".join(f"{chr(97 + i)}{chr(97 + n % 26)}{chr(97 + n // 26)}x" for i in range(25))
    extra = lambda n: "\nshare this page" if n < 12 else "\nread more here" if n < 21 else ""
    rows = [(n, prose(n) + extra(n), "h", 0) for n in range(300)]
    got = {r.doc_id: r.text for r in qr.quality_stage(spark, spark.createDataFrame(rows, DOCS), "").collect()}
    assert got == {n: prose(n) + (extra(n) if n >= 12 else "") for n in range(300)}
