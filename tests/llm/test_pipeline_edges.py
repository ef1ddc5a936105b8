import hashlib

import corpus_pipeline as cp
from pyspark.sql import types as T

S = T.StructType(
    [T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("lang", T.StringType()), T.StructField("source", T.StringType()), T.StructField("n_chars", T.LongType())]
    + [T.StructField(c, T.StringType()) for c in ("position", "size", "kept", "n_tokens")]
)


def prose(n: int, words: int = 60) -> str:
    return " ".join(hashlib.md5(f"{n}/{i}".encode()).hexdigest()[:6] for i in range(words))


def test_odd_documents(spark, tmp_path):
    """Nulls, an empty text, a very long one, repeated rows and columns with names of the stages' own."""
    own = ("p", "s", "k", "n")
    rows = [(n, prose(n), "en", "ab"[n % 2], 0, *own) for n in range(6)]
    rows += [rows[0], (10, None, None, None, None, *own), (11, "", "en", "a", 0, *own), (None, prose(12), "en", None, 0, *own), (13, prose(13, 30_000), "en", "a", 0, *own)]
    spark.createDataFrame(rows, S).write.parquet(f"{tmp_path}/documents.parquet")
    out = cp.run(spark, str(tmp_path)).collect()
    ids = {r.doc_id for r in out}
    assert ids <= {0, 1, 2, 3, 4, 5, None, 13} and {1, 3, 5} & ids
    texts = {hashlib.sha256(r[1].encode()).hexdigest() for r in rows if r[1]}
    assert {r.decoded_sha256 for r in out} <= texts and all(r.n_tokens == len(r.token_ids) > 0 for r in out)


def test_no_documents(spark, tmp_path):
    spark.createDataFrame([], S).write.parquet(f"{tmp_path}/documents.parquet")
    assert cp.run(spark, str(tmp_path)).count() == 0
