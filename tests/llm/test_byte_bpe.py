import hashlib
import random

import public_tokenizers as P
import pytest
from pyspark.sql import types as T

from lowrank_spark.llm.byte_bpe import ByteBpe, RankQueue, encode_documents, load_ranks, op6_byte_bpe


@pytest.fixture(scope="module")
def enc():
    import tiktoken

    ranks = load_ranks(P.path("byte_bpe_50k.tiktoken"))
    return ranks, tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})


def test_queue_order():
    q = RankQueue(50_000)
    rng = random.Random(3)
    items = [(rng.randrange(50_000), rng.randrange(1000)) for _ in range(3000)]
    for r, p in items:
        q.push(r, p)
    got = []
    while (e := q.pop()) is not None:
        got.append(e)
    assert got == sorted(items) and q.top == 0


def test_matches_tiktoken(enc):
    ranks, ref = enc
    bpe = ByteBpe(ranks, P.PATTERN)
    rng = random.Random(1)
    texts = ["", " ", "Hello  world\n\n", "a" * 5000, "éàü" * 700, "x1y2" * 400, "\x00\x7f", "日本語" * 90, "<|endoftext|>"]
    texts += ["".join(rng.choice("abcdefgh éß1 \n#") for _ in range(rng.randrange(1, 400))) for _ in range(300)]
    texts += ["".join(rng.choice("ab c  \n\t'sé\x1c\x1f\x85\xa0\u3000\u200b1²") for _ in range(rng.randrange(1, 60))) for _ in range(3000)]
    texts += [chr(c) + " " + chr(c) + "x y" + chr(c) for c in range(0x3100) if not 0xD800 <= c < 0xE000]
    for t in texts:
        assert bpe.encode(t) == ref.encode_ordinary(t), t[:50]
        assert bpe.decode(bpe.encode(t)) == t.encode()


def test_odd_rows(spark, enc):
    ranks, ref = enc
    s = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("n_tokens", T.StringType())])
    df = spark.createDataFrame([(1, None, "a"), (None, "", "b"), (2, "hi there", "c"), (2, "hi there", "c")], s)
    got = encode_documents(df, P.path("byte_bpe_50k.tiktoken"), P.PATTERN, ["token_ids", "decoded_text"]).collect()
    assert sorted((r.doc_id or 0, r.token_ids, r.decoded_text) for r in got) == sorted([(1, [], ""), (0, [], ""), (2, ref.encode_ordinary("hi there"), "hi there")] * 1 + [(2, ref.encode_ordinary("hi there"), "hi there")])
    assert encode_documents(df.limit(0), P.path("byte_bpe_50k.tiktoken"), P.PATTERN, ["n_tokens"]).count() == 0


def test_whole_table(spark, enc):
    sf = "/root/testdata/sf0.001"
    _, ref = enc
    want = {}
    for r in spark.read.parquet(f"{sf}/documents.parquet").collect():
        ids = ref.encode_ordinary(r.text or "")
        want[r.doc_id] = (len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256((r.text or "").encode()).hexdigest())
    got = {r.doc_id: (r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in op6_byte_bpe(spark, sf).collect()}
    assert got == want
