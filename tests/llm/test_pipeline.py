import hashlib

import corpus_pipeline as cp


def test_stages_hand_over_documents(spark):
    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    cols = docs.columns
    sizes = []
    for n, (_, stage) in enumerate(cp.STAGES):
        docs = stage(spark, docs, sf)
        if n + 1 < len(cp.STAGES):
            assert docs.columns == cols
            docs = docs.checkpoint()
            sizes.append({r.doc_id for r in docs.select("doc_id").collect()})
            texts = {r.doc_id: r.text for r in docs.select("doc_id", "text").collect()}
    assert all(b <= a for a, b in zip(sizes, sizes[1:]))
    assert len(sizes[1]) == len(sizes[0]) >= 150
    for r in docs.collect():
        assert r.decoded_sha256 == hashlib.sha256((texts[r.doc_id] or "").encode()).hexdigest() and r.n_tokens == len(r.token_ids)
