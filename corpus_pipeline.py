"""A training corpus from `documents`: rules, line dedup, near dedup, mixing, encoding. Each stage reads its predecessor's rows."""

from __future__ import annotations

from pyspark.sql import functions as F

from lowrank_spark.llm.byte_bpe import encode_documents
from lowrank_spark.llm.curriculum import mixing_stage
from lowrank_spark.llm.fuzzy_lines import line_stage
from lowrank_spark.llm.minhash_dedup import minhash_stage
from lowrank_spark.llm.quality_rules import quality_stage
from lowrank_spark.runtime import Scratch


def encoding_stage(spark, docs, sf_dir):
    """Token ids of every text, with digests of the ids and of the decoded bytes.

    The mixing stage writes its copies range-sorted by training position, so file and row number are the place of a copy
    in the curriculum: order by (part_file, part_row). Both are null where docs are not read from files.
    """
    import public_tokenizers as P

    place = {"part_file": F.lit(None).cast("string"), "part_row": F.lit(None).cast("long")}
    if docs.inputFiles():
        place = {"part_file": F.col("_metadata.file_name"), "part_row": F.col("_metadata.row_index")}
    docs = docs.select("doc_id", "text", *[c.alias(n) for n, c in place.items()])
    outputs = ["token_ids", "n_tokens", "ids_sha256", "decoded_sha256"]
    return encode_documents(docs, P.path("byte_bpe_50k.tiktoken"), P.PATTERN, outputs, carry=["doc_id", "part_file", "part_row"])


STAGES = [
    ("quality_rules", quality_stage),
    ("line_dedup", line_stage),
    ("minhash_near_dedup", minhash_stage),
    ("mixing", mixing_stage),
    ("byte_bpe", encoding_stage),
]

#: Components over full shingle sets and the byte-level merges are beyond one SQL statement; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    scratch = Scratch(spark, "pipeline")
    for i, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs = scratch.keep(docs)
    return docs
