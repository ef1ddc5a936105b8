"""Queries and SQL of the training-data operators."""

from __future__ import annotations

from lowrank_spark.llm import curriculum, minhash_dedup, quality_rules
from lowrank_spark.llm.byte_bpe import op6_byte_bpe
from lowrank_spark.llm.curriculum import op8_mixing
from lowrank_spark.llm.fuzzy_lines import op5_fuzzy_lines
from lowrank_spark.llm.minhash_dedup import op1_minhash
from lowrank_spark.llm.image_copies import op10_image_copies
from lowrank_spark.llm.license_markup import op4_license_markup
from lowrank_spark.llm.quality_rules import op2_quality_rules
from lowrank_spark.llm.secret_owners import op3_secret_owners
from lowrank_spark.llm.shard_table import op9_sharding
from lowrank_spark.llm.toxic_compression import op7_toxic_compression


def queries() -> dict:
    return {f.__name__: f for f in (op1_minhash, op2_quality_rules, op3_secret_owners, op4_license_markup, op5_fuzzy_lines, op6_byte_bpe, op7_toxic_compression, op8_mixing, op9_sharding, op10_image_copies)}


def oracle_sql() -> dict:
    return {"op1_minhash": minhash_dedup.SQL, "op2_quality_rules": quality_rules.SQL, "op8_mixing": curriculum.SQL}
