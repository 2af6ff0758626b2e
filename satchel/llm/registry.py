"""Queries of this subpackage and, where SQL can express them, their SQL."""

from __future__ import annotations

from .bpe_codec import op5_bpe_codec
from .id_shards import op10_id_shards
from .jaccard import op6_near_duplicates
from .mixing import OP7_SQL, op7_source_mix
from .pii import op1_private_data
from .quality_rules import op3_quality_rules
from .token_counts import op8_token_counts
from .topk import OP9_SQL, op9_top_products
from .toxicity import op4_toxicity
from .warc import OP2_SQL, op2_warc

QUERIES = {
    "op1_private_data": op1_private_data,
    "op2_warc": op2_warc,
    "op3_quality_rules": op3_quality_rules,
    "op4_toxicity": op4_toxicity,
    "op5_bpe_codec": op5_bpe_codec,
    "op6_near_duplicates": op6_near_duplicates,
    "op7_source_mix": op7_source_mix,
    "op8_token_counts": op8_token_counts,
    "op9_top_products": op9_top_products,
    "op10_id_shards": op10_id_shards,
}

SQL: dict[str, str] = {"op2_warc": OP2_SQL, "op7_source_mix": OP7_SQL, "op9_top_products": OP9_SQL}


def queries() -> dict:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(SQL)
