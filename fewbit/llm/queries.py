"""Queries of this subpackage, and their SQL where SQL can express them."""

from __future__ import annotations

from importlib import import_module

#: query -> module of this subpackage that holds it
_HOMES = {
    "op1_embedding_neardup": "embedding_dedup",
    "op2_ngram_jaccard": "ngram_join",
    "op3_best_two_fit": "packing",
    "op4_line_winnowing": "line_dedup",
    "op5_two_tier_bpe": "byte_bpe",
    "op6_attention_quality": "quality",
    "op7_hilbert_sharding": "sharding",
    "op8_url_filter": "url_filter",
    "op9_scaled_sketch": "sketch",
    "op10_pii": "pii",
}


def queries() -> dict:
    return {name: getattr(import_module(f"fewbit.llm.{home}"), name) for name, home in _HOMES.items()}


def oracle_sql() -> dict:
    from fewbit.llm.url_filter import OP8_SQL

    return {"op8_url_filter": OP8_SQL}
