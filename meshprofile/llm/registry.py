"""The queries and SQL of this subpackage."""

from __future__ import annotations

from meshprofile.llm import bpe, embedding_dedup, lm_scoring, mixing, packing, preferences, quality_cnn, quality_rules, simhash_dedup, toxicity

MODULES = (packing, lm_scoring, bpe, mixing, quality_rules, preferences, toxicity, quality_cnn, embedding_dedup, simhash_dedup)


def queries() -> dict:
    return {k: v for m in MODULES for k, v in m.QUERIES.items()}


def oracle_sql() -> dict:
    return {k: v for m in MODULES for k, v in m.ORACLES.items()}
