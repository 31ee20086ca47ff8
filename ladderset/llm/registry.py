"""Queries and oracle SQL of the corpus operators, for __spark_entry__."""

from __future__ import annotations

from . import exact_dedup, line_dedup, lm_scoring, ngram_join, packing, quality_rules, sentencepieces, token_files, toxicity, warc

MODULES = [exact_dedup, line_dedup, lm_scoring, ngram_join, packing, quality_rules, sentencepieces, token_files, toxicity, warc]


def queries() -> dict:
    return {name: fn for m in MODULES for name, fn in vars(m).items() if name.startswith("op") and name[2].isdigit()}


def oracle_sql() -> dict[str, str]:
    return {k: v for m in MODULES for k, v in getattr(m, "ORACLE", {}).items()}
