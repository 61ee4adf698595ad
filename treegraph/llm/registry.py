"""Queries and oracle SQL of the operators, for __spark_entry__."""

from __future__ import annotations

from . import bpe, decontaminate, language, language_model, lattice, line_dedup, main_text, ngram_join, quality, warc

_MODULES = (bpe, decontaminate, language, language_model, lattice, line_dedup, main_text, ngram_join, quality, warc)


def queries() -> dict:
    return {k: v for m in _MODULES for k, v in m.QUERIES.items()}


def oracles() -> dict[str, str]:
    return {k: v for m in _MODULES for k, v in m.ORACLES.items()}
