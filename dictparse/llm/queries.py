"""The queries and SQL of all corpus operators, by name."""

from __future__ import annotations

from dictparse.llm import decontamination, html_extraction, knn, line_dedup, near_dedup, packing, repeats, sharding, token_counts, toxicity

_MODULES = (html_extraction, decontamination, token_counts, sharding, repeats, packing, knn, toxicity, line_dedup, near_dedup)

QUERIES = {name: q for m in _MODULES for name, q in m.QUERIES.items()}
SQL = {name: s for m in _MODULES for name, s in m.SQL.items()}
