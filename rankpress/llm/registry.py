"""Queries and SQL of the subpackage."""

from __future__ import annotations

from . import html, langid, lm, mixing, pieces, quality, simhash, topk, toxicity, vectors

_MODULES = (html, langid, lm, mixing, pieces, quality, simhash, topk, toxicity, vectors)
QUERIES = {k: f for m in _MODULES for k, f in m.QUERIES.items()}
SQL = {k: s for m in _MODULES for k, s in m.SQL.items()}
