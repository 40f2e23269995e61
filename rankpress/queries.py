"""All registered queries of the engine and their SQL twins."""

from __future__ import annotations

from .plans import exact, neural, relational, surface, workloads

QUERIES: dict = relational.QUERIES | surface.QUERIES | workloads.QUERIES | exact.QUERIES | neural.QUERIES
SQL: dict[str, str] = relational.SQL | surface.SQL | workloads.SQL | exact.SQL | neural.SQL


def flagship(spark, sf_dir):
    """Codec on text, on ids and on predicted ranks, by language."""
    return QUERIES["w03_groups"](spark, sf_dir)
