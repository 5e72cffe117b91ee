"""Catalogue of the queries and their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import queries_core, queries_search, queries_surface
from .operators import index

_MODULES = (queries_core, queries_search, queries_surface)
QUERIES: dict = {k: v for m in _MODULES for k, v in m.QUERIES.items()}
SQL: dict[str, str] = {k: v for m in _MODULES for k, v in m.SQL.items()}


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Within, covers and stab queries in one batch over one bounded graph."""
    graph = queries_core.built(spark, sf_dir, queries_search.BOUNDED)
    return index.search(graph, queries_core.mixed(spark, sf_dir), 40, queries_search.BOUNDED)
