"""Query of line deduplication."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import linededup
from .common import documents


def op5_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return linededup.classes(documents(spark, sf_dir))


QUERIES = {"op5_line_dedup": op5_line_dedup}
SQL: dict[str, str] = {}
