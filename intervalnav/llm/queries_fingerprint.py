"""Query of the document fingerprints."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import fingerprint
from .common import documents


def op9_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprint.near(documents(spark, sf_dir))


QUERIES = {"op9_fingerprints": op9_fingerprints}
SQL: dict[str, str] = {}
