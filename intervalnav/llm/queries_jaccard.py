"""Query of the n-gram Jaccard join."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import jaccard
from .common import documents


def op4_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard.components(documents(spark, sf_dir))


QUERIES = {"op4_ngram_jaccard": op4_ngram_jaccard}
SQL: dict[str, str] = {}
