"""Query of HTML extraction."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import htmltext
from .common import pages


def op3_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return htmltext.extract(pages(spark, sf_dir))


QUERIES = {"op3_html_text": op3_html_text}
SQL: dict[str, str] = {}
