"""Query of the media columns."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from . import flac
from .common import documents


def op8_flac_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    return flac.media(documents(spark, sf_dir))


QUERIES = {"op8_flac_media": op8_flac_media}
SQL: dict[str, str] = {}
