"""Query of the language operator."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import langid
from .common import documents


def held_out(column: str = "doc_id", parts: int = 4):
    return F.crc32(F.col(column).cast("string")) % parts == 2


def op1_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    model = langid.learn(docs.where(~held_out()))
    out = langid.identify(docs, model)
    return out.select("doc_id", held_out().alias("held_out"), "lang_pred", "score", "known_share")


QUERIES = {"op1_language_id": op1_language_id}
SQL: dict[str, str] = {}
