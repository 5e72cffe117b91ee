"""Query of language-model scoring."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import gatedlm
from .common import documents
from .queries_langid import held_out


def op6_gated_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = gatedlm.score(documents(spark, sf_dir), ~held_out(parts=7))
    return out.select("doc_id", held_out(parts=7).alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score")


QUERIES = {"op6_gated_lm": op6_gated_lm}
SQL: dict[str, str] = {}
