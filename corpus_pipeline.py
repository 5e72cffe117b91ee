"""Corpus pipeline: stages over ``documents``, each written as Parquet and read again by the next.

Null and letterless texts go with the first stage; every later stage takes what the operators' docstrings
define for nulls, empty texts, ties and repeated rows. Tables that a stage's operator leaves in the shared
folder, and shuffle files, are deleted when the next stage begins, since by then its result has been written.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from intervalnav.llm import jaccard, langid, linededup
from intervalnav.llm.common import release, swept, tables_made, without, written
from intervalnav.llm.queries_langid import held_out
from intervalnav.llm.queries_packing import packed

#: Share of a text's n-grams that its language must know; clean prose is over 0.6.
KNOWN = 0.05

#: Near copies share this percentage of their shingles of so many words; op4's query has its own contract.
NEAR_WORDS, NEAR_PERCENT = 5, 80

_left: list[str] = []


def _stage(work):
    def run(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        release(spark, _left)
        swept(spark)
        with tables_made() as paths:
            out = work(spark, docs, sf_dir)
        _left[:] = paths
        return out

    run.__name__, run.__doc__ = work.__name__, work.__doc__
    return run


@_stage
def in_known_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a letter and a share of known n-grams; the languages are learned from the labelled rows."""
    model = langid.learn(docs.where(~held_out()))
    names = [f"c{i}" for i in range(len(docs.columns))]
    judged = langid.identify(docs.toDF(*names), model, text=names[docs.columns.index("text")], keep=tuple(names))
    return judged.where((F.col("lang_pred") != "und") & (F.col("known_share") >= KNOWN)).select(*names).toDF(*docs.columns)


@_stage
def without_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without lines that stand in an earlier one; those with nothing left go."""
    cut = linededup.without_repeats(docs)
    return cut.where(F.trim(F.col("text"), F.lit(" \t\n\r\f\v")) != "").withColumn("n_chars", F.char_length("text").cast(docs.schema["n_chars"].dataType)).select(*docs.columns)


@_stage
def without_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the least id of every group of near copies."""
    found = jaccard.components(docs.select("doc_id", "text"), n=NEAR_WORDS, percent=NEAR_PERCENT)
    later = written(found.where("doc_id != component_id").select("doc_id").distinct(), "near-copies")
    return without(docs, "doc_id", later).select(*docs.columns)


@_stage
def in_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token pieces of the documents and their places in sequences."""
    return packed(docs)


STAGES = [
    ("language ID", in_known_language),
    ("line dedup", without_repeated_lines),
    ("n-gram Jaccard join", without_near_copies),
    ("best-fit packing", in_sequences),
]

#: SQL can't express the stages (a trained model, edit-distance classes, a tokenizer); they are tested by brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), f"stage-{name.replace(' ', '-')}")
    return STAGES[-1][1](spark, docs, sf_dir)
