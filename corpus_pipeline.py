"""A training corpus from `documents`: language ID, near-dedup, substring dedup, decontamination, mixing.

Each stage takes (spark, docs, sf_dir), works on all that its predecessor kept, and returns the documents it keeps with the columns
of `documents`; the last adds copy_no (replacing a column of that name). Columns that clash with names used inside stay as they are. No stage
depends on the order of rows; reruns agree. An empty table gives an empty result at each stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from joinspace.llm import decontaminate, language, mixing, neardup, substrings
from joinspace.llm.common import Scratch


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Learns from all labelled rows of its input; documents that get no language go: null and empty texts, texts without a
    letter, texts without any n-gram that a language has. Rows are decided one by one, so repeated rows stay or go together; a
    null doc_id, lang or source changes nothing; ties between languages keep the document."""
    model = language.fit(docs.select("text", "lang"))
    packed = docs.select(F.struct("*").alias("row"), "text")
    kept = language.predict(packed, model).where((F.col("lang_pred") != "und") & (F.col("score") > 0))
    return kept.select(*[F.col("row")[c].alias(c) for c in docs.columns])


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Five-word shingles, similarity 0.8; the smallest doc_id of each group stays. Null and empty texts and rows with a null doc_id
    link with nothing and stay; rows that repeat a doc_id and text stay or go together."""
    return neardup.keep_one(docs, words=5, percent=80)


def substring_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages of 50 words or more that also stand in a smaller doc_id are cut from text, and n_chars is counted anew; documents left without a word by that
    go. Null texts have no words and stay; a null doc_id is larger than all others; rows with one doc_id are not smaller than each other."""
    return substrings.remove_repeats(docs, width=50)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with any window of a benchmark item go. Null and word-free texts have none and stay; rows are judged one by one."""
    return decontaminate.remove_documents(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeats or drops documents to meet the sources' targets. A null text has size 0, null is a source of its own, and rows that repeat
    a doc_id share its draw."""
    return mixing.mix(docs)


STAGES = [
    ("language_id", language_id),
    ("near_dedup", near_dedup),
    ("substring_dedup", substring_dedup),
    ("decontamination", decontamination),
    ("mixture", mixture),
]

#: Not expressible: the language model is fitted outside SQL. tests/llm/test_pipeline.py holds run() against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each written as Parquet and read again."""
    scratch = Scratch(spark)
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = scratch.store(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
