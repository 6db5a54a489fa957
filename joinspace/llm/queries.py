"""Queries of the training-data operators, and their SQL for DuckDB where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontaminate, language, licenses, lm, mixing, neardup, oracles, substrings, tokens, topk, warc


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def crc(column: str, modulus: int):
    return F.crc32(F.col(column).cast("string")) % modulus


def op1_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontaminate.scan(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return found.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"))


def op2_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return tokens.token_counts(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))


def file_tree(documents: DataFrame) -> DataFrame:
    """Documents as files: source/lang/block of 50 ids/id.txt; each 50th is its folder's licence file, each 1000th that of the folder above."""
    name = F.concat(F.col("doc_id").cast("string"), F.lit(".txt"))
    block = F.floor(F.col("doc_id") / 50).cast("string")
    top, low = F.concat_ws("/", "source", "lang"), F.concat_ws("/", F.col("source"), F.col("lang"), block)
    path = F.when(F.col("doc_id") % 1000 == 0, F.concat_ws("/", top, F.lit("LICENSE"))).when(F.col("doc_id") % 50 == 0, F.concat_ws("/", low, F.lit("LICENSE"))).otherwise(F.concat_ws("/", low, name))
    return documents.select("doc_id", path.alias("path"), "text")


def op3_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    files = file_tree(table(spark, sf_dir, "documents"))
    found = licenses.scan(files).select("path", "text_key", "own_licence", "score", "licence", "licence_from", "inherited")
    return found.drop("text_key")


def op4_lm_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    training = F.coalesce(crc("doc_id", 7) != 2, F.lit(True))
    return lm.score(table(spark, sf_dir, "documents"), training)


def op5_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    documents = table(spark, sf_dir, "documents")
    held = F.coalesce(crc("doc_id", 4) == 2, F.lit(False))  # a null doc_id is not held out
    model = language.fit(documents.where(~held).select("text", "lang"))
    return language.predict(documents.select("doc_id", held.alias("held_out"), "text"), model).select("doc_id", "held_out", "lang_pred", "score")


def op6_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = topk.whole(table(spark, sf_dir, "embeddings"))
    return topk.top_k(vectors, vectors.where(F.col("vec_id") % 50 == 0), k=5)


def op7_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.NearDuplicates(table(spark, sf_dir, "documents"), words=2).components().drop("text_key")


def op8_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substrings.removals(table(spark, sf_dir, "documents"), 50).select("doc_id", "n_words", "n_removed", "kept_sha256")


def op9_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    archive = warc.Archive.create(table(spark, sf_dir, "pages"))
    return archive.captures().select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op10_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    rated = mixing.rates(table(spark, sf_dir, "documents").select("doc_id", "text", "source"))
    return rated.select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"), "copies")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_decontaminate": op1_decontaminate,
    "op2_token_counts": op2_token_counts,
    "op3_license_scan": op3_license_scan,
    "op4_lm_scores": op4_lm_scores,
    "op5_language_id": op5_language_id,
    "op6_top_k": op6_top_k,
    "op7_near_duplicates": op7_near_duplicates,
    "op8_substring_dedup": op8_substring_dedup,
    "op9_warc": op9_warc,
    "op10_mix": op10_mix,
}
ORACLE_SQL = oracles.ORACLE_SQL
