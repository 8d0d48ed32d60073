"""The queries of this subpackage: one per operator, over its whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import chunk_bpe, decontaminate, language, quality, revisit, simhash, suffix_dedup, token_file, toxicity, vector_graph
from .common import table


def _vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_quality_mil(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    return quality.score(docs, quality.fit(docs, table(spark, sf_dir, "labels", "doc_id", "quality")))


def op2_warc_revisit(spark: SparkSession, sf_dir: str) -> DataFrame:
    return revisit.run(table(spark, sf_dir, "pages", "page_id", "url", "html"))


def op3_chunk_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chunk_bpe.digests(table(spark, sf_dir, "documents", "doc_id", "text"), _vocabulary("word_bpe_49k.json"))


def op4_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.digests(table(spark, sf_dir, "documents", "doc_id", "text"))


def op5_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontaminate.flag(table(spark, sf_dir, "documents", "doc_id", "text"), table(spark, sf_dir, "benchmark", "item_id", "text"))
    return found.withColumn("item_ids", F.array_join("item_ids", ","))


def op6_language_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text", "lang")
    return language.predict(docs.select("doc_id", "text"), language.fit(docs))


def op7_simhash_neardup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.group(table(spark, sf_dir, "documents", "doc_id", "text"))


def op8_toxicity_bigru(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    return toxicity.score(docs, toxicity.fit(docs, table(spark, sf_dir, "labels", "doc_id", "toxic")))


def op9_vector_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vector_graph.run(table(spark, sf_dir, "embeddings", "vec_id", "embedding"))


def op10_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_file.run(spark, table(spark, sf_dir, "documents", "doc_id", "text"), _vocabulary("byte_bpe_50k.json"))


def queries() -> dict:
    return {k: f for k, f in globals().items() if k.startswith("op") and k[2].isdigit()}


ORACLES: dict[str, str] = {"op2_warc_revisit": revisit.ORACLE, "op4_suffix_dedup": suffix_dedup.ORACLE, "op5_decontaminate": decontaminate.ORACLE, "op9_vector_graph": vector_graph.ORACLE}
