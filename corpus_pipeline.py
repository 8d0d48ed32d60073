"""From raw documents to tokens: toxicity filter, near-duplicates, repeated passages, benchmark
passages, BPE.  Every stage works on all that the one before it kept.

Rows with null or repeated ids are told apart in every stage; an empty table passes through as such;
columns of the table keep their names and values, whatever the names, but for what a stage says.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from treewalk.llm import chunk_bpe, decontaminate, simhash, suffix_dedup, toxicity
from treewalk.llm.common import cut, table

VOCABULARY = "word_bpe_49k.json"


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows below the toxicity threshold.  Null texts and texts without a word stay; without labels to learn
    from all rows stay."""
    return toxicity.keep(docs, toxicity.fit(docs, table(spark, sf_dir, "labels", "doc_id", "toxic")))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The first row, by id, of each group of texts alike in five-word shingles (similarity 0.8 and more).
    Null texts and texts without a word are one group."""
    return simhash.representatives(docs)


def drop_repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All rows; bytes of 200-byte strings that start elsewhere too are gone from ``text``, and ``n_chars``
    counts what is left.  Null texts become empty; a character cut in two goes as a whole."""
    return suffix_dedup.clean(docs)


def drop_benchmark_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows that hold no benchmark passage.  Null and empty texts stay; without items all rows stay."""
    return decontaminate.clean(docs, table(spark, sf_dir, "benchmark", "item_id", "text"))


def to_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of token count and digests for every row; null texts have no tokens."""
    return chunk_bpe.digests(docs, public_tokenizers.path(VOCABULARY))


STAGES = [
    ("toxicity", drop_toxic),
    ("simhash_neardup", drop_near_duplicates),
    ("suffix_dedup", drop_repeated_passages),
    ("decontamination", drop_benchmark_passages),
    ("bpe", to_tokens),
]

#: Learned and iterative stages: no SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
