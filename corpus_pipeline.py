"""A training corpus from raw documents: language, repeated lines, near copies, test items, token ids.

Every stage takes (spark, docs, sf_dir), works on all rows that its predecessor kept and returns a DataFrame, which is
written to the shared folder and read again for the next one. All but the last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from parley.llm import decontaminate, language, line_dedup, merge_dropout, simhash
from parley.llm.common import Tables, load, tokenizer_path


def known_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language is recognised, learned as op4 learns. Null texts and texts without a letter go; repeated rows fare alike."""
    return language.recognised(docs, language.train(docs.where(language.remainder("doc_id", 4) != 2)))


def first_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without lines that an earlier place holds nearly alike; those that lose all their words go.

    Rows that share an id are known by their texts; rows without an id and texts without a line of 20 characters stay as they are.
    """
    return line_dedup.dedup_documents(docs)


def one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents linked by their fingerprints, the one with the smallest id; rows that share an id are judged by their own texts, rows without one stay."""
    return simhash.one_of_each_group(docs)


def without_test_items(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no item of the benchmark; null and empty texts hold none, ids don't matter."""
    return decontaminate.clean(docs, load(spark, sf_dir, "benchmark"))


def token_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """(doc_id, ids, lossless): piece ids with merge-dropout, and whether they decode to the text (null: as the empty text). A row a row."""
    return merge_dropout.encode(docs, tokenizer_path("piece_bpe_32k.model"))


STAGES = [
    ("language", known_language),
    ("line_dedup", first_lines),
    ("simhash", one_of_each_group),
    ("decontamination", without_test_items),
    ("sentencepiece", token_ids),
]

#: SQL can express neither the language model nor the fingerprints' components; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last stage's rows; what a stage wrote goes once the next one has been written."""
    tables, docs = Tables(spark), load(spark, sf_dir, "documents")
    for name, stage in STAGES:
        before, docs = docs, tables.keep(stage(spark, docs, sf_dir), f"stage-{name}")
        tables.drop(before)
    return docs
