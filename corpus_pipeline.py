"""From documents to packed training sequences: language, near duplicates, repeated passages, benchmarks, packing.

Every stage takes (spark, docs, sf_dir) and works on all rows the stage before kept; its result is written as Parquet
and read again as the next one's ``docs``. All but the last return the columns of documents.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import wraps

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dedupflow.llm import decontaminate, language_id, near_dup, packing, substring_dup
from dedupflow.llm.common import small_side, text_batches, written
from dedupflow.llm.queries import pre_token_pattern, table, tokenizer_path

#: Word shingles and similarity of near duplicates; words of a repeated passage; tokens of a sequence.
SHINGLE, PERCENT, PASSAGE, SEQUENCE = 5, 80, 40, 2048


def _over_texts(stage: Callable) -> Callable:
    @wraps(stage)
    def bounded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        text_batches(spark)
        return stage(spark, docs, sf_dir)

    return bounded


@_over_texts
def keep_known_languages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose text is of a language learned from the labelled rows; null texts and texts without letters go."""
    return language_id.accepted(docs, language_id.train(docs.select("doc_id", "text", "lang")))


@_over_texts
def keep_one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document of smallest id of every group of near duplicates; of rows that repeat id and text one stays."""
    found = near_dup.near_duplicates(docs.select("doc_id", "text"), SHINGLE, PERCENT)
    gone = written(found.where(F.col("doc_id").isNotNull() & ~F.col("kept")).select("doc_id").distinct(), "near-duplicates")
    left = docs.join(small_side(gone, gone.count()), "doc_id", "left_anti").select(*docs.columns)
    again = written(docs.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1 AND doc_id IS NOT NULL").select("doc_id"), "repeated-ids")
    n = again.count()
    if not n:
        return left
    side = small_side(again, n)
    once = left.join(side, "doc_id", "left_semi").select(*docs.columns).dropDuplicates(["doc_id", "text"])
    return left.join(side, "doc_id", "left_anti").select(*docs.columns).union(once)


@_over_texts
def cut_repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, without passages of PASSAGE words or more that occur earlier."""
    return substring_dup.remove_repeats(docs, PASSAGE)


@_over_texts
def keep_clean_of_benchmarks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no passage of a benchmark item, with the item's values or others."""
    return decontaminate.clean(docs, table(spark, sf_dir, "benchmark"))


@_over_texts
def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents with their sequence and offset."""
    return packing.pack(docs, tokenizer_path("byte_bpe_50k.json"), tokenizer_path(packing.RANKS), pre_token_pattern(), SEQUENCE)


STAGES = [
    ("language_id", keep_known_languages),
    ("near_duplicates", keep_one_of_each),
    ("substring_dedup", cut_repeated_passages),
    ("decontamination", keep_clean_of_benchmarks),
    ("packing", pack_sequences),
]

#: SQL expresses neither the language model nor the tokenizer; tests/llm holds the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the whole documents table."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = written(stage(spark, docs, sf_dir), name)
    return docs
