"""A training corpus from ``documents``: each stage works on all that the one before it kept.

STAGES lists (name, function); a function takes (spark, docs, sf_dir) and returns a DataFrame, which is
written as Parquet and read again as the next one's documents.

Defined results, for every stage: null text counts as empty (the quality rules drop it); of rows with equal
text, or of near copies, the smallest id stays (null ids last); rows that repeat id and text count once
after ``exact_dedup``; very long texts are read whole; an empty table gives an empty table of the same
columns; other columns of ``documents`` pass through unchanged, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from gembed.llm import jaccard_join, mixing, quality_cascade, sentencepiece_codec, stream_dedup
from gembed.llm.catalog import tokenizer_file
from gembed.llm.common import scratch, table


#: Shares of expected tokens after mixing; poor text has nearly gone by then and is left as it is.
MIX_TARGETS = {"good": 0.95, "toxic": 0.05}


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality_cascade.keep_good(docs)


def exact_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return stream_dedup.keep_first(docs)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return jaccard_join.one_of_each(docs, jaccard_join.Measure(n=5, num=80, den=100))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.apply_rates(docs, table(spark, sf_dir, "labels"), MIX_TARGETS)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return sentencepiece_codec.encode_decode(docs, tokenizer_file("piece_bpe_32k.model"))


STAGES = [("quality_rules", quality_rules), ("exact_dedup", exact_dedup), ("near_dedup", near_dedup), ("mix_sources", mix_sources), ("encode", encode)]

#: The stages count repeated windows, follow links and fit rates; SQL has no equivalent. tests/llm tests run() against plain Python.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        path = scratch(spark, f"pipeline-{name}")
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
