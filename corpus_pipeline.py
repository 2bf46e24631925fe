"""A corpus pipeline over ``documents``: five stages, each written as Parquet and read again.

Language ID drops documents of no language; exact dedup and the n-gram Jaccard join keep one document
of each group (the smallest id); mixing repeats and drops documents to the sources' target weights;
byte-level BPE returns each document's token digests.
"""

from __future__ import annotations

import functools
from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from batchplan.llm import byte_bpe, exact_dedup, language_id, mixing, ngram_join
from batchplan.llm.shared import made_since, release_since, release_tables, table, trim_executors, written, written_mark

#: Least share of a document's character n-grams that must fit its language.
LEAST_FIT = 0.3


#: What the last stage's function has written on its way; its result is stored elsewhere when the next one begins.
_left: list[str] = []


def _tidied(stage: Callable) -> Callable:
    """stage, which first deletes what the stage before it has left, but for what docs still reads, and its heap."""

    @functools.wraps(stage)
    def run_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        release_tables(spark, list(_left), keep=[docs])
        trim_executors(spark)
        mark = written_mark()
        out = stage(spark, docs, sf_dir)
        _left[:] = made_since(mark)
        return out

    return run_stage


@_tidied
def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose n-grams fit a language; null texts and texts without letters go, repeated rows are judged alike."""
    return language_id.drop_unidentified(docs, LEAST_FIT)


@_tidied
def drop_exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each text, that of the smallest id (null last); a null text counts as empty."""
    return exact_dedup.drop_exact_duplicates(docs, keep="smallest")


@_tidied
def drop_near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document of smallest id of each group of near copies; documents without words or without an id stay."""
    return ngram_join.keep_smallest(docs, n=5, num=80, den=100)


@_tidied
def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents repeated, cut out or kept until each source (a null one too) is near its target; no rows for none."""
    return mixing.mix_documents(docs)


@_tidied
def encode_bytes(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The token digests of each row; a null text counts as empty."""
    return byte_bpe.encode_documents(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN, with_ids=False)


STAGES = [
    ("language_id", identify_language),
    ("exact_dedup", drop_exact),
    ("ngram_join", drop_near),
    ("mixing", mix_sources),
    ("byte_bpe", encode_bytes),
]

#: Near duplicates and learnt languages have no SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages applied to ``documents``."""
    docs, mark = table(spark, sf_dir, "documents"), written_mark()
    for name, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
        if stage is not STAGES[-1][1]:
            docs = written(docs, name)
            release_since(spark, mark, keep=[docs])
    return docs
