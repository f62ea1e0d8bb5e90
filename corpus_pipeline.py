"""A corpus pipeline: quality rules, near-duplicate documents, repeated paragraphs, packing.

Each stage takes (spark, docs, sf_dir); all but the last return the columns of ``documents``.  A stage's result is
written and reread as the next one's docs, so a stage begins by deleting what the one before it kept for its result.

Defined cases, for every stage: a null or empty text fails the quality rules, so later stages meet none from the first;
given one on its own, a later stage keeps it (packing: as the end token alone).  A null language is the empty one.
Repeated rows with one id are judged alike by the rules; the join keeps the one with the smallest id of a group, and of
rows that share that id all.  Ties go to the smaller id, then the earlier line.  Very long texts are read whole.  An empty table
gives an empty table.  Extra columns pass through, whatever they are called; the last stage returns pieces only.
"""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from mixagg.llm import ngram_join, packing, paragraph_dedup, quality
from mixagg.llm.session import discard, saved, steps_made, table

Stage = Callable[[SparkSession, DataFrame, str], DataFrame]
_kept: list[DataFrame] = []  # steps that the last stage's result still reads


def stage(fn: Stage) -> Stage:
    """``fn`` with the steps that the stage before it left deleted first."""

    def run(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        gone = [step for step in _kept if step.sparkSession.sparkContext._jsc is not None]
        _kept.clear()
        discard(*gone)
        with steps_made() as made:
            out = fn(spark, docs, sf_dir)
        _kept.extend(made)
        return out

    run.__doc__ = fn.__doc__
    return run


@stage
def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the rules reject go."""
    return quality.filter_documents(docs, labels=table(spark, sf_dir, "labels"))


@stage
def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of linked documents the one with the smallest id stays."""
    return ngram_join.keep_first(docs)


@stage
def substring_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeated paragraphs and passages go, but for their first place."""
    return paragraph_dedup.remove_paragraphs(docs)


@stage
def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of sequences of at most 1024 tokens."""
    return packing.pack_documents(docs, public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.PATTERN)


STAGES = [("quality rules", quality_rules), ("n-gram Jaccard join", near_duplicates), ("substring dedup", substring_dedup), ("packing", pack)]

ORACLE_SQL = None  # perplexity bands and packing are no SQL; see tests/llm/test_pipeline.py


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; each stage's rows are kept in the shared checkpoint folder."""
    docs = table(spark, sf_dir, "documents")
    for _, step in STAGES[:-1]:
        docs = saved(step(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
