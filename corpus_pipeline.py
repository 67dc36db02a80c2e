"""From raw documents to token ids: quality rules, near-dedup, passage dedup, mixing, BPE.

Each stage gets what its predecessor wrote and returns a DataFrame; all but the last return the columns of documents.
Other columns are carried along whatever they are called.  An empty table gives an empty result in every stage.
"""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from rowgraph.llm import bpe, hosts, mixing, neardup, passages
from rowgraph.llm.shared import discard, stage

Stage = Callable[[SparkSession, DataFrame, str], DataFrame]

#: Documents of this share of common shingles are near duplicates.
NEAR_PERCENT = 80


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the rules or their host's verdict reject go, null and empty texts among them; a null source is a host."""
    return hosts.keep_good(docs)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the smallest id of each group stays; rows without an id or without words stay, and rows that repeat
    an id stay or go together."""
    return neardup.drop_duplicates(docs, NEAR_PERCENT)


def passage_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages that stand elsewhere too are cut out of the texts; every row stays, null texts stay null."""
    return passages.cut_passages(docs)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows as often as their source's share takes them, a null source as a source of its own; repeated rows are taken apart."""
    return mixing.take_copies(docs)


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The ids of each whole text in a new column ``token_ids``, none for null; a column of that name gives way."""
    return bpe.encode_texts(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


STAGES: list[tuple[str, Stage]] = [
    ("quality_rules", quality_rules),
    ("near_dedup", near_dedup),
    ("passage_dedup", passage_dedup),
    ("mix", mix),
    ("tokens", tokens),
]

#: BPE ids can't be had in SQL; the stages are tested against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each written and read again before the next."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, step in STAGES:
        before, docs = docs, stage(step(spark, docs, sf_dir), f"pipeline-{name}")
        discard(before)
    return docs
