"""A corpus pipeline of five stages over ``documents``: rules, near copies, benchmark passages, personal data, tokens."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from shapegraph.llm.bpe import encode
from shapegraph.llm.common import cut, table
from shapegraph.llm.decontaminate import without_items
from shapegraph.llm.jaccard import keep_one
from shapegraph.llm.personal import redacted
from shapegraph.llm.quality import accepted


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows whose text the weakly supervised rules accept. Rows are judged by their texts, never by ids; null and empty texts
    go, equal texts share their verdict, an empty table stays empty."""
    return accepted(docs)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group that links at Jaccard 0.8 on five-word shingles: the one with the smallest id (null last).
    Rows are told apart by id and text; texts without words stay, an empty table stays empty."""
    return keep_one(docs, 5, 80)


def benchmark_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows whose text holds no benchmark item within its edit budget; null and empty texts stay, ids play no part."""
    return without_items(docs, table(spark, sf_dir, "benchmark"))


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with personal data in their texts replaced by its kind; n_chars follows. A null text stays null."""
    return redacted(docs)


def bpe_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token counts and digests of every row that is left; a null text counts as empty, repeated rows as often as they are there."""
    return encode(docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES = [
    ("quality_rules", quality_rules),
    ("near_copies", near_copies),
    ("benchmark_passages", benchmark_passages),
    ("personal_data", personal_data),
    ("bpe_tokens", bpe_tokens),
]

#: Votes, links, edit distances and merges are outside SQL; tests/llm/test_pipeline.py holds the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
