"""A corpus pipeline: quality rules, near-duplicates, benchmark decontamination, source mixing, sharding."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from depscope.llm.common import delete, passing_scratch, table, written
from depscope.llm.decontamination import clean_documents
from depscope.llm.mixing import mixed_documents
from depscope.llm.near_copies import near_copies
from depscope.llm.quality_rules import kept_documents
from depscope.llm.sharding import sharded
from depscope.llm.simhash import deduplicated


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that fail the base rules, or whose host is rejected, go."""
    return kept_documents(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each component of near copies (five-word shingles, similarity 0.8 or more) stays."""
    return deduplicated(docs, near_copies)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark window go."""
    return clean_documents(docs, table(spark, sf_dir, "benchmark"))


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources are cut or repeated to their target weights; a repeated document is a row for each epoch."""
    return mixed_documents(docs)


def sharding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The rows as a compacted store has them, with their run, tier and shard."""
    return sharded(docs)


STAGES = [
    ("quality rules", quality_rules),
    ("near-duplicates", near_duplicates),
    ("benchmark decontamination", decontamination),
    ("source mixing", mixing),
    ("sharding", sharding),
]

#: XXH64 fingerprints cannot be expressed in DuckDB; tests hold run() against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages in turn. A stage's scratch tables go once its rows are written, and its rows once the next stage has its own."""
    docs, before = table(spark, sf_dir, "documents"), None
    for name, stage in STAGES:
        with passing_scratch(spark) as paths:
            docs = written(stage(spark, docs, sf_dir), name.replace(" ", "_"))
            own = paths.pop()  # written() was the last to add one
        if before:
            delete(spark, before)
        before = own
    return docs
