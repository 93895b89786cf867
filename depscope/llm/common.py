"""What several corpus operators share: table access, shared scratch tables and native word expressions."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from depscope.operators.fixpoint import delete, forget_scratch, scratch_root

__all__ = ["delete", "forget_scratch"]

#: Java pattern of a run of white space and its complement, the words (code points outside space and \t..\r).
SPACES = "[ \\t-\\r]+"
SPACE_CHARS = " \t\n\x0b\x0c\r"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


_PATHS: list[list[str]] = []


def scratch_path(spark: SparkSession, tag: str) -> str:
    path = f"{scratch_root(spark)}/{uuid.uuid4().hex}/{tag}"
    for paths in _PATHS:
        paths.append(path)
    return path


def written(df: DataFrame, tag: str) -> DataFrame:
    """df as a Parquet table in the shared folder: computed once, lineage cut, readable after an executor is lost."""
    path = scratch_path(df.sparkSession, tag)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


@contextmanager
def passing_scratch(spark: SparkSession) -> Iterator[list[str]]:
    """Scratch tables made inside go at the end, but for those that the body takes out of the list it gets."""
    paths: list[str] = []
    _PATHS.append(paths)
    try:
        yield paths
    finally:
        _PATHS.remove(paths)
        for path in paths:
            delete(spark, path.rpartition("/")[0])


def text_or_empty(text: Column | str = "text") -> Column:
    return F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit(""))


def packed(docs: DataFrame, *more: Column) -> DataFrame:
    """docs as one column __doc, and more beside it: no name of docs can clash with those of a step. ``select("__doc.*")`` unpacks it."""
    return docs.select(F.struct(*docs.columns).alias("__doc"), *more)


def words(text: Column) -> Column:
    """The words of a text as an array; empty for a text without words."""
    trimmed = F.btrim(text, F.lit(SPACE_CHARS))
    return F.when(trimmed == "", F.array().cast("array<string>")).otherwise(F.split(trimmed, SPACES))


def ascii_lower(text: Column) -> Column:
    """A-Z lower-cased, all else kept."""
    return F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def hash_key(doc_id: Column) -> Column:
    """A hash-random key of a document, the same in any engine that has MD5."""
    return F.md5(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary"))
