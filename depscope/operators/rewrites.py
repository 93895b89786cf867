"""Queries simplified by FDs: narrower grouping and sort keys, needless DISTINCT and lookup joins.

Catalyst doesn't drop grouping keys that others determine; narrower keys mean narrower shuffles. FDs come as (lhs, rhs) of column names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

NamedFd = tuple[tuple[str, ...], str]


def determined(columns: set[str], fds: list[NamedFd]) -> set[str]:
    known, grown = set(columns), True
    while grown:
        more = {r for lhs, r in fds if set(lhs) <= known} - known
        grown, known = bool(more), known | more
    return known


def kept_keys(keys: list[str], fds: list[NamedFd]) -> list[str]:
    """Keys without those that the others determine; later keys go first."""
    kept = list(keys)
    for k in reversed(keys):
        rest = [x for x in kept if x != k]
        if k in kept and k in determined(set(rest), fds):
            kept = rest
    return kept


def reduce_group_keys(df: DataFrame, keys: list[str], aggs: list[Column], fds: list[NamedFd]) -> DataFrame:
    """groupBy(keys).agg(aggs) by the kept keys alone; determined keys are any value of their group."""
    kept = kept_keys(keys, fds)
    others = [F.any_value(k).alias(k) for k in keys if k not in kept]
    out = df.groupBy(*kept).agg(*others, *aggs)
    return out.select(*keys, *[c for c in out.columns if c not in keys])


def drop_distinct(df: DataFrame, unique_key: list[str] | None, fds: list[NamedFd] = ()) -> DataFrame:
    """distinct(), left out where a unique key is among the columns. An FD alone doesn't exclude equal rows, so uniqueness must be stated."""
    return df if unique_key and set(unique_key) <= determined(set(df.columns), list(fds)) and set(unique_key) <= set(df.columns) else df.distinct()


def reduce_sort_keys(df: DataFrame, order: list[str], fds: list[NamedFd]) -> DataFrame:
    """orderBy(order) without keys that earlier ones determine."""
    kept: list[str] = []
    for k in order:
        if k not in determined(set(kept), fds):
            kept.append(k)
    return df.orderBy(*kept)


def drop_lookup_join(left: DataFrame, right: DataFrame, on: list[str], used: list[str], fds: list[NamedFd], no_dangling: bool) -> DataFrame:
    """left join-ed to right, or left alone: where only left's columns are used, right is unique on the key and no key is missing there."""
    every = determined(set(on), fds) >= set(right.columns)
    if no_dangling and every and set(used) <= set(left.columns):
        return left.select(*used)
    return left.join(right, on).select(*used)
