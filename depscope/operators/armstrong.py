"""Services over a set of FDs: implication, covers, keys, composition and augmentation."""

from __future__ import annotations

from collections.abc import Iterable

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

Fd = tuple[frozenset, int]


def closure_of(fds: Iterable[Fd], start: Iterable[int]) -> frozenset:
    """All attributes that start determines."""
    fds, known = list(fds), set(start)
    grown = True
    while grown:
        grown = False
        for lhs, rhs in fds:
            if rhs not in known and lhs <= known:
                known.add(rhs)
                grown = True
    return frozenset(known)


def implies_fd(fds: Iterable[Fd], lhs: Iterable[int], rhs: int) -> bool:
    return rhs in closure_of(fds, lhs)


def cover(fds: Iterable[Fd]) -> list[Fd]:
    """A minimal cover: no left side can lose an attribute, no FD follows from the rest."""
    now = sorted({(frozenset(lhs), r) for lhs, r in fds if r not in lhs}, key=lambda f: (len(f[0]), sorted(f[0]), f[1]))
    slim = []
    for lhs, rhs in now:
        for a in sorted(lhs):
            if rhs in closure_of(now, lhs - {a}):
                lhs = lhs - {a}
        slim.append((lhs, rhs))
    slim = list(dict.fromkeys(slim))
    for f in sorted(slim, key=lambda f: (-len(f[0]), sorted(f[0]), f[1])):
        rest = [g for g in slim if g != f]
        if f[1] in closure_of(rest, f[0]):
            slim = rest
    return sorted(slim, key=lambda f: (sorted(f[0]), f[1]))


def keys_of(fds: Iterable[Fd], arity: int, most: int = 100_000) -> list[frozenset]:
    """All minimal attribute sets that determine all, smallest first; ValueError if there are more than ``most``.

    One superkey is shrunk to a key. Then each FD whose right side a key holds gives a superkey, the key with the left side
    in its place, and that holds a key of its own unless one is known. Once no key gives a new one, all are found.
    """
    every = frozenset(range(1, arity + 1))
    fds = [(lhs, r) for lhs, r in dict.fromkeys(fds) if r not in lhs and lhs <= every]

    def shrunk(superkey: frozenset) -> frozenset:
        for a in sorted(superkey, reverse=True):
            if closure_of(fds, superkey - {a}) >= every:
                superkey = superkey - {a}
        return superkey

    found = [shrunk(every)]
    for key in found:
        for lhs, rhs in fds:
            if rhs in key and not any(k <= (key - {rhs}) | lhs for k in found):
                found.append(shrunk((key - {rhs}) | lhs))
                if len(found) > most:
                    raise ValueError(f"more than {most} candidate keys")
    return sorted(found, key=lambda k: (len(k), sorted(k)))


def compose(fd: DataFrame) -> DataFrame:
    """rel, lhs, all_rhs: the right sides of one left side together."""
    return fd.groupBy("rel", "lhs").agg(F.array_sort(F.collect_set("rhs")).alias("all_rhs"))


def augment(fd: DataFrame, by: list[int]) -> DataFrame:
    """Left sides widened by columns; FDs whose right side is among them are trivial and go."""
    wide = F.array_sort(F.array_union("lhs", F.array(*map(F.lit, by))))
    return fd.withColumn("lhs", wide).where(~F.array_contains("lhs", F.col("rhs")))


def _of(table: pa.Table) -> list[Fd]:
    return [(frozenset(r["lhs"]), r["rhs"]) for r in table.select(["lhs", "rhs"]).to_pylist()]


def implies(fd: DataFrame, queries: DataFrame) -> DataFrame:
    """rel, lhs, rhs, implied for each row (rel, lhs, rhs) of queries; one relation's FDs are one group."""

    def answer(known: pa.Table, asked: pa.Table) -> pa.Table:
        fds = _of(known)
        out = [r | {"implied": r["rhs"] in r["lhs"] or implies_fd(fds, r["lhs"], r["rhs"])} for r in asked.to_pylist()]
        return pa.Table.from_pylist(out, schema=pa.schema([("rel", pa.string()), ("lhs", pa.list_(pa.int32())), ("rhs", pa.int32()), ("implied", pa.bool_())]))

    slim = fd.select("rel", "lhs", "rhs").distinct()
    return slim.groupBy("rel").cogroup(queries.select("rel", "lhs", "rhs").groupBy("rel")).applyInArrow(answer, "rel string, lhs array<int>, rhs int, implied boolean")


def minimal_cover(fd: DataFrame) -> DataFrame:
    """rel, lhs, rhs: a minimal cover of each relation's FDs."""

    def one(table: pa.Table) -> pa.Table:
        rel = table.column("rel")[0].as_py()
        rows = [{"rel": rel, "lhs": sorted(lhs), "rhs": r} for lhs, r in cover(_of(table))]
        return pa.Table.from_pylist(rows, schema=pa.schema([("rel", pa.string()), ("lhs", pa.list_(pa.int32())), ("rhs", pa.int32())]))

    return fd.select("rel", "lhs", "rhs").distinct().groupBy("rel").applyInArrow(one, "rel string, lhs array<int>, rhs int")


def candidate_keys(fd: DataFrame, attrs: DataFrame, most: int = 100_000) -> DataFrame:
    """rel, key: all minimal determining sets of each relation in attrs (rel, pos); an error if one has more than ``most``. They determine every column; a bag may still repeat rows."""

    def one(known: pa.Table, own: pa.Table) -> pa.Table:
        if not own.num_rows:
            return pa.table({"rel": pa.array([], pa.string()), "key": pa.array([], pa.list_(pa.int32()))})
        rel, arity = own.column("rel")[0].as_py(), own.num_rows
        rows = [{"rel": rel, "key": sorted(k)} for k in keys_of(_of(known), arity, most)]
        return pa.Table.from_pylist(rows, schema=pa.schema([("rel", pa.string()), ("key", pa.list_(pa.int32()))]))

    slim = fd.select("rel", "lhs", "rhs").distinct()
    return slim.groupBy("rel").cogroup(attrs.select("rel", "pos").distinct().groupBy("rel")).applyInArrow(one, "rel string, key array<int>")
