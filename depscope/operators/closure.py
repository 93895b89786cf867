"""Transitive closure of FD facts: extended transitivity with trace substitution, and twin columns."""

from __future__ import annotations

from collections import defaultdict

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema

from depscope.functions import traces
from depscope.operators.fixpoint import seminaive

KEY = ["rel", "lhs", "rhs", "trace", "mids", "status"]
COLUMNS = ["rel", "lhs", "rhs", "trace", "mids", "status", "rule", "level"]
NO_INTS = "array<int>"
#: Facts of one relation at which its closure in one task stops with an error that names strategy 'joint', which has no such limit.
MAX_FACTS = 200_000


class TooManyFacts(RuntimeError):
    """A relation whose FDs multiply beyond MAX_FACTS."""


def compose(first: DataFrame, second: DataFrame, prune: bool = True, keep_traces: bool = True, max_lhs: int | None = None) -> DataFrame:
    """Every fact of second whose left side holds the right side of a fact of first, with that column replaced by its left side.

    The two meet in an equi-join on relation and column. mids are the columns that a derivation has passed through; a
    derivation that comes back to one is dropped, which bounds the traces and loses no FD: a repeated target on a path can be cut out,
    and a source that is also passed through makes the FD follow from a smaller one.
    """
    a = first.select(*(F.col(c).alias(f"a_{c}") for c in COLUMNS))
    g = second.select(*(F.col(c).alias(f"g_{c}") for c in COLUMNS), F.explode("lhs").alias("g_at"))
    pairs = a.join(g, (F.col("a_rel") == F.col("g_rel")) & (F.col("a_rhs") == F.col("g_at"))).where(~F.array_contains("a_lhs", F.col("g_rhs")))
    lhs = F.array_sort(F.array_union("a_lhs", F.array_except("g_lhs", F.array("a_rhs"))))
    mids = F.array_sort(F.array_union(F.array_union("a_mids", "g_mids"), F.array("a_rhs")))
    trace = traces.substitute(F.col("g_trace"), F.col("a_rhs"), F.col("a_trace")) if keep_traces else F.array().cast("array<string>")
    out = pairs.select(
        F.col("a_rel").alias("rel"), lhs.alias("lhs"), F.col("g_rhs").alias("rhs"), trace.alias("trace"),
        (mids if prune else F.array().cast(NO_INTS)).alias("mids"),
        F.least("a_status", "g_status").alias("status"),  # a candidate sorts before a fact
        F.lit("transitive").alias("rule"), (F.greatest("a_level", "g_level") + 1).alias("level"),
    )
    out = out.where(~F.array_contains("lhs", F.col("rhs")))
    if prune:
        out = out.where(~F.array_contains("mids", F.col("rhs")) & ~F.arrays_overlap("lhs", "mids"))
    return out.where(F.size("lhs") <= max_lhs) if max_lhs is not None else out


def equate_twins(delta: DataFrame, known: DataFrame) -> DataFrame:
    """Columns that one term on the same sources computes are equal, so each determines the other."""
    a = delta.select("rel", "lhs", "trace", F.col("rhs").alias("x"), F.col("status").alias("s"), F.col("level").alias("l"))
    b = known.select(F.col("rel").alias("r2"), F.col("lhs").alias("l2"), F.col("trace").alias("t2"), F.col("rhs").alias("y"), F.col("status").alias("s2"), F.col("level").alias("v2"))
    pairs = a.join(b, (F.col("rel") == F.col("r2")) & (F.col("lhs") == F.col("l2")) & (F.col("trace") == F.col("t2"))).where("x <> y")

    def way(x: str, y: str) -> DataFrame:
        return pairs.select(
            "rel", F.array(x).alias("lhs"), F.col(y).alias("rhs"), F.array(traces.column(F.col(x))).alias("trace"), F.array().cast(NO_INTS).alias("mids"),
            F.least("s", "s2").alias("status"), F.lit("twins").alias("rule"), (F.greatest("l", "v2") + 1).alias("level"),
        )

    return way("x", "y").unionByName(way("y", "x"))


def step(delta: DataFrame, known: DataFrame, prune: bool = True, keep_traces: bool = True, twins: bool = True, max_lhs: int | None = None) -> DataFrame:
    """One semi-naive round over facts of relations in scope."""
    out = compose(delta, known, prune, keep_traces, max_lhs).unionByName(compose(known, delta, prune, keep_traces, max_lhs))
    return out.unionByName(equate_twins(delta, known)) if twins and keep_traces else out


def close_rows(rows: list[dict], prune: bool = True, keep_traces: bool = True, twins: bool = True, max_lhs: int | None = None) -> list[dict]:
    """The closure of one relation's facts in memory, by the rules of step(), semi-naive over a queue."""
    known: dict[tuple, dict] = {}
    by_rhs: dict[int, list[dict]] = defaultdict(list)
    by_lhs: dict[int, list[dict]] = defaultdict(list)
    by_term: dict[tuple, list[dict]] = defaultdict(list)
    queue: list[dict] = []

    def add(lhs: tuple, rhs: int, trace: tuple, mids: tuple, status: str, rule: str, level: int, why: tuple = ()) -> None:
        key = (lhs, rhs, trace, mids, status)
        if key in known or rhs in lhs or (max_lhs is not None and len(lhs) > max_lhs):
            return
        known[key] = row = {"rel": rel, "lhs": lhs, "rhs": rhs, "trace": trace, "mids": mids, "status": status, "rule": rule, "level": level, "why": why}
        if len(known) > MAX_FACTS:
            raise TooManyFacts(f"{rel} has more than {MAX_FACTS} FD facts; use strategy='joint', which shuffles them, or give max_lhs")
        queue.append(row)

    def composed(a: dict, g: dict) -> None:
        b, d = a["rhs"], g["rhs"]
        if d in a["lhs"]:
            return
        lhs = tuple(sorted({*a["lhs"], *g["lhs"]} - ({b} - set(a["lhs"]))))
        mids = tuple(sorted({*a["mids"], *g["mids"], b}))
        if prune and (d in mids or set(lhs) & set(mids)):
            return
        token = f"#{b}"
        trace = tuple(x for t in g["trace"] for x in (a["trace"] if t == token else (t,))) if keep_traces else ()
        add(lhs, d, trace, mids if prune else (), min(a["status"], g["status"]), "transitive", max(a["level"], g["level"]) + 1, (a, g))

    rel = rows[0]["rel"] if rows else ""
    for r in rows:
        add(tuple(r["lhs"]), r["rhs"], tuple(r["trace"]), tuple(r["mids"]), r["status"], r["rule"], r["level"], r.get("why", ()))
    at = 0
    while at < len(queue):
        new = queue[at]
        at += 1
        by_rhs[new["rhs"]].append(new)
        for c in new["lhs"]:
            by_lhs[c].append(new)
        for g in list(by_lhs[new["rhs"]]):
            composed(new, g)
        for c in new["lhs"]:
            for a in list(by_rhs[c]):
                composed(a, new)
        if twins and keep_traces:
            same = by_term[new["lhs"], new["trace"]]
            for other in same:
                if other["rhs"] != new["rhs"]:
                    for x, y in ((other["rhs"], new["rhs"]), (new["rhs"], other["rhs"])):
                        add((x,), y, (f"#{x}",), (), min(other["status"], new["status"]), "twins", max(other["level"], new["level"]) + 1, (other, new))
            same.append(new)
    return list(known.values())


def close_grouped(fd: DataFrame, prune: bool = True, keep_traces: bool = True, twins: bool = True, max_lhs: int | None = None) -> DataFrame:
    """close(), with each relation's fixpoint inside one task: one shuffle by relation instead of one job a round."""
    schema = fd.schema

    def closed(table: pa.Table) -> pa.Table:
        return pa.Table.from_pylist(close_rows(table.to_pylist(), prune, keep_traces, twins, max_lhs), schema=made)

    made = to_arrow_schema(schema)
    return fd.groupBy("rel").applyInArrow(closed, schema)


def scope(facts, which: str = "paper") -> DataFrame:
    """rel: relations in which new transitive FDs can appear: base, join, with an equality, with a constant; 'all' adds intersections and calls."""
    rels = facts.base_rels.select(F.col("name").alias("rel")).union(facts.ops.where("operator = 'join'").select("dst"))
    rels = rels.union(facts.eqconds.select("rel")).union(facts.constconds.select("rel")).union(facts.closing)
    if which == "all":
        rels = rels.union(facts.ops.where("operator IN ('intersection', 'product', 'union', 'recursion')").select("dst")).union(facts.node_calls.select("rel"))
    return rels.distinct()


def close(fd: DataFrame, scope_rels: DataFrame | None = None, prune: bool = True, keep_traces: bool = True, twins: bool = True, max_rounds: int | None = None, max_lhs: int | None = None) -> tuple[DataFrame, list[int]]:
    """The closure of fd alone, and new facts by round. Facts of relations outside scope_rels stay as they are."""
    inside = fd if scope_rels is None else fd.join(scope_rels.distinct(), "rel", "left_semi")
    found, sizes = seminaive(inside, lambda d, k: step(d, k, prune, keep_traces, twins, max_lhs), KEY, max_rounds)
    if scope_rels is not None:
        found = found.unionByName(fd.join(scope_rels.distinct(), "rel", "left_anti"))
    return found, sizes
