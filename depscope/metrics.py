"""Measures of a propagation: soundness and recall against data, counts, term sizes, rounds and times."""

from __future__ import annotations

import time
from contextlib import contextmanager

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from depscope.operators import armstrong, validate


def counts(fd: DataFrame) -> DataFrame:
    """rel, rule, status, n with subtotals (NULL: all)."""
    return fd.rollup("rel", "rule", "status").agg(F.count("*").alias("n"))


def term_sizes(fd: DataFrame) -> DataFrame:
    """rel, n_facts, longest, mean_length of traces."""
    return fd.groupBy("rel").agg(F.count("*").alias("n_facts"), F.max(F.size("trace")).alias("longest"), F.round(F.avg(F.size("trace")), 3).alias("mean_length"))


def round_sizes(reached: DataFrame) -> DataFrame:
    """hops, n_pairs: the new pairs of each round of a semi-naive closure; the number of rows is the number of rounds that found any."""
    return reached.groupBy("hops").agg(F.count("*").alias("n_pairs"))


def soundness(views: dict[str, DataFrame], fds: list[tuple[str, tuple[str, ...], str]]) -> DataFrame:
    """rel, lhs, rhs, violating_groups of reported FDs that the data violate; none for a sound propagation."""
    return validate.check_many(views, fds).where("violating_groups > 0")


def recall(reported: list[tuple[tuple[str, ...], str]], discovered: list[tuple[tuple[str, ...], str]]) -> dict[str, int]:
    """How many minimal FDs of the data are reported, follow from reported ones, or hold on this instance only."""
    names = sorted({c for lhs, r in [*reported, *discovered] for c in (*lhs, r)})
    at = {c: i for i, c in enumerate(names)}
    fds = [(frozenset(at[c] for c in lhs), at[r]) for lhs, r in reported]
    told = {(frozenset(lhs), r) for lhs, r in reported}
    out = {"reported": 0, "implied": 0, "instance_only": 0}
    for lhs, r in discovered:
        kind = "reported" if (frozenset(lhs), r) in told else "implied" if armstrong.implies_fd(fds, {at[c] for c in lhs}, at[r]) else "instance_only"
        out[kind] += 1
    return out


def _stages(spark) -> dict[int, tuple[int, int, int]]:
    """Tasks, bytes read and bytes shuffled of each completed stage of the application."""
    sc, jvm = spark.sparkContext._jsc.sc(), spark._jvm
    sc.listenerBus().waitUntilEmpty()
    none = spark.sparkContext._gateway.new_array(jvm.double, 0)
    found = sc.statusStore().stageList(jvm.java.util.ArrayList(), False, False, none, jvm.java.util.ArrayList())
    stages = (found.apply(i) for i in range(found.size()))
    return {s.stageId(): (s.numCompleteTasks(), s.inputBytes(), s.shuffleWriteBytes()) for s in stages}


def cost(spark, run) -> dict[str, float]:
    """What a call costs: seconds, stages, tasks, bytes read from tables and bytes shuffled. Classic sessions only; run nothing beside it."""
    before, began = _stages(spark), time.perf_counter()
    run()
    seconds = time.perf_counter() - began
    new = [v for k, v in _stages(spark).items() if k not in before]
    return {"seconds": seconds, "stages": len(new), "tasks": sum(v[0] for v in new), "input_bytes": sum(v[1] for v in new), "shuffle_bytes": sum(v[2] for v in new)}


@contextmanager
def timed(into: dict, name: str):
    began = time.perf_counter()
    yield
    into[name] = time.perf_counter() - began
