from __future__ import annotations

import random

import pytest
from pyspark.sql import functions as F

from depscope.functions import traces
from depscope.operators import armstrong, closure
from depscope.sources.facts import check_fd_invariants, local, struct


def fact(rel, lhs, rhs, symbol, status="fact"):
    return (rel, sorted(lhs), rhs, [f"F:{symbol}/{len(lhs)}", *(f"#{c}" for c in sorted(lhs))], [], status, "declared", 0)


def test_terms():
    tokens = ["F:t/2", "F:s/1", "#1", "K:int:3"]
    assert traces.parse(tokens) == ("F:t/2", ("F:s/1", ("#1",)), ("K:int:3",))
    assert traces.pretty(tokens) == "F:t(F:s(#1), K:int:3)" and traces.depth(tokens) == 3
    assert traces.evaluate(tokens, {1: 10}, {"F:s/1": lambda x: x + 1, "F:t/2": lambda a, b: (a, b)}) == (11, "3")
    with pytest.raises(ValueError):
        traces.parse(["#1", "#2"])


def test_term_columns(spark):
    df = local(spark, [(["F:t/2", "#2", "#1"], {1: 4, 2: 7})], "t array<string>, m map<int,int>")
    row = df.select(traces.rename(F.col("t"), F.col("m")).alias("r"), traces.substitute(F.col("t"), F.lit(2), F.array(F.lit("F:s/1"), F.lit("#9"))).alias("s")).first()
    assert row.r == ["F:t/2", "#7", "#4"] and row.s == ["F:t/2", "F:s/1", "#9", "#1"]


def test_ring_ends_and_both_ways_agree(spark):
    fd = local(spark, [fact("r", [1], 2, "A"), fact("r", [2], 3, "B"), fact("r", [3], 2, "C")], struct("fd"))
    native, sizes = closure.close(fd)
    grouped = closure.close_grouped(fd)
    key = lambda d: sorted((x.rel, x.lhs, x.rhs, x.trace, x.mids) for x in d.collect())
    assert key(native) == key(grouped) and len(key(native)) == 4 and len(sizes) < 5


def test_closure_is_sound_complete_and_closed(spark):
    """Random FD sets, one relation each: everything derived follows, everything that follows is derived up to augmentation."""
    rnd, rows, truth = random.Random(11), [], {}
    for n in range(150):
        arity, fds = rnd.randrange(3, 6), set()
        for _ in range(rnd.randrange(1, 6)):
            rhs = rnd.randrange(1, arity + 1)
            lhs = frozenset(rnd.sample([c for c in range(1, arity + 1) if c != rhs], rnd.randrange(0, 3)))
            fds.add((lhs, rhs))
        truth[f"r{n}"] = (arity, fds)
        rows += [fact(f"r{n}", lhs, rhs, f"{n}_{i}") for i, (lhs, rhs) in enumerate(sorted(fds, key=str))]
    fd = local(spark, rows, struct("fd"))
    closed = closure.close_grouped(fd).cache()
    assert not check_fd_invariants(closed).count()
    found = {}
    for r in closed.collect():
        found.setdefault(r.rel, set()).add((frozenset(r.lhs), r.rhs))
    for rel, (arity, fds) in truth.items():
        assert all(armstrong.implies_fd(fds, lhs, rhs) for lhs, rhs in found[rel])
        for mask in range(1 << arity):
            start = frozenset(c for c in range(1, arity + 1) if mask >> (c - 1) & 1)
            for c in armstrong.closure_of(fds, start) - start:
                assert any(lhs <= start and rhs == c for lhs, rhs in found[rel]), (rel, fds, start, c)
    assert closure.close_grouped(closed).count() == closed.count()


def test_twins_and_limits(spark):
    same = [("r", [1], 2, ["F:A/1", "#1"], [], "fact", "x", 0), ("r", [1], 3, ["F:A/1", "#1"], [], "fact", "x", 0)]
    got = {(tuple(r.lhs), r.rhs) for r in closure.close_grouped(local(spark, same, struct("fd"))).collect()}
    assert got == {((1,), 2), ((1,), 3), ((2,), 3), ((3,), 2)}
    rows = [dict(zip(closure.COLUMNS, fact("wide", [a], b, f"{a}.{b}"), strict=True)) for a in range(1, 6) for b in range(1, 6) if a != b]
    closure_of_all = closure.close_rows(rows, max_lhs=1)
    assert all(len(r["lhs"]) <= 1 for r in closure_of_all)


def test_candidates_stay_candidates():
    rows = [dict(zip(closure.COLUMNS, f, strict=True)) for f in (fact("r", [1], 2, "A", "candidate"), fact("r", [2], 3, "B"))]
    got = {(r["lhs"], r["rhs"]): r["status"] for r in closure.close_rows(rows)}
    assert got == {((1,), 2): "candidate", ((2,), 3): "fact", ((1,), 3): "candidate"}


def test_covers_and_keys():
    fds = [(frozenset({1}), 2), (frozenset({2}), 3), (frozenset({1}), 3), (frozenset({1, 4}), 2)]
    assert armstrong.cover(fds) == [(frozenset({1}), 2), (frozenset({2}), 3)]
    assert armstrong.keys_of(fds, 4) == [frozenset({1, 4})]
    assert armstrong.keys_of([(frozenset({1}), 2), (frozenset({2}), 1)], 2) == [frozenset({1}), frozenset({2})]
