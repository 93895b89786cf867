"""What the engine is compared with: direct metadata, the optimiser's own keys, and propagation without parts of it.

Propagation without traces, with every common FD kept in a union, with one pass over a recursion or with none are options of
propagate.run: ``traces="none", unions="drop"``, ``unions="naive"``, ``recursion="single_pass"`` and ``recursion="none"``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame

from depscope.operators import propagate
from depscope.plans.plan_reader import _seq
from depscope.sources.facts import local

WITHOUT = {
    "no_traces": {"traces": "none", "unions": "drop"},
    "naive_unions": {"traces": "none", "unions": "naive"},
    "shared_origin": {"require_shared_origin": True, "discriminated": False},
    "single_pass": {"recursion": "single_pass"},
    "no_recursion": {"recursion": "none"},
}


def without(facts, part: str) -> DataFrame:
    """The propagation's facts with one part left out or replaced by its plain form."""
    return propagate.run(facts, **WITHOUT[part])


def catalyst_keys(df: DataFrame) -> DataFrame:
    """key: column names of each distinct key that Catalyst knows of the optimised plan."""
    plan = df._jdf.queryExecution().optimizedPlan()
    found = []
    for key in _seq(plan.distinctKeys().toSeq()):
        found.append((",".join(sorted(a.name() for a in _seq(key.toSeq()))),))
    return local(df.sparkSession, sorted(set(found)), "key string")


def catalyst_constants(df: DataFrame) -> DataFrame:
    """constraint: what Catalyst infers to hold on every row of the optimised plan."""
    plan = df._jdf.queryExecution().optimizedPlan()
    rows = sorted({(c.sql(),) for c in _seq(plan.constraints().toSeq())})
    return local(df.sparkSession, rows, "constraint string")
