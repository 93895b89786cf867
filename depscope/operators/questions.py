"""Questions over the schema facts."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from depscope.operators import graph
from depscope.operators.fixpoint import seminaive


def reused_attribute_names(facts, ordered: bool = False) -> DataFrame:
    """r1, r2, name: attribute names in two relations; both orders, or r1 < r2 only."""
    a, b = facts.attrs.select(F.col("rel").alias("r1"), "name"), facts.attrs.select(F.col("rel").alias("r2"), F.col("name").alias("n2"))
    pairs = a.join(b, (F.col("name") == F.col("n2")) & ((F.col("r1") < F.col("r2")) if ordered else (F.col("r1") != F.col("r2"))))
    return pairs.select("r1", "r2", "name").distinct()


def views_calling_functions(facts) -> DataFrame:
    """view: derived relations with a call, built-in aggregates included."""
    return facts.derived_rels.select(F.col("name").alias("view")).join(facts.calls.select(F.col("rel").alias("view")), "view", "left_semi")


def views_calling(facts, fn: str) -> DataFrame:
    return facts.calls.where(F.col("fn") == fn).select(F.col("rel").alias("view")).distinct()


def affected_views(facts, table: str, strategy: str = "seminaive") -> DataFrame:
    """view, hops: views that a change of a table, of its rows or its structure, may reach."""
    there = graph.reach(facts.edges, [table], strategy)
    return there.join(facts.derived_rels, there["dst"] == F.col("name"), "left_semi").select(F.col("dst").alias("view"), "hops")


def affected_columns(facts, table: str, column: str) -> DataFrame:
    """rel, name: columns of registered views whose values come from a column, by copies and calls. Conditions are not values."""
    ops = facts.ops
    keep = ops.where("m IS NULL").select("dst", "src")
    mapped = ops.where("m IS NOT NULL").select("dst", "src", "m")
    within = facts.value_flows.distinct()
    start = facts.attrs.where((F.col("rel") == table) & (F.col("name") == column)).select("rel", "pos")

    def step(delta: DataFrame, known: DataFrame) -> DataFrame:
        same = delta.join(keep, delta["rel"] == keep["src"]).select(F.col("dst").alias("rel"), "pos")
        moved = delta.join(mapped, delta["rel"] == mapped["src"]).where(F.map_contains_key(F.col("m"), F.col("pos"))).select(F.col("dst").alias("rel"), F.element_at("m", F.col("pos")).alias("pos"))
        inside = delta.alias("d").join(within.alias("w"), (F.col("d.rel") == F.col("w.rel")) & (F.col("d.pos") == F.col("w.fro"))).select(F.col("d.rel").alias("rel"), F.col("w.to").alias("pos"))
        return same.unionByName(moved).unionByName(inside)

    found, _ = seminaive(start, step, ["rel", "pos"])
    views = facts.derived_rels.select(F.col("name").alias("rel"))
    return found.join(views, "rel", "left_semi").join(facts.attrs, ["rel", "pos"]).select("rel", "name").distinct()


def tables_changed_by(facts, fn: str) -> DataFrame:
    """table: base tables that a function may change, directly or through triggers and other functions."""
    there = graph.reach(facts.edges, [fn]).select(F.col("dst").alias("table"))
    return there.join(facts.base_rels.select(F.col("name").alias("table")), "table", "left_semi")


def tables_linked_by_function(facts) -> DataFrame:
    """a, b, fn: base table a depends on base table b through a function."""
    there = graph.reach(facts.edges)
    bases = facts.base_rels.select("name")
    to = there.alias("x").join(facts.funcs.select(F.col("name").alias("fn")), F.col("x.src") == F.col("fn")).join(bases.alias("ba"), F.col("x.dst") == F.col("ba.name")).select(F.col("x.dst").alias("a"), "fn")
    fro = there.alias("y").join(bases.alias("bb"), F.col("y.src") == F.col("bb.name")).select(F.col("y.src").alias("b"), F.col("y.dst").alias("via"))
    return to.join(fro, F.col("fn") == F.col("via")).select("a", "b", "fn").distinct()


def cyclic_tables_via_function(facts) -> DataFrame:
    """a, b: base tables that depend on each other through functions; a = b for a table that a function feeds back to itself."""
    one = tables_linked_by_function(facts).select("a", "b").distinct()
    back = one.select(F.col("a").alias("b"), F.col("b").alias("a"))
    return one.select("a", "b").intersect(back.select("a", "b"))


def objects_using(facts, operator: str | None = None, function: str | None = None, column: str | None = None) -> DataFrame:
    """rel: normal-form relations with an operator, views with a function, or relations with a column name."""
    parts = []
    if operator:
        parts.append(facts.ops.where(F.col("operator") == operator).select(F.col("dst").alias("rel")))
    if function:
        parts.append(facts.calls.where(F.col("fn") == function).select("rel"))
    if column:
        parts.append(facts.attrs.where(F.col("name") == column).select("rel"))
    out = parts[0].distinct()
    for p in parts[1:]:
        out = out.intersect(p.distinct())
    return out


def unused_objects(facts) -> DataFrame:
    """name, kind: base relations and functions that nothing reads or calls."""
    named = facts.base_rels.select("name", F.lit("table").alias("kind")).union(facts.funcs.select("name", F.lit("function")))
    used = facts.edges.where("kind IN ('reads', 'fires')").select(F.col("src").alias("name")).union(facts.edges.where("kind = 'calls'").select("dst"))
    return named.join(used, "name", "left_anti")


def dangling_references(facts) -> DataFrame:
    """name: objects that an edge names and nobody registered."""
    ends = facts.edges.select(F.explode(F.array("dst", "src")).alias("name")).distinct()
    known = facts.base_rels.select("name").union(facts.derived_rels.select("name")).union(facts.funcs.select("name")).union(facts.triggers.select("name"))
    return ends.join(known, "name", "left_anti")


def direct_only(facts, table: str) -> DataFrame:
    """view: what a catalog of direct dependencies alone answers to affected_views."""
    return facts.edges.where(F.col("src") == table).join(facts.derived_rels, F.col("dst") == F.col("name"), "left_semi").select(F.col("dst").alias("view")).distinct()


def tables_by_action(facts, action: str) -> DataFrame:
    """rel, trigger, role: tables whose insert, update or delete (``action``) a trigger watches, or that a trigger changes so."""
    watched = facts.triggers.where(F.col("event") == action).select(F.col("on_rel").alias("rel"), F.col("name").alias("trigger"), F.lit("watched").alias("role"))
    return watched.union(facts.triggers.where(F.col("action") == action).select("action_rel", "name", F.lit("changed")))


def views_by_aggregate(facts, fns: list[str]) -> DataFrame:
    """view, fn, name: the output columns of views that an aggregate of ``fns`` makes."""
    calls = facts.calls.where(F.col("fn").isin(fns)).select("rel", F.col("output").alias("pos"), "fn")
    return calls.join(facts.attrs, ["rel", "pos"]).select(F.col("rel").alias("view"), "fn", "name").distinct()
