"""Generated view hierarchies for scale tests."""

from __future__ import annotations

from pyspark.sql import SparkSession

from depscope.plans.registry import SchemaRegistry
from depscope.sources.facts import OpNode


def hierarchy(spark: SparkSession, chains: int, depth: int, columns: int = 4) -> SchemaRegistry:
    """chains independent chains of depth views over one base relation each: selections, projections, and joins with the neighbour's base."""
    r = SchemaRegistry(spark)
    for c in range(chains):
        r.add_table(f"b{c}", [f"c{i}" for i in range(columns)])
        r.declare_key(f"b{c}", [1])
    every = {p: p for p in range(1, columns + 1)}
    for c in range(chains):
        below = f"b{c}"
        for d in range(depth):
            name, kind = f"v{c}_{d}", d % 3
            if kind == 0:
                node = OpNode(name, "selection", [below], columns, consts=[(columns, str(d), "int")])
            elif kind == 1:
                node = OpNode(name, "projection", [below], columns, maps=[{p: p for p in every}])
            else:
                # the last column is looked up in the neighbour's key and replaced by its second column
                joined = f"{name}.1"
                r.catalog.nodes[joined] = OpNode(joined, "join", [below, f"b{(c + 1) % chains}"], columns + 1, maps=[every, {1: columns, 2: columns + 1}])
                node = OpNode(name, "projection", [joined], columns, maps=[{**{p: p for p in range(1, columns)}, columns + 1: columns}])
            node.columns = [(f"c{i}", "int") for i in range(columns)]
            r.catalog.nodes[name] = node
            r.catalog.views[name] = node.columns
            below = name
    return r
