"""Linear recursion: FDs of the base case are candidates of the recursive relation; those that the step gives back by the same term hold."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from depscope.operators.fixpoint import Growing
from depscope.sources.facts import Catalog, local


class NonLinearRecursion(ValueError):
    """A step that reads its recursive relation more than once, or relations that recur through each other."""


def below(catalog: Catalog, rel: str) -> set[str]:
    """The relations that rel reads, directly or not."""
    seen, todo = set(), [rel]
    while todo:
        node = catalog.nodes.get(todo.pop())
        for src in node.inputs if node else []:
            if src not in seen:
                seen.add(src)
                todo.append(src)
    return seen


def detect(catalog: Catalog) -> list[tuple[str, str, str]]:
    """(recursive relation, base case, step) of every union that reads itself through exactly one operand, once."""
    found = []
    for name, node in catalog.nodes.items():
        if name not in below(catalog, name):
            continue
        if node.operator != "union":
            continue
        back = [src for src in node.inputs if src == name or name in below(catalog, src)]
        if len(back) == len(node.inputs):
            inner = [s for s in back if s in catalog.nodes and catalog.nodes[s].operator == "union"]
            if inner:
                continue  # the inner union is the recursive one
            raise NonLinearRecursion(f"{name} has no base case")
        body = {x for x in below(catalog, back[0]) | {back[0]} if x in catalog.nodes and name in below(catalog, x)} - {name}
        if sum(catalog.nodes[x].inputs.count(name) for x in body) != 1:
            raise NonLinearRecursion(f"{name} is read more than once by its step")
        base = next(s for s in node.inputs if s not in back)
        found.append((name, base, back[0]))
    return found


def ordered(catalog: Catalog) -> list[tuple[str, str, str]]:
    """The recursions, those that others read first."""
    return sorted(catalog.recdefs, key=lambda r: len({x[0] for x in catalog.recdefs} & below(catalog, r[0])))


def body(catalog: Catalog, rec: tuple[str, str, str]) -> list[str]:
    """The relations of the step: they read the recursive one and are read by it."""
    return [x for x in below(catalog, rec[0]) if x in catalog.nodes and rec[0] in below(catalog, x) and x != rec[0]]


def _recdefs(propagation, recs: list[tuple[str, str, str]]) -> DataFrame:
    return local(propagation.facts.spark, [tuple(r) for r in recs], "rec string, rec_base string, rec_step string")


def seed(fd: DataFrame, recdefs: DataFrame) -> DataFrame:
    """The base cases' FDs as candidates of their recursive relations."""
    found = fd.where("status = 'fact'").join(recdefs, fd["rel"] == recdefs["rec_base"])
    return found.select(F.col("rec").alias("rel"), "lhs", "rhs", "trace", "mids", F.lit("candidate").alias("status"), F.lit("seed").alias("rule"), "level")


def push(propagation, facts_so_far: DataFrame, candidates: DataFrame, recs: list[tuple[str, str, str]]) -> DataFrame:
    """Candidates of the whole steps: all rules over the steps' operators, facts and candidates mixed."""
    inside = sorted({x for rec in recs for x in body(propagation.facts.catalog, rec)})
    if propagation.o.strategy != "joint":
        return propagation.pushed(facts_so_far, candidates, inside, [r[0] for r in recs]).where("status = 'candidate'")
    return propagation.settle(facts_so_far.unionByName(candidates), propagation.ops.where(F.col("dst").isin(inside))).where("status = 'candidate'")


def survivors(candidates: DataFrame, pushed: DataFrame, recdefs: DataFrame) -> DataFrame:
    """The candidates that their steps give back with the same columns and term."""
    back = pushed.join(recdefs, pushed["rel"] == recdefs["rec_step"]).select(F.col("rec").alias("of"), F.col("lhs").alias("l"), F.col("rhs").alias("r"), F.col("trace").alias("t")).distinct()
    on = (F.col("rel") == F.col("of")) & (F.col("lhs") == F.col("l")) & (F.col("rhs") == F.col("r")) & (F.col("trace") == F.col("t"))
    return candidates.join(back, on, "left_semi")


def conclude(propagation, fd: DataFrame, recs: list[tuple[str, str, str]], mode: str = "fixpoint") -> tuple[DataFrame, list[int]]:
    """FDs of recursive relations that don't read each other, and the number of candidates by outer round.

    'single_pass' accepts what one pass gives back. That can be wrong, as a candidate may lean on another that doesn't survive;
    'fixpoint' seeds again with the survivors until all survive, so that the last set proves itself.
    """
    table, recdefs = Growing(fd.sparkSession, fd.schema), _recdefs(propagation, recs)
    now = table.add(seed(fd, recdefs))
    sizes = [now.count()]
    while sizes[-1]:
        left = table.add(survivors(now, push(propagation, fd, now, recs), recdefs))
        sizes.append(left.count())
        now = left
        if mode == "single_pass" or sizes[-1] == sizes[-2]:
            break
    return now.select("rel", "lhs", "rhs", "trace", "mids", F.lit("fact").alias("status"), F.lit("recursion").alias("rule"), "level"), sizes
