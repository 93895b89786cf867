"""Unions: which FDs of both operands hold on their union."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from depscope.functions import traces


def _sides(ops: DataFrame, left: DataFrame, right: DataFrame, constants: bool = False) -> DataFrame:
    """rel (the union), l_* and r_* columns of facts of its first and second operand with equal lhs and rhs; with ``constants``, also of a constant and any fact of that column."""
    one = ops.where("operator = 'union' AND operand = 1").select(F.col("dst").alias("rel"), F.col("src").alias("src1"))
    two = ops.where("operator = 'union' AND operand = 2").select(F.col("dst").alias("rel2"), F.col("src").alias("src2"))
    pair = one.join(two, F.col("rel") == F.col("rel2")).drop("rel2")
    a = left.select(*(F.col(c).alias(f"l_{c}") for c in left.columns))
    b = right.select(*(F.col(c).alias(f"r_{c}") for c in right.columns))
    out = pair.join(a, F.col("src1") == F.col("l_rel"))
    same = F.col("l_lhs") == F.col("r_lhs")
    if constants:
        same = same | (F.size("l_lhs") == 0) | (F.size("r_lhs") == 0)
    return out.join(b, (F.col("src2") == F.col("r_rel")) & (F.col("l_rhs") == F.col("r_rhs")) & same)


def _fact(pairs: DataFrame, trace, rule: str, lhs=None) -> DataFrame:
    return pairs.select(
        "rel", (F.col("l_lhs") if lhs is None else lhs).alias("lhs"), F.col("l_rhs").alias("rhs"), trace.alias("trace"),
        F.array_sort(F.array_union("l_mids", "r_mids")).alias("mids"), F.least("l_status", "r_status").alias("status"),
        F.lit(rule).alias("rule"), (F.greatest("l_level", "r_level") + 1).alias("level"),
    )


def union_by_trace(left: DataFrame, right: DataFrame, ops: DataFrame, shared_origin: DataFrame | None = None) -> DataFrame:
    """FDs that both operands hold by the same term. shared_origin (a, b: relations with a common ancestor) adds the stricter test."""
    pairs = _sides(ops, left, right).where("l_trace = r_trace")
    if shared_origin is not None:
        pairs = pairs.join(shared_origin, (F.col("src1") == shared_origin["a"]) & (F.col("src2") == shared_origin["b"]), "left_semi")
    return _fact(pairs, F.col("l_trace"), "union")


def union_naive(left: DataFrame, right: DataFrame, ops: DataFrame) -> DataFrame:
    """Every common FD, whatever computes it: unsound, kept for contrast."""
    return _fact(_sides(ops, left, right), F.array().cast("array<string>"), "union_naive")


def union_discriminated(left: DataFrame, right: DataFrame, ops: DataFrame) -> DataFrame:
    """FDs that both operands hold by different terms, where a column is a different constant in each: that column joins the left side.

    A column that is constant in one operand follows from any left side there.
    """
    both = F.array_union("l_lhs", "r_lhs")

    def constants(df: DataFrame, p: str) -> DataFrame:
        k = df.where((F.size("lhs") == 0) & (F.size("trace") == 1) & traces.is_constant(F.get("trace", F.lit(0))))
        return k.select(F.col("rel").alias(f"{p}k_rel"), F.col("rhs").alias(f"{p}k_pos"), F.get("trace", F.lit(0)).alias(f"{p}k"), F.split_part(F.get("trace", F.lit(0)), F.lit(":"), F.lit(2)).alias(f"{p}k_type"))

    pairs = _sides(ops, left, right, True).where("l_trace <> r_trace")
    pairs = pairs.join(constants(left, "l"), F.col("src1") == F.col("lk_rel"))
    pairs = pairs.join(constants(right, "r"), (F.col("src2") == F.col("rk_rel")) & (F.col("lk_pos") == F.col("rk_pos")))
    pairs = pairs.where((F.col("lk") != F.col("rk")) & (F.col("lk_type") == F.col("rk_type")) & (F.col("lk_pos") != F.col("l_rhs")) & ~F.array_contains(both, F.col("lk_pos")))
    a, b = F.concat(F.array("lk"), F.col("l_trace")), F.concat(F.array("rk"), F.col("r_trace"))
    branches = F.when(F.col("lk") < F.col("rk"), F.concat(a, b)).otherwise(F.concat(b, a))
    trace = F.concat(F.array(F.lit("D:case/5"), F.concat(F.lit("#"), F.col("lk_pos").cast("string"))), branches)
    return _fact(pairs, trace, "union_discriminated", F.array_sort(F.array_union(both, F.array("lk_pos"))))


def both_ways(delta: DataFrame, known: DataFrame, combine) -> DataFrame:
    """A semi-naive round of a binary rule: new facts on either side."""
    return combine(delta, known).unionByName(combine(known, delta))
