"""What each operator does to functional dependencies."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from depscope.sources.facts import local

KEEPING = ("selection", "extension", "negation", "intersection")
CHANGING = ("projection", "product", "join")
OPERATORS = ("projection", "extension", "selection", "product", "union", "intersection", "negation", "join")

# fixed values: the property matrix of the eight operators, in the order of OPERATORS
PROPERTIES = {
    "fds_preserved": (True, True, True, True, False, True, True, True),
    "positions_preserved": (False, True, True, False, True, True, True, False),
    "transitive_fds": (False, True, True, False, False, False, False, True),
    "equality_fds": (False, True, True, False, False, False, False, False),
    "instance_reduction": (False, False, True, False, False, True, True, True),
}


def matrix(spark: SparkSession) -> DataFrame:
    """operator, property, holds."""
    rows = [(op, p, v) for p, values in PROPERTIES.items() for op, v in zip(OPERATORS, values, strict=True)]
    return local(spark, rows, "operator string, property string, holds boolean")
