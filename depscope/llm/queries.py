"""The registered queries of the corpus operators, and DuckDB SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from depscope.llm.decontamination import OP8_SQL, op8_decontamination
from depscope.llm.mixing import OP7_SQL, op7_mixing
from depscope.llm.pii import op5_pii
from depscope.llm.quality_classifier import op4_quality_classifier
from depscope.llm.quality_rules import OP10_SQL, op10_quality_rules
from depscope.llm.secrets import op9_secrets
from depscope.llm.sharding import OP1_SQL, op1_sharding
from depscope.llm.simhash import op3_simhash
from depscope.llm.token_counts import op2_token_counts
from depscope.llm.url_filter import op6_url_filter


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_sharding": op1_sharding,
        "op2_token_counts": op2_token_counts,
        "op3_simhash": op3_simhash,
        "op4_quality_classifier": op4_quality_classifier,
        "op5_pii": op5_pii,
        "op6_url_filter": op6_url_filter,
        "op7_mixing": op7_mixing,
        "op8_decontamination": op8_decontamination,
        "op9_secrets": op9_secrets,
        "op10_quality_rules": op10_quality_rules,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op1_sharding": OP1_SQL,
        "op7_mixing": OP7_SQL,
        "op8_decontamination": OP8_SQL,
        "op10_quality_rules": OP10_SQL,
    }
