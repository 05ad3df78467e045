"""Registry of the subpackage's queries and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import chaining, exact_dedup, jaccard_join, langid, line_dedup, mixing, packing, quality_rules, suffix_dedup, toxicity
from .base import documents

Query = Callable[[SparkSession, str], DataFrame]


def queries() -> dict[str, Query]:
    return {
        "op1_line_dedup": lambda s, d: line_dedup.digest(documents(s, d)),
        "op2_quality_rules": lambda s, d: quality_rules.digest(documents(s, d)),
        "op3_exact_dedup": lambda s, d: exact_dedup.digest(s, documents(s, d)),
        "op4_mixing": lambda s, d: mixing.calibrated(s, documents(s, d)),
        "op5_suffix_dedup": lambda s, d: suffix_dedup.digest(s, documents(s, d)),
        "op6_chaining": lambda s, d: chaining.passages(s, documents(s, d)),
        "op7_packing": lambda s, d: packing.digest(s, documents(s, d)),
        "op8_language_id": lambda s, d: langid.identify(s, documents(s, d)),
        "op9_jaccard_join": lambda s, d: jaccard_join.similar(s, documents(s, d)),
        "op10_toxicity": lambda s, d: toxicity.classify(s, documents(s, d), s.read.parquet(f"{d}/labels.parquet")),
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op1_line_dedup": line_dedup.ORACLE_SQL,
        "op2_quality_rules": quality_rules.ORACLE_SQL,
        "op3_exact_dedup": exact_dedup.ORACLE_SQL,
        "op9_jaccard_join": jaccard_join.ORACLE_SQL,
    }
