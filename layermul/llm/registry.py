"""The subpackage's queries and their SQL, for __spark_entry__."""

from __future__ import annotations

from collections.abc import Callable
from importlib import import_module

from pyspark.sql import DataFrame, SparkSession

#: query name -> module, oracle function or None where SQL cannot express it
OPERATORS = {
    "op1_decontaminate": ("decontaminate", "op1_oracle"),
    "op2_url_filter": ("url_filter", None),
    "op2_rules": ("url_filter", "op2_rules_oracle"),
    "op3_license_scan": ("license_scan", None),
    "op3_base": ("license_scan", "op3_base_oracle"),
    "op4_sharding": ("sharding", None),
    "op5_mixing": ("mixing", "op5_oracle"),
    "op6_pii": ("pii", None),
    "op6_base": ("pii", "op6_base_oracle"),
    "op7_secret_scan": ("secret_scan", "op7_oracle"),
    "op8_ngram_join": ("ngram_join", "op8_oracle"),
    "op9_quality": ("quality", None),
    "op10_fingerprint": ("fingerprint", None),
}


def _query(name: str) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return getattr(import_module(f"{__package__}.{OPERATORS[name][0]}"), name)(spark, sf_dir)

    return run


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: _query(name) for name in OPERATORS}


def oracle_sql() -> dict[str, str]:
    return {name: getattr(import_module(f"{__package__}.{module}"), sql)() for name, (module, sql) in OPERATORS.items() if sql}
