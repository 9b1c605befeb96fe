"""Registered queries of the text operators, and the SQL of those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable
from importlib import import_module

from pyspark.sql import DataFrame, SparkSession

from ..session import ship

NAMES = {
    "op1_suffix_array_dedup": "suffixdedup",
    "op2_best_fit_packing": "packing",
    "op3_exact_dedup": "exactdedup",
    "op4_exact_top_k": "topk",
    "op5_html_extraction": "htmlextract",
    "op6_lm_scoring": "hmm",
    "op7_line_dedup": "linededup",
    "op8_ngram_jaccard_join": "setjoin",
    "op9_mixing": "mixing",
    "op10_language_id": "langid",
}


def _query(name: str) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return getattr(import_module(f".{NAMES[name]}", __package__), name)(ship(spark), sf_dir)

    run.__name__ = name
    return run


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: _query(name) for name in NAMES}


def oracle_sql() -> dict[str, str]:
    found = {}
    for name, module in NAMES.items():
        sql = getattr(import_module(f".{module}", __package__), "ORACLE_SQL", None)
        if sql:
            found[name] = sql
    return found
