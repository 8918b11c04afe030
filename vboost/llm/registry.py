"""The queries of this subpackage and their SQL."""

from __future__ import annotations

import importlib
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import oracles

MODULES = (
    "op1_ngram_jaccard",
    "op2_mix_sources",
    "op3_chat_format",
    "op4_html_extract",
    "op5_quality_rules",
    "op6_license_scan",
    "op7_quality_classifier",
    "op8_token_output",
    "op9_decontaminate",
    "op10_toxicity",
)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: getattr(importlib.import_module(f"{__package__}.{name}"), name) for name in MODULES}


def oracle_sql() -> dict[str, str]:
    return dict(oracles.SQL)
