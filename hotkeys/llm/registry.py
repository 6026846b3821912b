"""Queries of the training-data operators and the SQL that some of them can be held against."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from hotkeys.llm.best_fit_packing import op5_best_fit_packing
from hotkeys.llm.byte_bpe import op7_byte_bpe
from hotkeys.llm.chat_format import op10_chat_format
from hotkeys.llm.exact_dedup import op6_exact_dedup
from hotkeys.llm.minmax_dedup import op9_minmax_dedup
from hotkeys.llm.oracles import ORACLES
from hotkeys.llm.pii import op3_pii
from hotkeys.llm.quality_rules import op1_quality_rules
from hotkeys.llm.repeated_passages import op2_suffix_dedup
from hotkeys.llm.token_counts import op8_token_counts
from hotkeys.llm.url_filter import op4_url_filter


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_quality_rules": op1_quality_rules,
        "op2_suffix_dedup": op2_suffix_dedup,
        "op3_pii": op3_pii,
        "op4_url_filter": op4_url_filter,
        "op5_best_fit_packing": op5_best_fit_packing,
        "op6_exact_dedup": op6_exact_dedup,
        "op7_byte_bpe": op7_byte_bpe,
        "op8_token_counts": op8_token_counts,
        "op9_minmax_dedup": op9_minmax_dedup,
        "op10_chat_format": op10_chat_format,
    }


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
