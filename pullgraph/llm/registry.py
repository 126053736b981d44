"""Queries and oracle SQL of the text operators, for the driver's entry module."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .chat import OP4_SQL, op4_chat
from .language import op7_language
from .licenses import op9_license_scan
from .lines import op6_line_dedup
from .minhash import OP8_SQL, op8_minhash
from .packing import op10_packing
from .pieces import op3_sentencepiece
from .quality import op5_quality
from .suffixes import op2_suffix_dedup
from .topk import OP1_SQL, op1_exact_topk


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_exact_topk": op1_exact_topk,
        "op2_suffix_dedup": op2_suffix_dedup,
        "op3_sentencepiece": op3_sentencepiece,
        "op4_chat": op4_chat,
        "op5_quality": op5_quality,
        "op6_line_dedup": op6_line_dedup,
        "op7_language": op7_language,
        "op8_minhash": op8_minhash,
        "op9_license_scan": op9_license_scan,
        "op10_packing": op10_packing,
    }


def oracle_sql() -> dict[str, str]:
    return {"op1_exact_topk": OP1_SQL, "op4_chat": OP4_SQL, "op8_minhash": OP8_SQL}
