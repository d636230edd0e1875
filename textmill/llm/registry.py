"""Queries and oracle SQL of the training-data operators."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import oracles
from .chat_format import op9_chat_format
from .decontaminate import op5_decontaminate
from .mixing import op1_mixing
from .quality_classifier import op4_quality_classifier
from .quality_rules import op7_quality_rules
from .secret_scan import op6_secret_scan
from .simhash import op8_simhash
from .substring_dedup import op10_substring_dedup
from .suffix_dedup import op3_suffix_dedup
from .token_output import op2_token_output

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_mixing": op1_mixing,
    "op2_token_output": op2_token_output,
    "op3_suffix_dedup": op3_suffix_dedup,
    "op4_quality_classifier": op4_quality_classifier,
    "op5_decontaminate": op5_decontaminate,
    "op6_secret_scan": op6_secret_scan,
    "op7_quality_rules": op7_quality_rules,
    "op8_simhash": op8_simhash,
    "op9_chat_format": op9_chat_format,
    "op10_substring_dedup": op10_substring_dedup,
}
ORACLE: dict[str, str] = {"op3_suffix_dedup": oracles.REPEATS, "op9_chat_format": oracles.CHAT, "op10_substring_dedup": oracles.PASSAGES}
