"""The queries of this subpackage and their SQL twins, for the driver's entry module."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .decontaminate import op1_decontamination
from .language import op2_language_id
from .lm import OP10_SQL, op10_lm_scoring
from .mixing import OP9_SQL, op9_mixing
from .neardup import op3_near_duplicates
from .quality import op7_quality_rules
from .secrets import op4_secret_scan
from .substrings import op6_substring_dedup
from .toxicity import op5_toxicity
from .warc import OP8_SQL, op8_warc_revisits

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_decontamination": op1_decontamination,
    "op2_language_id": op2_language_id,
    "op3_near_duplicates": op3_near_duplicates,
    "op4_secret_scan": op4_secret_scan,
    "op5_toxicity": op5_toxicity,
    "op6_substring_dedup": op6_substring_dedup,
    "op7_quality_rules": op7_quality_rules,
    "op8_warc_revisits": op8_warc_revisits,
    "op9_mixing": op9_mixing,
    "op10_lm_scoring": op10_lm_scoring,
}

ORACLES: dict[str, str] = {
    "op8_warc_revisits": OP8_SQL,
    "op9_mixing": OP9_SQL,
    "op10_lm_scoring": OP10_SQL,
}
