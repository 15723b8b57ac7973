"""The queries of the text operators and, where SQL expresses them, their DuckDB twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .decontam import op4_decontamination
from .fingerprints import op3_simhash
from .jaccard import op6_jaccard_join
from .language import op8_language_id
from .licenses import op5_license_scan
from .packing import op10_best_fit_packing
from .secrets import op9_secret_scan
from .sentences import op1_sentence_dedup
from .suffixes import op7_suffix_dedup
from .toxicity import op2_toxicity

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_sentence_dedup": op1_sentence_dedup,
    "op2_toxicity": op2_toxicity,
    "op3_simhash": op3_simhash,
    "op4_decontamination": op4_decontamination,
    "op5_license_scan": op5_license_scan,
    "op6_jaccard_join": op6_jaccard_join,
    "op7_suffix_dedup": op7_suffix_dedup,
    "op8_language_id": op8_language_id,
    "op9_secret_scan": op9_secret_scan,
    "op10_best_fit_packing": op10_best_fit_packing,
}

ORACLE_SQL: dict[str, str | None] = {}
