"""Queries of the training-data operators, one per operator, each over its whole table, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .bpe import op1_byte_bpe
from .fingerprint import op8_fingerprints
from .html import op3_html_text
from .jaccard import op10_ngram_jaccard_join
from .langid import op5_language_id
from .media import op6_media_chunks
from .packing import op9_best_fit_packing
from .secrets import op7_secret_scan
from .substring import OP2_SQL, op2_substring_dedup
from .toxicity import op4_toxicity

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_byte_bpe": op1_byte_bpe,
    "op2_substring_dedup": op2_substring_dedup,
    "op3_html_text": op3_html_text,
    "op4_toxicity": op4_toxicity,
    "op5_language_id": op5_language_id,
    "op6_media_chunks": op6_media_chunks,
    "op7_secret_scan": op7_secret_scan,
    "op8_fingerprints": op8_fingerprints,
    "op9_best_fit_packing": op9_best_fit_packing,
    "op10_ngram_jaccard_join": op10_ngram_jaccard_join,
}

SQL: dict[str, str] = {"op2_substring_dedup": OP2_SQL}
