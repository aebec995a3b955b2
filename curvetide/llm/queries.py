"""The registered queries of the corpus operators and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import sql
from .embedding_dedup import op9_embedding_dedup
from .language_id import op6_language_id
from .mixing import op5_mixing
from .near_dedup import op4_near_dedup
from .quality import op10_quality_classifier
from .quality_rules import op8_quality_rules
from .sentencepiece_codec import op1_sentencepiece
from .substring_dedup import op2_substring_dedup
from .token_counts import op7_token_counts
from .warc import op3_warc


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = [op1_sentencepiece, op2_substring_dedup, op3_warc, op4_near_dedup, op5_mixing, op6_language_id, op7_token_counts, op8_quality_rules, op9_embedding_dedup, op10_quality_classifier]
    return {f.__name__: f for f in found}


def oracle_sql() -> dict[str, str]:
    return sql.oracle_sql()
