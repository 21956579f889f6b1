"""Queries of this subpackage, and SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .byte_bpe import op3_byte_bpe
from .fingerprint import op5_fingerprints
from .language_id import op10_language_id
from .mixing import op7_mixing
from .ngram_join import OP1_SQL, op1_ngram_jaccard_join
from .quotes import OP4_SQL, op4_chat_formatting
from .substring_dedup import OP8_SQL, op8_substring_dedup
from .token_count import op2_token_counts
from .vector_search import op9_vector_search
from .warc import OP6_SQL, op6_warc


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = (op1_ngram_jaccard_join, op2_token_counts, op3_byte_bpe, op4_chat_formatting, op5_fingerprints, op6_warc, op7_mixing, op8_substring_dedup, op9_vector_search, op10_language_id)
    return {f.__name__: f for f in found}


def oracle_sql() -> dict[str, str]:
    return {"op1_ngram_jaccard_join": OP1_SQL, "op4_chat_formatting": OP4_SQL, "op6_warc": OP6_SQL, "op8_substring_dedup": OP8_SQL}
