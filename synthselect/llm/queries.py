"""Queries of the corpus operators, each over its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .fingerprints import op1_minhash
from .licenses import op5_licenses
from .packing import op6_packing
from .pieces import op7_pieces
from .quality import op10_quality
from .secrets import op2_secrets
from .simhash import op8_simhash
from .suffixes import op9_suffixes
from .tokencount import op4_tokens
from .vecdedup import op3_vectors

Query = Callable[[SparkSession, str], DataFrame]


def queries() -> dict[str, Query]:
    return {
        "op1_minhash": op1_minhash,
        "op2_secrets": op2_secrets,
        "op3_vectors": op3_vectors,
        "op4_tokens": op4_tokens,
        "op5_licenses": op5_licenses,
        "op6_packing": op6_packing,
        "op7_pieces": op7_pieces,
        "op8_simhash": op8_simhash,
        "op9_suffixes": op9_suffixes,
        "op10_quality": op10_quality,
    }


def oracle_sql() -> dict[str, str]:
    return {}
