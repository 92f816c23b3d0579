"""Queries of the training-data operators and the SQL of those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import oracles
from .op1_sentencepiece import op1_sentencepiece
from .op2_packing import op2_packing
from .op3_chat import op3_chat
from .op4_embeddings import op4_embeddings
from .op5_substring import op5_substring
from .op6_minhash import op6_minhash
from .op7_language import op7_language
from .op8_host_rules import op8_host_rules
from .op9_quality import op9_quality
from .op10_licenses import op10_licenses


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = [op1_sentencepiece, op2_packing, op3_chat, op4_embeddings, op5_substring, op6_minhash, op7_language, op8_host_rules, op9_quality, op10_licenses]
    return {f.__name__: f for f in found}


def oracle_sql() -> dict[str, str]:
    return {"op3_chat": oracles.CHAT, "op4_embeddings": oracles.EMBEDDINGS, "op5_substring": oracles.SUBSTRING, "op8_host_rules": oracles.HOST_RULES}
