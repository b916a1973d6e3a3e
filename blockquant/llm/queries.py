"""Queries of this subpackage and, where DuckDB can express them, their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .bm25_leaks import op6_bm25_leaks
from .bpe_prefix import op8_bpe_prefix
from .chat_schemas import OP10_SQL, op10_chat_schemas
from .class_ngrams import op4_class_ngrams
from .compression_quality import op9_compression_quality
from .host_trust import op3_host_trust, op3_sql
from .learned_partitions import op7_learned_partitions
from .order_minhash import op5_order_minhash
from .pii_feistel import op1_pii_feistel
from .token_cache import op2_token_cache

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (op1_pii_feistel, op2_token_cache, op3_host_trust, op4_class_ngrams, op5_order_minhash, op6_bm25_leaks, op7_learned_partitions, op8_bpe_prefix, op9_compression_quality, op10_chat_schemas)}

ORACLES: dict[str, str] = {"op3_host_trust": op3_sql(), "op10_chat_schemas": OP10_SQL}
