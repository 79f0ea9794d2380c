"""Queries of the text operators and the SQL of those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from vertexalg.llm.chat_format import OP6_SQL, op6_chat_format
from vertexalg.llm.decontamination import OP5_SQL, op5_decontamination
from vertexalg.llm.language_id import op1_language_id
from vertexalg.llm.near_dedup import OP7_SQL, op7_minhash_near_dedup
from vertexalg.llm.packing import op4_best_fit_packing
from vertexalg.llm.quality_classifier import op10_quality_classifier
from vertexalg.llm.secret_scan import OP2_SQL, op2_secret_scan
from vertexalg.llm.substring_dedup import OP3_SQL, op3_substring_dedup
from vertexalg.llm.url_filter import OP8_SQL, op8_url_filter
from vertexalg.llm.vector_search import op9_nearest_neighbours

_ALL = (op1_language_id, op2_secret_scan, op3_substring_dedup, op4_best_fit_packing, op5_decontamination, op6_chat_format, op7_minhash_near_dedup, op8_url_filter, op9_nearest_neighbours, op10_quality_classifier)
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in _ALL}
ORACLES: dict[str, str] = {
    "op2_secret_scan": OP2_SQL,
    "op3_substring_dedup": OP3_SQL,
    "op5_decontamination": OP5_SQL,
    "op6_chat_format": OP6_SQL,
    "op7_minhash_near_dedup": OP7_SQL,
    "op8_url_filter": OP8_SQL,
}
