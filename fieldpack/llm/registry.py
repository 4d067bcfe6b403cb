"""The queries of this subpackage, and the SQL of those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .bpe import op3_byte_bpe
from .licenses import op10_license_scan
from .line_quality import op8_line_quality
from .mixing import op6_mix_sources
from .near_dedup import OP9_SQL, op9_near_dedup
from .rule_quality import op2_rule_quality
from .secrets import OP7_SQL, op7_secret_scan
from .topk import OP4_SQL, op4_top_k
from .toxicity import op1_toxicity
from .warc import OP5_SQL, op5_arc_to_warc

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_toxicity": op1_toxicity,
    "op2_rule_quality": op2_rule_quality,
    "op3_byte_bpe": op3_byte_bpe,
    "op4_top_k": op4_top_k,
    "op5_arc_to_warc": op5_arc_to_warc,
    "op6_mix_sources": op6_mix_sources,
    "op7_secret_scan": op7_secret_scan,
    "op8_line_quality": op8_line_quality,
    "op9_near_dedup": op9_near_dedup,
    "op10_license_scan": op10_license_scan,
}

ORACLES: dict[str, str] = {
    "op4_top_k": OP4_SQL,
    "op5_arc_to_warc": OP5_SQL,
    "op7_secret_scan": OP7_SQL,
    "op9_near_dedup": OP9_SQL,
}
