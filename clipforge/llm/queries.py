"""The operators as registered queries, and SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import license_digests, line_spread
from .leak_windows import op7_leak_windows
from .license_digests import op2_license_digests
from .line_spread import op8_line_spread
from .private_spans import op9_private_spans
from .quality_cnn import op4_quality_cnn
from .shingle_forest import op1_shingle_forest
from .source_mix import op6_source_mix
from .token_codes import op10_token_codes
from .toxicity import op5_toxicity
from .vantage_trees import op3_vantage_trees

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_shingle_forest": op1_shingle_forest,
    "op2_license_digests": op2_license_digests,
    "op3_vantage_trees": op3_vantage_trees,
    "op4_quality_cnn": op4_quality_cnn,
    "op5_toxicity": op5_toxicity,
    "op6_source_mix": op6_source_mix,
    "op7_leak_windows": op7_leak_windows,
    "op8_line_spread": op8_line_spread,
    "op9_private_spans": op9_private_spans,
    "op10_token_codes": op10_token_codes,
}

ORACLES: dict[str, str] = {"op2_license_digests": license_digests.ORACLE, "op8_line_spread": line_spread.ORACLE}
