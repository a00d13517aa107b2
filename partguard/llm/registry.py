"""Queries of this subpackage and the SQL of those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .hyperdim import op2_language_id
from .licenses import op9_licenses
from .line_rules import OP4_SQL, op4_line_rules
from .nbsvm import op6_quality_classifier
from .near_dedup import op7_near_dedup
from .near_dedup_sql import OP7_SQL
from .merkle import OP5_SQL, op5_fingerprints
from .packing import op8_packing
from .pieces import op3_pieces
from .token_files import op1_token_files
from .warc import OP10_SQL, op10_warc

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_token_files": op1_token_files,
    "op2_language_id": op2_language_id,
    "op3_pieces": op3_pieces,
    "op4_line_rules": op4_line_rules,
    "op6_quality_classifier": op6_quality_classifier,
    "op7_near_dedup": op7_near_dedup,
    "op5_fingerprints": op5_fingerprints,
    "op10_warc": op10_warc,
    "op8_packing": op8_packing,
    "op9_licenses": op9_licenses,
}
SQL: dict[str, str] = {
    "op4_line_rules": OP4_SQL,
    "op5_fingerprints": OP5_SQL,
    "op10_warc": OP10_SQL,
    "op7_near_dedup": OP7_SQL,
}
