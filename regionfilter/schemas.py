"""Declared schemas, and the check that every public function makes of its input."""

from __future__ import annotations

from pyspark.sql import DataFrame

HISTOGRAM = "seg int, kc bigint, qc bigint"
REGIONS = "region int, seg_lo int, seg_hi int, n_keys bigint, a double, b double"
PLAN = "region int, seg_lo int, seg_hi int, a double, b double, rate double, n_keys bigint, bits bigint, hashes int"
WORDS = "region int, word bigint, bits bigint"
CURVE = "method string, k int, target double, backup_bits double, expected_rate double"


class SchemaError(ValueError):
    """An input lacks columns."""


def require(df: DataFrame, *columns: str) -> DataFrame:
    """df itself, if it has the columns."""
    lacking = [c for c in columns if c not in df.columns]
    if lacking:
        raise SchemaError(f"missing columns {lacking}; found {df.columns}")
    return df
