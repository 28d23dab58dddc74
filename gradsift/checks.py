"""Invariants that a run can assert."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def repeated_picks(picks: DataFrame) -> int:
    """Indices picked more than once; 0 for the fragmented scheme."""
    return picks.groupBy("param_idx").count().where("count > 1").count()


def assert_disjoint(picks: DataFrame) -> DataFrame:
    if repeated_picks(picks):
        raise AssertionError("an index was picked by more than one worker")
    return picks


def finite(acc: DataFrame) -> DataFrame:
    """Reject NaN and infinities: NaN would sort above all magnitudes."""
    v = F.col("v").cast("double")
    if acc.where(F.isnan(v) | (F.abs(v) == float("inf"))).limit(1).count():
        raise ValueError("the accumulator holds a value that is not finite")
    return acc


def index_range(rows: DataFrame, n_g: int) -> int:
    """Rows whose parameter index is outside the vector."""
    return rows.where((F.col("param_idx") < 0) | (F.col("param_idx") >= n_g)).count()
