"""Which worker holds which training rows, and which batch takes them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def assign(rows: DataFrame, key: str, n_workers: int, exact: bool = False) -> DataFrame:
    """Add worker: a hash of the key, or in the exact lane the key itself."""
    source = F.col(key) if exact else F.xxhash64(key)
    return rows.withColumn("worker", F.pmod(source, F.lit(n_workers)).cast("int"))


def _number(key: str, batches: int, seed: int):
    return F.pmod(F.xxhash64(F.lit(seed), F.col(key)), F.lit(batches))


def numbered(rows: DataFrame, key: str, batches: int, seed: int = 42) -> DataFrame:
    """Add batch, the number of the batch that a row belongs to."""
    return rows.withColumn("batch", _number(key, batches, seed).cast("int"))


def span_of(batch: Column, batches: int, spans: int) -> Column:
    """The span of neighbouring batches that a batch belongs to, of at most
    `spans`."""
    n = min(batches, spans)
    return F.floor(batch.cast("long") * n / batches).cast("int")


def batch_of(rows: DataFrame, t: int, batches: int) -> DataFrame:
    """The rows of iteration t, of numbered rows."""
    return rows.where(F.col("batch") == t % batches)


def batch(rows: DataFrame, key: str, t: int, batches: int, seed: int = 42) -> DataFrame:
    """The rows of batch t of `batches`, the same at any partitioning."""
    return rows.where(_number(key, batches, seed) == t % batches)
