"""The collectives: gather of indices, mean of values, update of the model."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Indices up to which a set is broadcast: some 40 bytes each in the driver's
#: table of them, for each run that is driven at a time. Above, the set is
#: joined by a shuffle on both sides.
BROADCAST_ROWS = 500_000


def union_indices(picks: DataFrame, disjoint: bool = False) -> DataFrame:
    """All picked indices, once. Disjoint picks need no shuffle for that."""
    rows = picks.select("param_idx")
    return rows if disjoint else rows.distinct()


all_gather = union_indices


def sized(indices: DataFrame, at_most: int | None) -> DataFrame:
    """indices, to be broadcast if a known bound on their number allows it."""
    return F.broadcast(indices) if at_most is not None and at_most <= BROADCAST_ROWS else indices


def average(acc: DataFrame, indices: DataFrame | None, n_workers: int, at_most: int | None = None) -> DataFrame:
    """Mean over all workers at every index; an absent row is a zero, so the
    sum is divided by the number of workers and not of rows."""
    rows = acc if indices is None else acc.join(sized(indices, at_most), "param_idx", "left_semi")
    return rows.groupBy("param_idx").agg((F.sum("v") / F.lit(n_workers)).alias("mean"))


all_reduce = average


def apply_update(params: DataFrame, mean: DataFrame, lr: float = 1.0, lr_mode: str = "accumulate") -> DataFrame:
    """params minus the mean, times the rate where it was not applied yet."""
    step = F.coalesce("mean", F.lit(0.0)) * (F.lit(1.0) if lr_mode == "accumulate" else F.lit(lr))
    return params.join(mean, "param_idx", "left").select("param_idx", (F.col("value") - step).alias("value"))
