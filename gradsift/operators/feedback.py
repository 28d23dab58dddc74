"""Error feedback: what is not sent is kept and added to the next gradient."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def accumulate(error: DataFrame | None, grads: DataFrame, lr: float = 1.0, lr_mode: str = "accumulate") -> DataFrame:
    """Error plus gradient, by (worker, param_idx). With lr_mode "accumulate"
    the rate is applied here, else at the update."""
    scaled = grads.select("worker", "param_idx", (F.col("v") * F.lit(lr) if lr_mode == "accumulate" and lr != 1.0 else F.col("v")).alias("v"))
    if error is None:
        return scaled
    both = error.select("worker", "param_idx", F.col("v").cast("double")).unionByName(scaled.select("worker", "param_idx", F.col("v").cast("double")))
    return both.groupBy("worker", "param_idx").agg(F.sum("v").alias("v"))


def residual(acc: DataFrame, indices: DataFrame | None) -> DataFrame:
    """The next error: the accumulator without the exchanged entries. None
    stands for all indices."""
    if indices is None:
        return acc.select("worker", "param_idx", "v").where(F.lit(False))
    return acc.select("worker", "param_idx", "v").join(indices.select("param_idx"), "param_idx", "left_anti").where("v <> 0").select("worker", "param_idx", "v")
