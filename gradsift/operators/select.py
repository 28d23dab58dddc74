"""Top-k by group, with four kernels that agree, and layer-wise selection.

window     one sort per group, which the planner cuts before the shuffle where
           a literal bound of PLANNER_LIMIT or less allows it; for a larger
           bound the threshold kernel takes over
two_phase  groups are first cut into sub-blocks of BLOCK_WIDTH parameters,
           whose own top rows are exact supersets of the group's share
threshold  a histogram of magnitudes finds the bucket that holds the k-th of
           each group; rows below it are dropped before any shuffle, and the
           others are sorted bucket by bucket, so that no task holds a group.
           Only a bucket of one magnitude cannot be split further
arrow      one partition by group in numpy
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from gradsift.operators.pack import publish

BLOCK_WIDTH = 1 << 22
#: Buckets of the histogram for each doubling of the magnitude.
PER_OCTAVE = 64
#: Largest literal rank for which the planner cuts groups by itself
#: (spark.sql.optimizer.windowGroupLimitThreshold).
PLANNER_LIMIT = 1000


def _ranked(rows: DataFrame, group: list[str], quota: str, most: int | None) -> DataFrame:
    order = Window.partitionBy(*group).orderBy(F.desc("_score"), "param_idx")
    out = rows.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= F.col(quota))
    return out.where(F.col("rank") <= most) if most and most <= PLANNER_LIMIT else out


def _bucket(score: Column) -> Column:
    """A number that never falls as the magnitude grows."""
    octave = F.floor(F.log2(score))
    inside = F.floor((score / F.pow(F.lit(2.0), octave) - 1) * PER_OCTAVE)
    return F.when(score > 0, octave * PER_OCTAVE + inside).otherwise(-(1 << 20)).cast("int")


def _by_bucket(rows: DataFrame, group: list[str], quota: str) -> DataFrame:
    rows = rows.withColumn("_bucket", _bucket(F.col("_score").cast("double")))
    cells = rows.groupBy(*group, "_bucket").agg(F.count("*").alias("_n"), F.first(quota).alias("_quota"))
    above = Window.partitionBy(*group).orderBy(F.desc("_bucket")).rowsBetween(Window.unboundedPreceding, -1)
    cells = cells.withColumn("_above", F.coalesce(F.sum("_n").over(above), F.lit(0))).where(F.col("_above") < F.col("_quota"))
    rows = rows.join(F.broadcast(cells.select(*group, "_bucket", "_above")), [*group, "_bucket"])
    order = Window.partitionBy(*group, "_bucket").orderBy(F.desc("_score"), "param_idx")
    rank = (F.row_number().over(order) + F.col("_above")).cast("int")
    return rows.withColumn("rank", rank).where(F.col("rank") <= F.col(quota)).drop("_bucket", "_above")


def topk_by_group(rows: DataFrame, group: list[str], score: Column, quota: str, kernel: str = "window", most: int | None = None) -> DataFrame:
    """The rows of largest score of every group, as many as its quota column
    says, with their rank; ties go to the lowest param_idx. A null or zero
    quota selects nothing. most: a bound of all quotas, if one is known. The
    histogram has one row a group and bucket, whatever the length of a group."""
    rows = rows.withColumn("_score", score).where(F.col(quota) > 0)
    if kernel == "arrow":
        return _numpy(rows, group, quota).drop("_score")
    if kernel == "threshold" or (kernel == "window" and most and most > PLANNER_LIMIT):
        return _by_bucket(rows, group, quota).drop("_score")
    if kernel == "two_phase":
        part = F.floor(F.col("param_idx") / BLOCK_WIDTH)
        rows = _ranked(rows.withColumn("_block", part), [*group, "_block"], quota, most).drop("rank", "_block")
    return _ranked(rows, group, quota, most).drop("_score")


def _numpy(rows: DataFrame, group: list[str], quota: str) -> DataFrame:
    def run(part: pd.DataFrame) -> pd.DataFrame:
        q = int(part[quota].iloc[0])
        s = part["_score"].to_numpy()
        if q < len(s):
            edge = -np.partition(-s, q - 1)[q - 1]
            part = part[s >= edge]
        part = part.sort_values(["_score", "param_idx"], ascending=[False, True]).head(q)
        return part.assign(rank=np.arange(1, len(part) + 1, dtype=np.int32))

    schema = T.StructType([*rows.schema.fields, T.StructField("rank", T.IntegerType())])
    return rows.groupBy(*group).applyInPandas(run, schema)


def layerwise(acc: DataFrame, quotas: DataFrame, owner: DataFrame, kernel: str = "window", most: int | None = None) -> DataFrame:
    """What every worker picks from its own fragments by its own accumulator.

    The broadcast join keeps, of each worker's rows, only those of the
    fragments in its bin: the search space shrinks to 1/n before any shuffle.
    """
    own = owner.join(quotas.select("worker", "frag_id", "quota"), ["worker", "frag_id"]).where("quota > 0")
    found = acc.join(publish(own), ["worker", "frag_id"])
    return topk_by_group(found, ["frag_id"], F.abs("v"), "quota", kernel, most).select("worker", "frag_id", "param_idx", "v", "rank")
