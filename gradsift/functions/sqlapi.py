"""The SQL front door: functions by name, and one iteration as views."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from gradsift.config import RunConfig
from gradsift.functions import udfs
from gradsift.operators import fragment, select
from gradsift.operators.sparsifiers import Fragmented, Model


def register(spark: SparkSession) -> None:
    """block_norm, block_topk, l2_norm, and the table functions pack_bins and
    split_layer."""
    for name in ("block_norm", "block_topk", "l2_norm"):
        spark.udf.register(name, getattr(udfs, name))
    spark.udtf.register("pack_bins", udfs.PackBins)
    spark.udtf.register("split_layer", udfs.SplitLayer)


def iteration_views(spark: SparkSession, manifest: DataFrame, acc: DataFrame, cfg: RunConfig, t: int = 0) -> None:
    """Views fragments, quotas, bins, owner and picks of one iteration."""
    model = Model.of(manifest, cfg)
    tagged = fragment.tag(acc, model.fragments)
    quotas, bins, owner = Fragmented(cfg).plan(tagged, model, t)
    views = {"fragments": model.fragments, "quotas": quotas, "bins": bins, "owner": owner, "picks": select.layerwise(tagged, quotas, owner, cfg.kernel)}
    for name, df in views.items():
        df.createOrReplaceTempView(name)
