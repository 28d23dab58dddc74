"""Readers: the given tables, gradient dumps in several formats, synthetic
gradients."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gradsift import schemas

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_gradients(spark: SparkSession, path: str, format: str = "parquet", blocked: bool = False) -> DataFrame:
    """(worker, param_idx, v) from a dump; blocked dumps hold arrays of
    consecutive parameters from `base` on."""
    rows = spark.read.schema(schemas.BLOCKS if blocked else schemas.GRADS).format(format).load(path)
    return unblock(rows) if blocked else rows


def unblock(blocks: DataFrame) -> DataFrame:
    return blocks.select("worker", "base", F.posexplode("vals").alias("at", "x")).select("worker", (F.col("base") + F.col("at")).alias("param_idx"), F.col("x").cast("double").alias("v"))


def block(grads: DataFrame, width: int = 4096) -> DataFrame:
    """Array form of dense gradients: one row for `width` parameters."""
    at = F.floor(F.col("param_idx") / width).cast("int")
    cells = F.array_sort(F.collect_list(F.struct("param_idx", "v")))
    return grads.groupBy("worker", at.alias("block")).agg(cells.alias("cells")).select("worker", "block", F.col("cells")[0]["param_idx"].alias("base"), F.transform("cells", lambda c: c["v"].cast("float")).alias("vals"))


def synthetic_gradients(spark: SparkSession, manifest: DataFrame, n_workers: int, seed: int = 42, partitions: int | None = None) -> DataFrame:
    """Normal gradients whose scale halves from layer to layer. Workers share
    a common part, as they do when they hold the same model."""
    layers = [(r["start"], r["size"], r["layer_id"]) for r in manifest.collect()]
    n_g = max(s + z for s, z, _ in layers)
    scale = F.lit(1.0)
    for start, _, layer in sorted(layers):
        scale = F.when(F.col("param_idx") >= start, F.lit(2.0**-layer)).otherwise(scale)
    base = spark.range(0, n_g, 1, partitions).select(F.col("id").alias("param_idx"), F.randn(seed).alias("common"))
    each = base.select("param_idx", "common", F.explode(F.sequence(F.lit(0), F.lit(n_workers - 1))).alias("worker"))
    # noise from a hash, so that a recomputed partition gives the same rows
    u = (F.pmod(F.xxhash64(F.lit(seed), "worker", "param_idx"), F.lit(1 << 52)) + 0.5) / float(1 << 52)
    w = (F.pmod(F.xxhash64(F.lit(seed + 1), "worker", "param_idx"), F.lit(1 << 52)) + 0.5) / float(1 << 52)
    normal = F.sqrt(-2 * F.log(u)) * F.cos(2 * F.pi() * w)
    return each.select("worker", "param_idx", ((F.col("common") + normal) * scale).alias("v"))
