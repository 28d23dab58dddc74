"""Saved state: lineage cuts, versioned state of a run, metrics."""

from __future__ import annotations

import gc
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir of the session. Where it is unset, a temporary
    folder, on one machine only: executors elsewhere could not read it."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.getCheckpointDir():
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        spark.sparkContext.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="gradsift-"))
    return spark.sparkContext.getCheckpointDir().rstrip("/")


def commit(df: DataFrame, label: str, by: str | None = None, unlike: tuple[str, ...] = ()) -> DataFrame:
    """df, written to the shared folder and read again: the iteration's
    boundary. A lost executor recomputes no earlier iteration. by: a column
    of few values, each of which gets a folder of its own. unlike: columns
    whose values hardly repeat, which no dictionary is made for."""
    path = f"{shared_dir(df.sparkSession)}/{label}-{uuid.uuid4().hex}"
    out = df.write.options(**{f"parquet.enable.dictionary#{c}": "false" for c in unlike})
    (out.partitionBy(by) if by else out).parquet(path)
    got = df.sparkSession.read.schema(df.schema).parquet(path)
    got.committed_at = path
    return got


def discard(*tables: DataFrame | None) -> None:
    """Delete committed tables that nothing reads any more."""
    for df in tables:
        path = getattr(df, "__dict__", {}).pop("committed_at", None)
        if path:
            _delete(df.sparkSession, path)


def collect_garbage(spark: SparkSession) -> None:
    """Let go of the shuffle files and broadcasts of plans that have run: they
    go when the driver collects its garbage, for which a run may give it no
    cause before the disk is full."""
    gc.collect()
    spark._jvm.System.gc()


def write_state(df: DataFrame, path: str, iteration: int) -> None:
    """Version `iteration` of a state table; writing it again replaces it."""
    df.sortWithinPartitions("param_idx").write.mode("overwrite").parquet(f"{path}/iteration={iteration}")


def read_state(spark: SparkSession, path: str, iteration: int) -> DataFrame:
    return spark.read.parquet(f"{path}/iteration={iteration}")


def drop_iteration(spark: SparkSession, path: str, iteration: int) -> None:
    """Delete version `iteration` of a state table."""
    _delete(spark, f"{path}/iteration={iteration}")


def _delete(spark: SparkSession, path: str) -> None:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


def write_metrics(metrics: DataFrame, path: str, format: str = "parquet") -> None:
    """Append metric rows as parquet, json or csv."""
    writer = metrics.write.mode("append").format(format)
    (writer.option("header", True) if format == "csv" else writer).save(path)
