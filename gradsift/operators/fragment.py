"""Stages one and two: cut the parameter vector into fragments."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gradsift import schemas


def build_manifest(spark: SparkSession, layers: list[tuple[str, int]]) -> DataFrame:
    """The layers of a model, contiguous from 0."""
    rows, start = [], 0
    for i, (name, size) in enumerate(layers):
        if size < 1:
            raise ValueError(f"layer {name} has size {size}")
        rows.append((i, name, start, size))
        start += size
    return spark.createDataFrame(rows, schemas.MANIFEST)


def split_oversized(manifest: DataFrame, n_workers: int, stages: int = 2) -> DataFrame:
    """Fragments in the order of their starts. stages: 0, one fragment; 1, the
    layers; 2, layers above n_g / n_workers in n_workers pieces, of which the
    first size mod n_workers are longer by one."""
    n = F.lit(n_workers)
    if stages == 0:
        whole = manifest.agg(F.sum("size").alias("size"))
        return whole.select(F.lit(0).alias("frag_id"), F.lit(-1).alias("layer_id"), F.lit(0).alias("piece"), F.lit(0).cast("long").alias("start"), "size")
    total = manifest.agg(F.sum("size").alias("n_g"))
    pieces = F.when(F.col("size") * n > F.col("n_g"), n).otherwise(1) if stages == 2 else F.lit(1)
    cut = manifest.join(F.broadcast(total), how="cross").select("layer_id", "start", "size", pieces.alias("parts"))
    cut = cut.select("*", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("piece"))
    floor, odd = F.floor(F.col("size") / F.col("parts")), F.col("size") % F.col("parts")
    cut = cut.select(
        "layer_id",
        "piece",
        (F.col("start") + F.col("piece") * floor + F.least("piece", odd)).cast("long").alias("start"),
        (floor + (F.col("piece") < odd).cast("int")).cast("long").alias("size"),
    ).where("size > 0")
    # a numbering of the manifest, whose length is the model's, not the data's
    ordered = cut.agg(F.array_sort(F.collect_list(F.struct("start", "layer_id", "piece", "size"))).alias("f"))
    return ordered.select(F.posexplode("f").alias("frag_id", "f")).select("frag_id", "f.layer_id", "f.piece", "f.start", "f.size")


def layer_fragments(manifest: DataFrame) -> DataFrame:
    return split_oversized(manifest, 1, stages=1)


def cell_width(n_g: int, fragments: int) -> int:
    """Width of the stretches by which tag looks fragments up."""
    return max(1, (n_g or 1) // (4 * max(1, fragments)))


def tag(rows: DataFrame, fragments: DataFrame, width: int | None = None) -> DataFrame:
    """Add frag_id to rows with param_idx, by a broadcast hash join: the
    fragments are listed under every stretch of equal width that they touch,
    at most 5 for each fragment on average, and a row looks up its stretch.
    width: cell_width of the model; where it is not given, it is asked for."""
    if width is None:
        got = fragments.agg(F.sum("size").alias("n_g"), F.count("*").alias("n")).first()
        width = cell_width(got["n_g"], got["n"])
    cell = lambda c: c - F.pmod(c, F.lit(width))
    end = F.col("start") + F.col("size")
    listed = fragments.select("frag_id", F.col("start").alias("_a"), end.alias("_b"), F.explode(F.sequence(cell(F.col("start")), cell(end - 1), F.lit(width).cast("long"))).alias("_cell"))
    inside = (F.col("param_idx") >= F.col("_a")) & (F.col("param_idx") < F.col("_b"))
    return rows.withColumn("_cell", cell(F.col("param_idx"))).join(F.broadcast(listed), "_cell").where(inside).drop("_cell", "_a", "_b")


def tag_by_range(rows: DataFrame, fragments: DataFrame) -> DataFrame:
    """The general form of tag: a broadcast range join."""
    f = F.broadcast(fragments.select("frag_id", F.col("start").alias("_a"), (F.col("start") + F.col("size")).alias("_b")))
    return rows.join(f, (F.col("param_idx") >= F.col("_a")) & (F.col("param_idx") < F.col("_b"))).drop("_a", "_b")
