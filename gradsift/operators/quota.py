"""How many parameters each fragment may give: quotas by norm."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def fragment_norms(acc: DataFrame, fragments: DataFrame, n_workers: int, p: int = 2) -> DataFrame:
    """(worker, frag_id, size, norm) for every worker and fragment; absent
    rows are zeros."""
    v = F.col("v").cast("double")
    norm = F.sqrt(F.sum(v * v)) if p == 2 else F.sum(F.abs(v))
    found = acc.groupBy("worker", "frag_id").agg(norm.alias("norm"))
    every = fragments.select("frag_id", "size", F.explode(F.sequence(F.lit(0), F.lit(n_workers - 1))).alias("worker"))
    return every.join(found, ["worker", "frag_id"], "left").select("worker", "frag_id", "size", F.coalesce("norm", F.lit(0.0)).alias("norm"))


def prioritise(norms: DataFrame) -> DataFrame:
    """Add priority: 1 for the largest norm of a worker, ties by fragment."""
    order = Window.partitionBy("worker").orderBy(F.desc("norm"), "frag_id")
    return norms.withColumn("priority", F.row_number().over(order))


def _rounded(x: Column, rounding: str) -> Column:
    return {"nearest": F.floor(x + 0.5), "floor": F.floor(x), "ceil": F.ceil(x)}[rounding].cast("long")


def assign(norms: DataFrame, k: int, rounding: str = "nearest", cap: bool = True, min_quota: int = 0, policy: str = "norm", refill: bool = False) -> DataFrame:
    """Add priority and quota.

    Fragments are walked in priority order; each takes of the k not yet given
    the share that its weight has in the weight not yet walked, and both
    remainders shrink by what it took (the rounded quota). The walk is a fold
    over one array for each worker, inside the JVM. The array is as long as
    the fragment list, which is the model's and not the data's size.
    refill: a second walk hands what the caps left over to fragments with room.
    """
    weight = {"norm": F.col("norm"), "size": F.col("size").cast("double"), "energy": F.col("norm") * F.col("norm")}[policy]
    item = F.struct((-weight).alias("order"), "frag_id", "size", "norm", weight.alias("weight"))
    per_worker = norms.groupBy("worker").agg(F.array_sort(F.collect_list(item)).alias("items"))
    empty = F.expr("cast(array() as array<bigint>)")
    total = F.aggregate("items", F.lit(0.0), lambda s, x: s + x["weight"])
    start = F.struct(F.lit(k).cast("long").alias("k"), total.alias("w"), empty.alias("out"))

    def walk(s, x):
        share = F.when(s["w"] > 0, s["k"] * x["weight"] / s["w"]).otherwise(0.0)
        q = F.greatest(_rounded(share, rounding), F.lit(min_quota).cast("long"))
        q = F.least(q, x["size"], s["k"]) if cap else q
        return F.struct((s["k"] - q).alias("k"), (s["w"] - x["weight"]).alias("w"), F.concat(s["out"], F.array(q)).alias("out"))

    walked = per_worker.select("worker", "items", F.aggregate("items", start, walk).alias("s"))
    quotas = F.col("s")["out"]
    if refill:

        def fill(s, x):
            more = F.when(x["items"]["weight"] > 0, F.greatest(F.least(x["items"]["size"] - x["q"], s["k"]), F.lit(0).cast("long"))).otherwise(F.lit(0).cast("long"))
            return F.struct((s["k"] - more).alias("k"), F.concat(s["out"], F.array(x["q"] + more)).alias("out"))

        zipped = F.arrays_zip(F.col("items").alias("items"), quotas.alias("q"))
        walked = walked.select("worker", "items", F.aggregate(zipped, F.struct(F.col("s")["k"].alias("k"), empty.alias("out")), fill).alias("s"))
    rows = walked.select("worker", F.posexplode(F.arrays_zip(F.col("items").alias("items"), F.col("s")["out"].alias("quota"))).alias("at", "x"))
    return rows.select("worker", F.col("x.items.frag_id").alias("frag_id"), F.col("x.items.size").alias("size"), F.col("x.items.norm").alias("norm"), (F.col("at") + 1).alias("priority"), F.col("x.quota").alias("quota"))


def proportional(norms: DataFrame, k: int) -> DataFrame:
    """The closed form without rounding and caps: taking a share of both
    remainders keeps their ratio, so every share is k * norm / total."""
    total = F.sum("norm").over(Window.partitionBy("worker"))
    return norms.select("worker", "frag_id", "size", "norm", F.when(total > 0, F.lit(k) * F.col("norm") / total).otherwise(0.0).alias("share"))
