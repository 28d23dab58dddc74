"""Who searches what: fragments are packed into bins by predicted cost."""

from __future__ import annotations

import heapq

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: Costs are compared and added in millionths, as integers, so that sums and
#: ties do not depend on the last bit of a logarithm.
MICRO = 1_000_000
#: Fragments up to which the fold is used; above, one task with a heap. The
#: number of fragments is the model's, and is known before the data are read.
FOLD_LIMIT = 4096


def fragment_costs(quotas: DataFrame, cost_model: str = "log") -> DataFrame:
    """Add cost, in nats: size times the log of the quota; quotas of 0 and 1
    cost nothing. scan: size * (1 + log2 quota), which also counts the read."""
    q = F.greatest(F.col("quota"), F.lit(1)).cast("double")
    cost = F.col("size") * F.log(q) if cost_model == "log" else F.col("size") * (1 + F.log2(q))
    return quotas.withColumn("cost", F.round(cost, 6))


def greedy(costs: DataFrame, n_workers: int) -> DataFrame:
    """Costliest fragment first, each to the lightest bin, ties to the lowest
    fragment and bin. One sort and one fold over one row."""
    item = F.struct((-F.round(F.col("cost") * MICRO).cast("long")).alias("order"), "frag_id", "cost")
    one = costs.agg(F.array_sort(F.collect_list(item)).alias("items"))
    zeros = F.array_repeat(F.lit(0).cast("long"), n_workers)
    start = F.struct(zeros.alias("loads"), F.expr("cast(array() as array<int>)").alias("out"))

    def put(s, x):
        at = (F.array_position(s["loads"], F.array_min(s["loads"])) - 1).cast("int")
        loads = F.transform(s["loads"], lambda load, i: F.when(i == at, load - x["order"]).otherwise(load))
        return F.struct(loads.alias("loads"), F.concat(s["out"], F.array(at)).alias("out"))

    packed = one.select("items", F.aggregate("items", start, put)["out"].alias("bins"))
    rows = packed.select(F.posexplode(F.arrays_zip("items", "bins")).alias("at", "x"))
    return rows.select(F.col("x.bins").alias("bin"), F.col("x.items.frag_id").alias("frag_id"), F.col("x.items.cost").alias("cost"), F.col("at").cast("int").alias("pack_order"))


def greedy_heap(costs: DataFrame, n_workers: int) -> DataFrame:
    """The same packing for long fragment lists, in one task."""

    def run(part: pd.DataFrame) -> pd.DataFrame:
        micro = (part["cost"] * MICRO).round().astype("int64")
        part = part.assign(micro=micro).sort_values(["micro", "frag_id"], ascending=[False, True])
        heap = [(0, b) for b in range(n_workers)]
        bins = []
        for cost in part["micro"].tolist():
            load, b = heapq.heappop(heap)
            bins.append(b)
            heapq.heappush(heap, (load + cost, b))
        return pd.DataFrame({"bin": bins, "frag_id": part["frag_id"].to_numpy(), "cost": part["cost"].to_numpy(), "pack_order": range(len(bins))})

    return costs.select("frag_id", "cost").groupBy().applyInPandas(run, "bin int, frag_id int, cost double, pack_order int")


def pack(costs: DataFrame, n_workers: int, policy: str = "greedy", fragments: int = 0) -> DataFrame:
    """Bins of the leader's fragments. policy: greedy by cost; size, greedy by
    size; round_robin, equal numbers; contiguous, runs of fragments.
    fragments: their number, by which greedy packing folds or takes a heap."""
    in_turn = greedy_heap if fragments > FOLD_LIMIT else greedy
    if policy == "size":
        by_size = in_turn(costs.select("frag_id", F.col("size").cast("double").alias("cost")), n_workers)
        return by_size.drop("cost").join(costs.select("frag_id", "cost"), "frag_id").select("bin", "frag_id", "cost", "pack_order")
    if policy == "greedy":
        return in_turn(costs, n_workers)
    n = F.count("*").over(Window.partitionBy())
    at = F.row_number().over(Window.orderBy("frag_id")) - 1
    bins = at % n_workers if policy == "round_robin" else F.floor(at * n_workers / n)
    return costs.select(bins.cast("int").alias("bin"), "frag_id", "cost", at.cast("int").alias("pack_order"))


def rotate(bins: DataFrame, t: int, n_workers: int) -> DataFrame:
    """(worker, frag_id): in iteration t worker r takes bin (t + r) mod n."""
    return bins.select(F.pmod(F.col("bin") - F.lit(t % n_workers), F.lit(n_workers)).cast("int").alias("worker"), "frag_id")


def publish(bins: DataFrame) -> DataFrame:
    """The leader's broadcast: four bytes for each fragment."""
    return F.broadcast(bins)
