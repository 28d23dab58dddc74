"""Costs, densities, errors and accuracies, as DataFrames.

Costs are model costs in nats: they depend on worker counts, not on cores.
Undefined ratios (a cost of zero, k not above n) are null.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from gradsift.operators import pack

# -- density -----------------------------------------------------------------


def density_of(k: int, n_g: int) -> tuple[float, float]:
    """Set density and compression ratio."""
    return k / n_g, n_g / k


def actual_density(picks: DataFrame, n_g: int) -> DataFrame:
    return picks.agg(F.count_distinct("param_idx").alias("selected")).select("selected", (F.col("selected") / F.lit(n_g)).alias("density"))


def build_up(picks: DataFrame, k: int) -> DataFrame:
    """Union size in units of k: 1 without build-up, n at worst."""
    return picks.agg(F.count_distinct("param_idx").alias("selected")).select("selected", (F.col("selected") / F.lit(k)).alias("build_up"))


def overlap(picks: DataFrame) -> DataFrame:
    """How many indices were picked by exactly so many workers."""
    by_index = picks.groupBy("param_idx").agg(F.count_distinct("worker").alias("workers"))
    return by_index.groupBy("workers").agg(F.count("*").alias("indices"))


def jaccard(picks: DataFrame) -> DataFrame:
    """Overlap of the picks of every two workers, from the pairs of workers
    that an index has; an index has few."""
    size = picks.groupBy("worker").agg(F.count_distinct("param_idx").alias("size"))
    who = picks.groupBy("param_idx").agg(F.array_sort(F.collect_set("worker")).alias("w")).where(F.size("w") > 1)
    pairs = who.select(F.explode("w").alias("a"), "w").select("a", F.explode(F.filter("w", lambda b: b > F.col("a"))).alias("b"))
    both = pairs.groupBy("a", "b").agg(F.count("*").alias("both"))
    grid = size.select(F.col("worker").alias("a"), F.col("size").alias("sa")).join(size.select(F.col("worker").alias("b"), F.col("size").alias("sb")), F.col("a") < F.col("b"))
    n = F.coalesce("both", F.lit(0))
    return grid.join(both, ["a", "b"], "left").select("a", "b", n.alias("both"), (n / (F.col("sa") + F.col("sb") - n)).alias("jaccard"))


def density_summary(per_iteration: DataFrame) -> DataFrame:
    return per_iteration.agg(F.avg("density").alias("mean"), F.stddev("density").alias("sd"), F.min("density").alias("least"), F.max("density").alias("most"))


# -- error -------------------------------------------------------------------


def local_error(error: DataFrame, n_workers: int) -> DataFrame:
    """L2 norm of every worker's error memory; an absent worker's is 0."""
    v = F.col("v").cast("double")
    found = error.groupBy("worker").agg(F.sqrt(F.sum(v * v)).alias("norm"))
    every = error.sparkSession.range(n_workers).select(F.col("id").cast("int").alias("worker"))
    return every.join(F.broadcast(found), "worker", "left").select("worker", F.coalesce("norm", F.lit(0.0)).alias("norm"))


def mean_error(error: DataFrame, n_workers: int) -> DataFrame:
    return local_error(error, n_workers).agg((F.sum("norm") / F.lit(n_workers)).alias("error"))


# -- selection cost ----------------------------------------------------------


def global_cost(k: int, n_g: int) -> float:
    return n_g * math.log(k)


def worker_costs(quotas: DataFrame, owner: DataFrame, n_workers: int, cost_model: str = "log") -> DataFrame:
    """Cost, picks and fragments of every worker, by its own quotas."""
    own = pack.fragment_costs(quotas, cost_model).join(F.broadcast(owner), ["worker", "frag_id"])
    found = own.groupBy("worker").agg(F.sum("cost").alias("cost"), F.sum("quota").alias("picks"), F.count("*").alias("fragments"))
    every = quotas.sparkSession.range(n_workers).select(F.col("id").cast("int").alias("worker"))
    zero = lambda c: F.coalesce(c, F.lit(0)).alias(c)
    return every.join(F.broadcast(found), "worker", "left").select("worker", F.coalesce("cost", F.lit(0.0)).alias("cost"), zero("picks"), zero("fragments"))


def selection_cost(costs: DataFrame) -> DataFrame:
    """The slowest worker's cost, and the most that one worker sends."""
    return costs.agg(F.max("cost").alias("cost"), F.max("picks").alias("kappa"), F.sum("picks").alias("picks"))


def trivial_cost(n: int, k: int, n_g: int) -> float | None:
    return n_g / n * math.log(k / n) if k > n else None


def trivial_speedup(n: int, k: int) -> float | None:
    if k == 1 or k <= n:
        return None
    return n * math.log(k) / math.log(k / n)


def trivial_grid(spark: SparkSession, k: int, n_g: int, workers: list[int]) -> DataFrame:
    n = F.col("n")
    cost = F.when(F.lit(k) > n, F.lit(n_g) / n * F.log(F.lit(float(k)) / n))
    fast = F.try_divide(F.lit(n_g) * F.log(F.lit(float(k))), cost)
    rows = spark.createDataFrame([(w,) for w in workers], "n int")
    return rows.select("n", cost.alias("cost"), fast.alias("speedup"), (fast / n).alias("per_worker"))


def bound_report(f: Column, f_trivial: Column, n: Column) -> list[Column]:
    """Does the measured speed-up exceed the trivial one, and that one n?"""
    return [(f >= f_trivial).alias("above_trivial"), (f_trivial >= n).alias("trivial_above_n"), (f_trivial / n).alias("trivial_per_worker")]


def payload_bytes(bins: DataFrame) -> DataFrame:
    """Four bytes for each fragment of the leader's broadcast."""
    return bins.agg((F.count("*") * 4).alias("bytes"))


def comm_cost(n: int, kappa: float, alpha: float, beta: float) -> float:
    """Modelled time of the exchange: latency term plus value term."""
    return math.log(n) * alpha + 2 * (n - 1) * kappa * beta


def balance(costs: DataFrame) -> DataFrame:
    return costs.agg(F.try_divide(F.max("cost"), F.avg("cost")).alias("cost_ratio"), F.try_divide(F.max("picks"), F.avg("picks")).alias("picks_ratio"), F.min("fragments").alias("least_fragments"), F.max("fragments").alias("most_fragments"))


def scanned(acc: DataFrame, owner: DataFrame | None = None) -> DataFrame:
    """Entries that every worker's selection reads."""
    rows = acc if owner is None else acc.join(F.broadcast(owner), ["worker", "frag_id"], "left_semi")
    return rows.groupBy("worker").agg(F.count("*").alias("scanned"))


# -- fidelity ----------------------------------------------------------------


def recall(picks: DataFrame, reference: DataFrame) -> DataFrame:
    """Share of the reference's indices picked, and of its L1 and L2 mass."""
    got = reference.join(picks.select("param_idx").distinct().withColumn("hit", F.lit(1)), "param_idx", "left")
    v, hit = F.abs("v").cast("double"), F.coalesce("hit", F.lit(0))
    return got.agg(F.avg(hit.cast("double")).alias("recall"), F.try_divide(F.sum(v * hit), F.sum(v)).alias("l1"), F.try_divide(F.sum(v * v * hit), F.sum(v * v)).alias("l2"))


def fragment_density(quotas: DataFrame) -> DataFrame:
    return quotas.select("worker", "frag_id", "size", "quota", (F.col("quota") / F.col("size")).alias("density"))


def quota_dispersion(quotas: DataFrame) -> DataFrame:
    """How much a fragment's quota differs between workers."""
    return quotas.groupBy("frag_id").agg(F.min("quota").alias("least"), F.max("quota").alias("most"), F.stddev_pop("quota").alias("sd"))


def off_k(costs: DataFrame, k: int) -> DataFrame:
    """What all workers pick together, and its distance from k in shares of
    k; costs as of worker_costs."""
    return costs.agg(F.sum("picks").alias("picks")).select("picks", (F.abs(F.col("picks") - F.lit(k)) / F.lit(k)).alias("off"))


def layer_share(picks: DataFrame, fragments: DataFrame) -> DataFrame:
    """Share of all picks that falls on each layer; picks with iteration."""
    by = picks.join(F.broadcast(fragments.select("frag_id", "layer_id")), "frag_id").groupBy("iteration", "layer_id").agg(F.count("*").alias("picks"))
    return by.withColumn("share", F.col("picks") / F.sum("picks").over(Window.partitionBy("iteration")))


def staleness(picks: DataFrame, n_g: int, now: int) -> DataFrame:
    """Iterations since an index was last picked, and indices never picked."""
    last = picks.groupBy("param_idx").agg(F.max("iteration").alias("last"))
    return last.agg(F.avg(F.lit(now) - F.col("last")).alias("mean"), F.max(F.lit(now) - F.col("last")).alias("most"), (F.lit(n_g) - F.count("*")).alias("never"))


# -- time --------------------------------------------------------------------


def time_breakdown(timings: DataFrame) -> DataFrame:
    """Mean time by phase: slowest worker of an iteration, mean over
    iterations, mean over seeds."""
    slowest = timings.groupBy("seed", "iteration", "phase").agg(F.max("ms").alias("ms"))
    return slowest.groupBy("seed", "phase").agg(F.avg("ms").alias("ms")).groupBy("phase").agg(F.avg("ms").alias("ms"))


def overhead_share(timings: DataFrame, phase: str = "partition") -> DataFrame:
    by = time_breakdown(timings)
    return by.agg(F.try_divide(F.sum(F.when(F.col("phase") == phase, F.col("ms")).otherwise(0.0)), F.sum("ms")).alias("share"))


def wall_speedup(by_n: DataFrame) -> DataFrame:
    """(n, ms) against the row of n = 1."""
    one = by_n.where("n = 1").select(F.col("ms").alias("one"))
    return by_n.join(F.broadcast(one), how="cross").select("n", "ms", (F.col("one") / F.col("ms")).alias("speedup"))


# -- accuracy ----------------------------------------------------------------


def accuracy(predictions: DataFrame) -> DataFrame:
    return predictions.agg(F.avg((F.col("prediction") == F.col("label")).cast("double")).alias("accuracy"))


def perplexity(nll: DataFrame) -> DataFrame:
    """exp of the mean negative log likelihood of a symbol."""
    return nll.agg(F.exp(F.sum("nll") / F.sum("n")).alias("perplexity"))


def hit_rate(scores: DataFrame, top: int = 10) -> DataFrame:
    """Share of users whose held-out item is among their top candidates."""
    order = Window.partitionBy("user").orderBy(F.desc("score"), "item")
    ranked = scores.withColumn("rank", F.row_number().over(order)).where("held_out")
    return ranked.agg(F.avg((F.col("rank") <= top).cast("double")).alias("hit_rate"))


def best_so_far(metric: DataFrame) -> DataFrame:
    w = Window.partitionBy("run").orderBy("epoch").rowsBetween(Window.unboundedPreceding, 0)
    return metric.withColumn("best", F.max("value").over(w))


def epochs_to(metric: DataFrame, target: float, within: float, larger_is_better: bool = True) -> DataFrame:
    """First epoch of each run within `within` of the target."""
    ok = F.col("value") >= target - within if larger_is_better else F.col("value") <= target + within
    return metric.groupBy("run").agg(F.min(F.when(ok, F.col("epoch"))).alias("epoch"))


def relative_to_dense(metric: DataFrame) -> DataFrame:
    """Every run's value beside the dense run's at the same epoch."""
    dense = metric.where("run = 'dense'").select("epoch", F.col("value").alias("dense"))
    return metric.join(F.broadcast(dense), "epoch", "left").withColumn("gap", F.col("value") - F.col("dense"))
