"""Driver queries of the engine, most with an oracle in plans.oracles."""

from __future__ import annotations

import math
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import replace
from functools import cached_property, reduce

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from gradsift import checks
from gradsift.config import RunConfig
from gradsift.operators import exchange, feedback, fragment, pack, quota, select
from gradsift.operators.sparsifiers import SPARSIFIERS, Fragmented, Model
from gradsift.plans import measures, train
from gradsift.sources import commit, load
from gradsift.workloads.additive import Additive

N = 4
DENSITY = 0.1
SWEEP = (1, 2, 4, 8, 16, 32)
RATE = 2.0**-14

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}


def query(f: Query) -> Query:
    QUERIES[f.__name__] = f
    return f


class Additive0:
    """The additive workload at its start model, for one number of workers.
    What several operators of a query read is written once."""

    def __init__(self, spark: SparkSession, sf_dir: str, n: int = N, density: float = DENSITY, sweep: Sweep | None = None, **options):
        self.spark, self.cfg, self.sweep = spark, RunConfig(n_workers=n, density=density, **options), sweep
        self.workload = replace(sweep.workload, n_workers=n) if sweep else Additive.load(spark, sf_dir, n)
        self.model = Model.of(self.workload.manifest(spark), self.cfg)
        self.k = self.cfg.resolve_k(self.model.n_g)

    @property
    def grads(self) -> DataFrame:
        return self.sweep.gradients(self.cfg.n_workers) if self.sweep else self.workload.first_gradients()

    @cached_property
    def acc(self) -> DataFrame:
        return commit(self.model.tag(self.grads), "acc")

    @property
    def norms(self) -> DataFrame:
        return quota.fragment_norms(self.acc, self.model.fragments, self.cfg.n_workers)

    def quotas(self, **options) -> DataFrame:
        return quota.assign(self.norms, self.k, **options)

    def leader(self, quotas: DataFrame, t: int = 0) -> DataFrame:
        return quotas.where(F.col("worker") == self.cfg.leader_of(t))


class Sweep:
    """Gradients of the largest number of workers, written once. Every number
    of the sweep divides it, so a worker's gradient is a sum of some of them."""

    def __init__(self, spark: SparkSession, sf_dir: str):
        self.workload = Additive.load(spark, sf_dir, max(SWEEP))
        self.finest = commit(self.workload.first_gradients(), "finest")

    def gradients(self, n: int) -> DataFrame:
        return self.finest.groupBy(F.pmod("worker", F.lit(n)).cast("int").alias("worker"), "param_idx").agg(F.sum("v").alias("v"))


@query
def manifest_additive(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Additive.load(spark, sf_dir, N).manifest(spark)


@query
def fragments_n4(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Additive0(spark, sf_dir).model.fragments


@query
def fragments_n16(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Additive0(spark, sf_dir, 16).model.fragments


@query
def worker_gradients(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Additive0(spark, sf_dir).grads


@query
def fragment_norms(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Additive0(spark, sf_dir).norms.withColumn("norm", F.round("norm", 6))


@query
def fragment_priority(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quota.prioritise(Additive0(spark, sf_dir).norms).select("worker", "frag_id", "priority")


def _quotas(spark: SparkSession, sf_dir: str, **options) -> DataFrame:
    return Additive0(spark, sf_dir).quotas(**options).select("worker", "frag_id", "size", "priority", "quota")


@query
def quota_sequential(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _quotas(spark, sf_dir)


@query
def quota_uncapped(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _quotas(spark, sf_dir, cap=False)


@query
def quota_size(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _quotas(spark, sf_dir, policy="size")


@query
def quota_energy(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _quotas(spark, sf_dir, policy="energy")


@query
def quota_closed_form(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Additive0(spark, sf_dir)
    return quota.proportional(s.norms, s.k).select("worker", "frag_id", F.round("share", 6).alias("share"))


@query
def fragment_costs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack.fragment_costs(Additive0(spark, sf_dir).quotas()).select("worker", "frag_id", "quota", F.round("cost", 4).alias("cost"))


def _bins(spark: SparkSession, sf_dir: str, policy: str) -> DataFrame:
    s = Additive0(spark, sf_dir)
    return pack.pack(pack.fragment_costs(s.leader(s.quotas())), N, policy)


@query
def bins_greedy(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _bins(spark, sf_dir, "greedy").select("bin", "frag_id", "pack_order")


@query
def bins_round_robin(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _bins(spark, sf_dir, "round_robin").select("bin", "frag_id")


@query
def bins_contiguous(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _bins(spark, sf_dir, "contiguous").select("bin", "frag_id")


@query
def bins_by_size(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _bins(spark, sf_dir, "size").select("bin", "frag_id", "pack_order")


@query
def bins_rotated_t3(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack.rotate(_bins(spark, sf_dir, "greedy"), 3, N)


def _picks(spark: SparkSession, sf_dir: str, name: str, n: int = N, density: float = DENSITY, t: int = 0) -> DataFrame:
    s = Additive0(spark, sf_dir, n, density)
    return SPARSIFIERS[name](s.cfg).select(s.acc, s.model, t).picks.select("worker", "param_idx", "v", "rank")


@query
def picks_fragmented(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _picks(spark, sf_dir, "fragmented")


@query
def picks_global(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _picks(spark, sf_dir, "global_topk")


@query
def picks_cyclic(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _picks(spark, sf_dir, "cyclic_topk", t=1)


@query
def picks_slices(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _picks(spark, sf_dir, "equal_slices")


@query
def picks_threshold(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Additive0(spark, sf_dir)
    return SPARSIFIERS["threshold"](s.cfg, 100.0).select(s.acc, s.model, 0).picks.select("worker", "param_idx", "v")


def _kernel(kernel: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        s = Additive0(spark, sf_dir, kernel=kernel)
        return Fragmented(s.cfg).select(s.acc, s.model, 0).picks.select("worker", "param_idx", "v", "rank")

    return run


for _name in ("two_phase", "threshold", "arrow"):
    QUERIES[f"picks_fragmented_{_name}"] = _kernel(_name)


@query
def picks_leader_quotas(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The leader's quotas on all workers: the union is exactly their sum."""
    s = Additive0(spark, sf_dir, quota_scope="leader")
    picks = Fragmented(s.cfg).select(s.acc, s.model, 0).picks
    return picks.groupBy("frag_id").agg(F.count("*").alias("picks"))


def _after(spark: SparkSession, sf_dir: str):
    s = Additive0(spark, sf_dir)
    acc = s.acc
    indices = exchange.union_indices(Fragmented(s.cfg).select(acc, s.model, 0).picks, disjoint=True)
    return s, acc, indices


@query
def dense_mean(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Additive0(spark, sf_dir)
    return exchange.average(s.grads, None, N)


@query
def exchange_mean(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, acc, indices = _after(spark, sf_dir)
    return exchange.average(acc, indices, N, 2 * s.k)


@query
def params_after_1(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, acc, indices = _after(spark, sf_dir)
    return exchange.apply_update(s.workload.init_params(spark), exchange.average(acc, indices, N, 2 * s.k), RATE, "update")


@query
def residual_after_1(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, acc, indices = _after(spark, sf_dir)
    return feedback.residual(acc, indices)


@query
def mean_error_after_1(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, acc, indices = _after(spark, sf_dir)
    return measures.mean_error(feedback.residual(acc, indices), N).select(F.round("error", 6).alias("error"))


@query
def local_error_after_1(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, acc, indices = _after(spark, sf_dir)
    return measures.local_error(feedback.residual(acc, indices), N).select("worker", F.round("norm", 6).alias("norm"))


def _by_n(one: Callable[[int], DataFrame], sweep: tuple[int, ...] = SWEEP) -> DataFrame:
    """The rows of every n. What each n writes on the way is small, so the
    plans are driven side by side."""
    run = inheritable_thread_target(SparkSession.active())(one)
    with ThreadPoolExecutor(len(sweep)) as pool:
        found = list(pool.map(run, sweep))
    return reduce(DataFrame.unionByName, [rows.select(F.lit(n).alias("n"), "*") for n, rows in zip(sweep, found, strict=True)])


@query
def buildup_by_n(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Union of the global top-k in units of k, at density 0.01."""

    sweep = Sweep(spark, sf_dir)

    def one(n: int) -> DataFrame:
        s = Additive0(spark, sf_dir, n, 0.01, sweep)
        picks = SPARSIFIERS["global_topk"](s.cfg).select(s.grads, s.model, 0).picks
        return measures.build_up(picks, s.k).select("selected", F.round("build_up", 6).alias("build_up"))

    return _by_n(one)


@query
def density_by_sparsifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Selected indices and actual density of every selector, 16 workers."""
    out, s = None, Additive0(spark, sf_dir, 16, 0.01)
    for name in ("global_topk", "cyclic_topk", "fragmented", "equal_slices"):
        rows = measures.actual_density(SPARSIFIERS[name](s.cfg).select(s.acc, s.model, 0).picks, s.model.n_g)
        rows = rows.select(F.lit(name).alias("sparsifier"), "selected", F.round("density", 9).alias("density"))
        out = rows if out is None else out.unionByName(rows)
    return out


@query
def overlap_hist(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.overlap(_picks(spark, sf_dir, "global_topk"))


@query
def jaccard_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = measures.jaccard(_picks(spark, sf_dir, "global_topk"))
    return got.select("a", "b", "both", F.round("jaccard", 6).alias("jaccard"))


def _costs(spark: SparkSession, sf_dir: str, n: int, sweep: Sweep, policy: str = "greedy") -> tuple[Additive0, DataFrame, DataFrame]:
    s = Additive0(spark, sf_dir, n, sweep=sweep, pack_policy=policy)
    quotas, bins, owner = Fragmented(s.cfg).plan(s.acc, s.model, 0)
    return s, measures.worker_costs(quotas, owner, n), bins


@query
def cost_report_by_n(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Model cost, speed-ups and the most that one worker sends, by n."""
    sweep = Sweep(spark, sf_dir)

    def one(n: int) -> DataFrame:
        s, costs, _ = _costs(spark, sf_dir, n, sweep)
        whole = measures.global_cost(s.k, s.model.n_g)
        trivial = measures.trivial_speedup(n, s.k)
        got = measures.selection_cost(costs)
        f = F.when(F.col("cost") > 0, F.lit(whole) / F.col("cost"))
        return got.select(F.round("cost", 3).alias("cost"), F.round(f, 4).alias("f"), F.round(F.lit(trivial).cast("double"), 6).alias("f_trivial"), F.col("kappa").cast("long").alias("kappa"), F.col("picks").cast("long").alias("quota_sum"))

    return _by_n(one)


@query
def bound_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = cost_report_by_n(spark, sf_dir)
    return got.select("n", *measures.bound_report(F.col("f"), F.col("f_trivial"), F.col("n"))).withColumn("trivial_per_worker", F.round("trivial_per_worker", 6))


@query
def trivial_speedup_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    n_g = Additive.load(spark, sf_dir, N).n_g
    got = measures.trivial_grid(spark, max(1, math.floor(DENSITY * n_g + 0.5)), n_g, list(SWEEP))
    return got.select("n", *[F.round(c, 6).alias(c) for c in ("cost", "speedup", "per_worker")])


@query
def comm_cost_by_n(spark: SparkSession, sf_dir: str, alpha: float = 1e-5, beta: float = 1e-9) -> DataFrame:
    """Modelled exchange time of the global and of the fragmented scheme."""
    sweep = Sweep(spark, sf_dir)

    def one(n: int) -> DataFrame:
        s, costs, _ = _costs(spark, sf_dir, n, sweep)
        time = lambda kappa: F.round(F.lit(math.log(n) * alpha) + F.lit(2 * (n - 1) * beta) * kappa, 12)
        return measures.selection_cost(costs).select(F.lit(s.k).cast("long").alias("kappa_global"), F.col("kappa").cast("long").alias("kappa"), time(F.lit(s.k)).alias("seconds_global"), time(F.col("kappa")).alias("seconds"))

    return _by_n(one)


@query
def payload_by_n(spark: SparkSession, sf_dir: str) -> DataFrame:
    sweep = Sweep(spark, sf_dir)
    return _by_n(lambda n: measures.payload_bytes(_costs(spark, sf_dir, n, sweep)[2]))


@query
def balance_by_policy(spark: SparkSession, sf_dir: str) -> DataFrame:
    out, sweep = None, Sweep(spark, sf_dir)
    for policy in ("greedy", "round_robin", "contiguous", "size"):
        b = measures.balance(_costs(spark, sf_dir, N, sweep, policy)[1])
        b = b.select(F.lit(policy).alias("policy"), *[F.round(c, 4).alias(c) for c in ("cost_ratio", "picks_ratio")], "least_fragments", "most_fragments")
        out = b if out is None else out.unionByName(b)
    return out


@query
def comm_cost_cyclic_by_n(spark: SparkSession, sf_dir: str, alpha: float = 1e-5, beta: float = 1e-9) -> DataFrame:
    """Modelled exchange time of the cyclic leader: its k indices are all that
    is sent, as with global top-k, and the values at them."""
    k = max(1, math.floor(DENSITY * Additive.load(spark, sf_dir, N).n_g + 0.5))
    rows = [(n, k, round(measures.comm_cost(n, k, alpha, beta), 12)) for n in SWEEP]
    return spark.createDataFrame(rows, "n int, kappa long, seconds double")


@query
def set_density(spark: SparkSession, sf_dir: str) -> DataFrame:
    """k, set density and compression ratio."""
    n_g = Additive.load(spark, sf_dir, N).n_g
    k = max(1, math.floor(DENSITY * n_g + 0.5))
    density, ratio = measures.density_of(k, n_g)
    return spark.createDataFrame([(k, round(density, 9), round(ratio, 6))], "k long, density double, ratio double")


@query
def quota_off_k_by_n(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How far the quotas of all owners together are off k, in shares of k."""
    sweep = Sweep(spark, sf_dir)

    def one(n: int) -> DataFrame:
        s, costs, _ = _costs(spark, sf_dir, n, sweep)
        return measures.off_k(costs, s.k).select(F.col("picks").cast("long").alias("picks"), F.round("off", 6).alias("off"))

    return _by_n(one)


@query
def fragments_by_stages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One fragment, and one a layer: the stages that are left out."""
    manifest = Additive.load(spark, sf_dir, N).manifest(spark)
    whole, layers = (fragment.split_oversized(manifest, N, stages) for stages in (0, 1))
    return whole.select(F.lit(0).alias("stages"), "*").unionByName(layers.select(F.lit(1).alias("stages"), "*"))


@query
def picks_repeated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Indices that two workers picked: none in the fragmented scheme, many
    in global top-k."""
    s = Additive0(spark, sf_dir)
    rows = [(name, checks.repeated_picks(SPARSIFIERS[name](s.cfg).select(s.acc, s.model, 0).picks)) for name in ("fragmented", "global_topk")]
    return spark.createDataFrame(rows, "sparsifier string, repeated long")


@query
def random_k_shape(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Number, distinct number and range of indices drawn at random, and
    whether two iterations draw unlike ones."""
    s = Additive0(spark, sf_dir)
    first, second = (SPARSIFIERS["random_k"](s.cfg).select(s.acc, s.model, t).picks.select("param_idx") for t in (0, 1))
    both = first.intersect(second).agg((F.count("*") < s.k).alias("unlike"))
    got = first.agg(F.count("*").alias("drawn"), F.count_distinct("param_idx").alias("indices"), ((F.min("param_idx") >= 0) & (F.max("param_idx") < s.model.n_g)).alias("inside"))
    return got.join(F.broadcast(both), how="cross")


@query
def idle_by_n(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share of the workers with gradients that wait while the leader selects."""
    finest = Additive.load(spark, sf_dir, max(SWEEP)).rows.select("worker").distinct()
    every = finest.withColumn("n", F.explode(F.array(*[F.lit(n) for n in SWEEP])))
    slots = every.select("n", F.pmod("worker", "n").cast("int").alias("worker")).distinct()
    return slots.groupBy("n").agg(F.round(F.avg((F.col("worker") != 0).cast("double")), 6).alias("idle"))


@query
def scanned_by_worker(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Additive0(spark, sf_dir)
    _, _, owner = Fragmented(s.cfg).plan(s.acc, s.model, 0)
    return measures.scanned(s.acc, owner)


@query
def recall_vs_global(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Additive0(spark, sf_dir)
    mine = Fragmented(s.cfg).select(s.acc, s.model, 0).picks
    mean = exchange.average(s.grads, None, N).select(F.lit(0).alias("worker"), "param_idx", F.col("mean").alias("v"))
    best = mean.orderBy(F.desc(F.abs("v")), "param_idx").limit(s.k)
    got = measures.recall(mine, best)
    return got.select(*[F.round(c, 6).alias(c) for c in got.columns])


@query
def fragment_density(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = measures.fragment_density(Additive0(spark, sf_dir).quotas())
    return got.withColumn("density", F.round("density", 9))


@query
def quota_dispersion(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.quota_dispersion(Additive0(spark, sf_dir).quotas()).withColumn("sd", F.round("sd", 6))


def train_metrics(spark: SparkSession, sf_dir: str, name: str, iterations: int = 3, **options) -> DataFrame:
    cfg = RunConfig(n_workers=N, density=DENSITY, lr=RATE, **options)
    result = train.run(Additive.load(spark, sf_dir, N), name, cfg, spark, iterations)
    got = result.metrics_df(spark).groupBy("iteration").pivot("metric", ["selected", "error", "rmse"]).agg(F.first("value"))
    return got.select("iteration", F.col("selected").cast("long").alias("selected"), F.round("error", 6).alias("error"), F.round("rmse", 6).alias("rmse"))


for _name in ("fragmented", "global_topk", "cyclic_topk", "dense"):
    QUERIES[f"train3_{_name}"] = lambda spark, sf_dir, name=_name: train_metrics(spark, sf_dir, name)


@query
def train3_no_feedback(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What is not sent is lost."""
    return train_metrics(spark, sf_dir, "fragmented", error_feedback=False)


@query
def train3_decay(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rate falls to a quarter before the third iteration."""
    return train_metrics(spark, sf_dir, "fragmented", decay_steps=(2,), gamma=0.25)


@query
def metrics_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Picks by worker and layer, with all totals."""
    s = Additive0(spark, sf_dir)
    picks = Fragmented(s.cfg).select(s.acc, s.model, 0).picks
    named = picks.join(F.broadcast(s.model.fragments.select("frag_id", "layer_id")), "frag_id")
    return named.cube("worker", "layer_id").agg(F.count("*").alias("picks"), F.sum(F.abs("v")).alias("mass"))


def _led_in_turn(spark: SparkSession, sf_dir: str) -> tuple[Additive0, DataFrame]:
    """Picks of N iterations of the cyclic leader over one accumulator: in
    iteration t worker t picks, so the iteration is the worker."""
    s = Additive0(spark, sf_dir)
    picks = SPARSIFIERS["global_topk"](s.cfg).select(s.acc, s.model, 0).picks
    return s, picks.withColumn("iteration", F.col("worker"))


@query
def staleness_cyclic(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, picks = _led_in_turn(spark, sf_dir)
    got = measures.staleness(picks, s.model.n_g, N)
    return got.select(F.round("mean", 6).alias("mean"), F.col("most").cast("long").alias("most"), "never")


@query
def layer_share_cyclic(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, picks = _led_in_turn(spark, sf_dir)
    got = measures.layer_share(fragment.tag(picks, s.model.fragments), s.model.fragments)
    return got.withColumn("share", F.round("share", 6))


@query
def density_summary_rotation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Actual density of the fragmented scheme while leader and bins rotate."""
    s = Additive0(spark, sf_dir)
    each = None
    for t in range(N):
        rows = measures.actual_density(Fragmented(s.cfg).select(s.acc, s.model, t).picks, s.model.n_g)
        each = rows if each is None else each.unionByName(rows)
    got = measures.density_summary(each)
    return got.select(*[F.round(c, 9).alias(c) for c in got.columns])


@query
def hr_at_10_popularity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gradsift.workloads.base_rates import popularity_hits

    return popularity_hits(spark, sf_dir)


@query
def bigram_perplexity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gradsift.workloads.base_rates import bigram_base

    return bigram_base(spark, sf_dir)


@query
def lang_majority_accuracy(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents").select("doc_id", "lang")
    most = docs.where("doc_id % 5 <> 4").groupBy("lang").count().orderBy(F.desc("count"), "lang").limit(1).select(F.col("lang").alias("prediction"))
    held = docs.where("doc_id % 5 = 4").join(F.broadcast(most), how="cross").select("prediction", F.col("lang").alias("label"))
    return measures.accuracy(held).select(F.round("accuracy", 6).alias("accuracy"))


@query
def events_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gradsift.streaming.windows import tumbling

    return tumbling(load(spark, sf_dir, "events"))


@query
def events_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gradsift.streaming.windows import sliding

    return sliding(load(spark, sf_dir, "events"))


@query
def events_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gradsift.streaming.windows import sessions

    return sessions(load(spark, sf_dir, "events"))


# -- the worked example --------------------------------------------------------

EXAMPLE = [8, 6, 0, 0, 0, 0, 3, 4, 0, 0, 0, 0, 2, -1, 2, 0, 0, 0, 12, -5]
EXAMPLE_LAYERS = [("a", 12), ("b", 3), ("c", 3), ("d", 2)]


def example(spark: SparkSession, cap: bool = True) -> tuple[RunConfig, Model, DataFrame]:
    cfg = RunConfig(n_workers=2, k=8, cap=cap)
    model = Model.of(fragment.build_manifest(spark, EXAMPLE_LAYERS), cfg)
    rows = [(w, i, float(v)) for w in range(2) for i, v in enumerate(EXAMPLE)]
    return cfg, model, fragment.tag(spark.createDataFrame(rows, "worker int, param_idx long, v double"), model.fragments)


@query
def worked_example_quotas(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The example's setting, two workers and eight picks, on the additive
    workload: quotas of the first worker with and without the cap."""
    out, s = None, Additive0(spark, sf_dir, 2, None, k=8)
    for cap in (True, False):
        rows = s.quotas(cap=cap).where("worker = 0")
        rows = rows.select(F.lit(cap).alias("cap"), "frag_id", F.round("norm", 6).alias("norm"), "priority", "quota")
        out = rows if out is None else out.unionByName(rows)
    return out


@query
def worked_example_picks(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Additive0(spark, sf_dir, 2, None, k=8)
    return Fragmented(s.cfg).select(s.acc, s.model, 3).picks.select("worker", "param_idx")


@query
def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row for each worker: fragments, picks, cost and density of one
    fragmented selection."""
    s = Additive0(spark, sf_dir)
    quotas, bins, owner = Fragmented(s.cfg).plan(s.acc, s.model, 0)
    picks = select.layerwise(s.acc, quotas, owner, most=s.k)
    got = picks.groupBy("worker").agg(F.count("*").alias("picked"))
    costs = measures.worker_costs(quotas, owner, N)
    share = F.col("picked") / F.lit(s.model.n_g)
    return costs.join(F.broadcast(got), "worker", "left").select("worker", F.col("fragments").cast("long").alias("fragments"), F.coalesce("picked", F.lit(0)).cast("long").alias("picked"), F.round("cost", 3).alias("cost"), F.round(F.coalesce(share, F.lit(0.0)), 9).alias("density"))


@query
def moving_error(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Error change and moving mean over a three-iteration run."""
    got = train_metrics(spark, sf_dir, "fragmented")
    w = Window.orderBy("iteration")
    return got.select("iteration", F.round(F.col("error") - F.lag("error").over(w), 5).alias("change"), F.round(F.avg("error").over(w.rowsBetween(-1, 0)), 5).alias("smoothed"))


# -- training of nets: no SQL -----------------------------------------------------------


def _summed(rows: DataFrame, last: int) -> DataFrame:
    from gradsift.plans import experiments

    got = experiments.summary(rows, last)
    return got.select("run", "sparsifier", "n", "density", "metric", *[F.round(c, 5).alias(c) for c in ("late_mean", "most", "least", "final")])


def _trained(experiment: str, iterations: int, *args) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        from gradsift.plans import experiments

        return _summed(getattr(experiments, experiment)(spark, sf_dir, *args, iterations=iterations), max(1, iterations // 4))

    return run


def experiment_convergence(spark: SparkSession, sf_dir: str, iterations: int = 12) -> DataFrame:
    """When each run on language identification comes near the dense one."""
    from gradsift.plans import experiments

    rows = experiments.compare(spark, sf_dir, "langid", iterations, 2)
    got = experiments.convergence(rows, "accuracy", 0.05)
    return got.select("run", *[F.round(c, 5).alias(c) for c in ("final", "best", "gap")], "reached")


def experiment_decay(spark: SparkSession, sf_dir: str, iterations: int = 12) -> DataFrame:
    """Mean error before and after the rate falls to a tenth."""
    from gradsift.plans import experiments

    got = experiments.before_and_after(experiments.decay(spark, sf_dir, iterations=iterations), 2 * iterations // 3)
    return got.select("run", *[F.round(c, 6).alias(c) for c in ("before", "after")])


def experiment_breakdown(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Milliseconds by phase on the language model, mean of four seeds."""
    from gradsift.plans import experiments

    got = experiments.breakdown(spark, sf_dir, iterations=1)
    return got.select("sparsifier", "phase", F.round("ms", 3).alias("ms"), F.round("partition_share", 5).alias("partition_share"))


def experiment_speedup_by_n(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Wall time of the slowest worker's search by number of workers."""
    from gradsift.plans import experiments

    return experiments.selection_time(spark).select("n", F.round("ms", 4).alias("ms"), F.round("speedup", 3).alias("speedup"))


#: Experiment queries, over whole tables; gradsift.plans.experiments runs them
#: at any length.
TRAINED: dict[str, Query] = {
    "experiment_langid": _trained("compare", 6, "langid"),
    "experiment_charlm": _trained("compare", 6, "charlm"),
    "experiment_recommend": _trained("compare", 5, "recommend"),
    "experiment_vectors": _trained("compare", 4, "vectors"),
    "experiment_equal_density": _trained("equal_density", 4),
    "experiment_density_sweep": _trained("density_sweep", 5, "charlm"),
    "experiment_scale_sweep": _trained("scale_sweep", 4),
    "experiment_buildup": _trained("buildup", 3),
    "experiment_ablations": _trained("ablate", 4, "langid"),
    "experiment_convergence": experiment_convergence,
    "experiment_decay": experiment_decay,
    "experiment_breakdown": experiment_breakdown,
    "experiment_speedup_by_n": experiment_speedup_by_n,
}
QUERIES |= TRAINED
