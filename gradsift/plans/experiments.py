"""The experiments: which settings each compares, and on which set.

Every run is plans.train.run with the DataFrame operators, over whole tables:
gradients by worker where the rows are, everything after them as one plan an
iteration. Runs of an experiment share the written training rows and are
driven side by side, so that the small stages of one fill the gaps of another;
timed runs are driven one by one. `iterations` scales them from a smoke test
to full runs.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pyarrow as pa
from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gradsift.config import RunConfig
from gradsift.operators.fragment import build_manifest
from gradsift.operators.sparsifiers import Fragmented, Model
from gradsift.plans import measures, train
from gradsift.sources import collect_garbage, commit, discard, synthetic_gradients
from gradsift.workloads.nets import Recurrent
from gradsift.workloads.training_sets import SETS, NetWorkload, by_value

WORKERS = 16
#: Set, density, rate and local batch of the three applications and of the
#: shape-only variant.
APPLICATIONS = {
    "langid": (0.01, 0.5, 32),
    "charlm": (0.001, 0.5, 32),
    "recommend": (0.1, 2.0, 4096),
    "vectors": (0.01, 0.5, 8),
}
COMPARED = ("dense", "global_topk", "cyclic_topk", "fragmented")
SWEEP = (1, 2, 4, 8, 16, 32)
#: Runs that are driven side by side.
TOGETHER = 4
#: Dealt copies of a large set that are on disk at a time.
DEALT = 2

METRICS = "run string, sparsifier string, n int, density double, seed int, iteration int, metric string, value double"
Job = tuple[str, str, RunConfig, NetWorkload]


def _cfg(app: str, n: int = WORKERS, density: float | None = None, **options) -> RunConfig:
    d, lr, batch = APPLICATIONS[app]
    return RunConfig(n_workers=n, **({"density": density or d, "lr": lr, "local_batch": batch} | options))


def runs(spark: SparkSession, jobs: list[Job], iterations: int, evaluate_each: int = 0, together: int = TOGETHER) -> tuple[DataFrame, DataFrame]:
    """Metrics and timings of all jobs."""

    def one(job: Job) -> tuple[list[tuple], list[tuple]]:
        label, name, cfg, work = job
        got = train.run(work, name, cfg, spark, iterations, evaluate_each or iterations, label=label, costs=True)
        return [(*m[:4], cfg.seed, *m[4:]) for m in got.metrics], [(label, *t) for t in got.timings]

    with ThreadPoolExecutor(together) as pool:
        done = [f.result() for f in [pool.submit(inheritable_thread_target(spark)(one), job) for job in jobs]]
    metrics, timings = [m for d in done for m in d[0]], [t for d in done for t in d[1]]
    return spark.createDataFrame(metrics, METRICS), spark.createDataFrame(timings, "run string, seed int, iteration int, worker int, phase string, ms double")


def compare(spark: SparkSession, sf_dir: str, app: str, iterations: int = 100, evaluate_each: int = 0, names: tuple[str, ...] = COMPARED, **options) -> DataFrame:
    """Convergence, actual density and error of all sparsifiers, 16 workers."""
    cfg = _cfg(app, **options)
    made = SETS[app](spark, sf_dir)
    work = made.dealt(cfg.n_workers, cfg.local_batch, cfg.seed)
    discard(made.train)
    collect_garbage(spark)
    return runs(spark, [(name, name, cfg, work) for name in names], iterations, evaluate_each)[0]


def equal_density(spark: SparkSession, sf_dir: str, apps: tuple[str, ...] = ("langid", "charlm"), iterations: int = 100) -> DataFrame:
    """The fragmented scheme at ten times the density beside global top-k."""
    jobs: list[Job] = []
    for app in apps:
        cfg = _cfg(app)
        work = SETS[app](spark, sf_dir).dealt(cfg.n_workers, cfg.local_batch)
        jobs += [(f"{app} global_topk", "global_topk", cfg, work), (f"{app} fragmented", "fragmented", cfg, work), (f"{app} fragmented x10", "fragmented", _cfg(app, density=10 * cfg.density), work)]
    return runs(spark, jobs, iterations)[0]


def density_sweep(spark: SparkSession, sf_dir: str, app: str = "charlm", iterations: int = 100, densities: tuple[float, ...] = (0.1, 0.01, 0.001)) -> DataFrame:
    cfg = _cfg(app)
    work = SETS[app](spark, sf_dir).dealt(cfg.n_workers, cfg.local_batch)
    return runs(spark, [(f"d={d}", "fragmented", _cfg(app, density=d), work) for d in densities], iterations)[0]


def scale_sweep(spark: SparkSession, sf_dir: str, iterations: int = 100, name: str = "fragmented", workers: tuple[int, ...] = SWEEP, hidden: int = 96) -> DataFrame:
    """Convergence, cost and build-up of the language model by number of
    workers at density 0.001; the local batch is fixed, and the net is wide
    enough for k to exceed the workers."""
    work, out = SETS["charlm"](spark, sf_dir, hidden), None
    for lo in range(0, len(workers), DEALT):
        jobs = [(f"n={n}", name, cfg, work.dealt(n, cfg.local_batch)) for n in workers[lo : lo + DEALT] for cfg in [_cfg("charlm", n)]]
        rows = runs(spark, jobs, iterations)[0]
        discard(*[dealt.train for *_, dealt in jobs])
        out = rows if out is None else out.unionByName(rows)
    discard(work.train, work.test)
    return out


def buildup(spark: SparkSession, sf_dir: str, iterations: int = 5, workers: tuple[int, ...] = SWEEP) -> DataFrame:
    """Actual density of global top-k by number of workers, density 0.01,
    batches of 256 rows a worker, on language identification."""
    work = SETS["langid"](spark, sf_dir)
    jobs = [(f"n={n}", "global_topk", cfg, work.dealt(n, 256)) for n in workers for cfg in [_cfg("langid", n, local_batch=256)]]
    return runs(spark, jobs, iterations)[0]


def decay(spark: SparkSession, sf_dir: str, app: str = "langid", iterations: int = 60, names: tuple[str, ...] = COMPARED[1:]) -> DataFrame:
    """Runs whose rate falls to a tenth after two thirds of the iterations:
    the error falls with it."""
    cfg = _cfg(app, decay_steps=(2 * iterations // 3,))
    work = SETS[app](spark, sf_dir).dealt(cfg.n_workers, cfg.local_batch)
    return runs(spark, [(name, name, cfg, work) for name in names], iterations)[0]


def before_and_after(rows: DataFrame, at: int) -> DataFrame:
    """Mean error of each run just before the rate falls, and at the end."""
    rows = rows.where("metric = 'error'")
    end = rows.agg(F.max("iteration")).first()[0]
    mean = lambda lo, hi: F.avg(F.when((F.col("iteration") >= lo) & (F.col("iteration") < hi), F.col("value")))
    return rows.groupBy("run").agg(mean(at - max(1, at // 10), at).alias("before"), mean(end + 1 - max(1, (end + 1 - at) // 2), end + 1).alias("after"))


def convergence(rows: DataFrame, metric: str, within: float, larger_is_better: bool = True) -> DataFrame:
    """By run: last and best value, gap to the dense run's last value, and
    the first iteration that came within `within` of it."""
    own = rows.where(F.col("metric") == metric).select("run", F.col("iteration").alias("epoch"), "value")
    last = own.groupBy("run").agg(F.max_by("value", "epoch").alias("final"), (F.max("value") if larger_is_better else F.min("value")).alias("best"))
    target = last.where("run = 'dense'").first()["final"]
    reached = measures.epochs_to(own, target, within, larger_is_better).withColumnRenamed("epoch", "reached")
    gap = measures.relative_to_dense(own).groupBy("run").agg(F.max_by("gap", "epoch").alias("gap"))
    return last.join(reached, "run").join(gap, "run")


def breakdown(spark: SparkSession, sf_dir: str, app: str = "charlm", iterations: int = 5, seeds: int = 4, names: tuple[str, ...] = COMPARED[1:]) -> DataFrame:
    """(sparsifier, phase, ms): forward and backward pass of the slowest
    worker, and the plans of partition, selection, communication and residual;
    mean over iterations, then over seeds. accumulate is the plan that runs
    the passes and adds the error."""
    base = SETS[app](spark, sf_dir)
    found: list[tuple] = []
    for seed in range(seeds):
        cfg = _cfg(app, seed=seed)
        work = base.dealt(cfg.n_workers, cfg.local_batch, seed)
        for name in names:
            found += runs(spark, [(name, name, cfg, work.timed(spark))], iterations, together=1)[1].collect()
        discard(work.train)
    discard(base.train, base.test)
    rows = spark.createDataFrame(found, "run string, seed int, iteration int, worker int, phase string, ms double")
    out = None
    for name in names:
        own = rows.where(F.col("run") == name)
        got = measures.time_breakdown(own).join(F.broadcast(measures.overhead_share(own.where("phase not in ('forward', 'backward')")).withColumnRenamed("share", "partition_share")), how="cross").select(F.lit(name).alias("sparsifier"), "phase", "ms", "partition_share")
        out = got if out is None else out.unionByName(got)
    return out


def _timed_search(repeats: int) -> Callable[[tuple, pa.Table], pa.Table]:
    def run(key: tuple, table: pa.Table) -> pa.Table:
        frag, v, q = (table.column(c).to_numpy() for c in ("frag_id", "v", "quota"))
        order = np.argsort(frag, kind="stable")
        edges = np.flatnonzero(np.concatenate([[True], np.diff(frag[order]) != 0, [True]]))
        parts = [(np.abs(v[order[a:b]]), int(q[order[a]])) for a, b in zip(edges[:-1], edges[1:], strict=True)]
        best = np.inf
        for _ in range(repeats):
            began = time.perf_counter()
            for m, k in parts:
                if 0 < k < len(m):
                    np.argpartition(m, len(m) - k)
            best = min(best, 1000 * (time.perf_counter() - began))
        return pa.table({"worker": np.array([key[0].as_py()], np.int32), "ms": [best]})

    return run


def selection_time(spark: SparkSession, density: float = 0.01, workers: tuple[int, ...] = SWEEP, net: Recurrent | None = None, repeats: int = 5) -> DataFrame:
    """(n, ms, speedup): wall time of the slowest worker's search by number of
    workers, on gradients with the layers of a recurrent net. One worker
    searches the whole vector at once, as global top-k does."""
    by_value()
    net = net or Recurrent(67, 64, 192)
    out = None
    for n in workers:
        cfg = RunConfig(n_workers=n, density=density)
        manifest = build_manifest(spark, net.sizes)
        model = Model.of(manifest, cfg)
        acc = commit(model.tag(synthetic_gradients(spark, manifest, n)), "acc")
        if n == 1:
            own = acc.select("worker", F.lit(0).alias("frag_id"), "v", F.lit(cfg.resolve_k(model.n_g)).cast("long").alias("quota"))
        else:
            quotas, _, owner = Fragmented(cfg).plan(acc, model, 0)
            own = acc.join(F.broadcast(owner.join(quotas, ["worker", "frag_id"]).select("worker", "frag_id", "quota")), ["worker", "frag_id"])
        slowest = own.select("worker", "frag_id", "v", "quota").groupBy("worker").applyInArrow(_timed_search(repeats), "worker int, ms double").agg(F.max("ms").alias("ms"))
        rows = commit(slowest.select(F.lit(n).alias("n"), "ms"), "search")
        out = rows if out is None else out.unionByName(rows)
    return measures.wall_speedup(out)


#: Variants of the scheme, each changing one choice.
ABLATIONS = {
    "as proposed": {},
    "one fragment a layer": {"stages": 1},
    "one fragment": {"stages": 0},
    "quota by size": {"quota_policy": "size"},
    "quota by energy": {"quota_policy": "energy"},
    "packed in turn": {"pack_policy": "round_robin"},
    "packed by size": {"pack_policy": "size"},
    "scan cost": {"cost_model": "scan"},
    "leader quotas": {"quota_scope": "leader"},
    "norms of the gradient": {"norm_of": "gradient"},
    "no cap": {"cap": False},
    "no error feedback": {"error_feedback": False},
}


def ablate(spark: SparkSession, sf_dir: str, app: str = "langid", iterations: int = 100) -> DataFrame:
    cfg = _cfg(app)
    work = SETS[app](spark, sf_dir).dealt(cfg.n_workers, cfg.local_batch)
    return runs(spark, [(label, "fragmented", _cfg(app, **options), work) for label, options in ABLATIONS.items()], iterations)[0]


def summary(rows: DataFrame, last: int = 20) -> DataFrame:
    """Per run and metric: mean of the last iterations, best and final value."""
    end = rows.agg(F.max("iteration").alias("end"))
    late = rows.join(F.broadcast(end), how="cross").withColumn("late", F.col("iteration") > F.col("end") - last)
    return late.groupBy("run", "sparsifier", "n", "density", "metric").agg(F.avg(F.when(F.col("late"), F.col("value"))).alias("late_mean"), F.max("value").alias("most"), F.min("value").alias("least"), F.max_by("value", "iteration").alias("final"))
