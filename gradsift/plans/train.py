"""Distributed SGD with sparsification and error feedback, run to the end.

A worker is a column, never a task. One iteration is one logical plan of
gradients, accumulation, selection, exchange, update and residual; the state
that it leaves, model and error, is written to the shared folder, which ends
the lineage, and the state before it is deleted. No operator brings anything of
the length of the vector to the driver.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field, replace
from typing import Protocol

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gradsift import schemas
from gradsift.config import RunConfig
from gradsift.operators import exchange, feedback
from gradsift.operators.sparsifiers import SPARSIFIERS, Model, Selection, Sparsifier
from gradsift.plans import measures
from gradsift.sources import collect_garbage, commit, discard, read_state, write_state


class Workload(Protocol):
    n_workers: int

    def manifest(self, spark: SparkSession) -> DataFrame: ...
    def init_params(self, spark: SparkSession) -> DataFrame: ...
    def gradients(self, params: DataFrame, t: int) -> DataFrame: ...
    def evaluate(self, params: DataFrame) -> DataFrame: ...


@dataclass(frozen=True)
class State:
    params: DataFrame
    error: DataFrame | None
    t: int = 0


@dataclass
class RunResult:
    state: State
    metrics: list[tuple] = field(default_factory=list)
    timings: list[tuple] = field(default_factory=list)

    def metrics_df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.metrics, schemas.METRICS)

    def timings_df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.timings, schemas.TIMINGS)


class Clock:
    """Wall time of the phases of an iteration, as rows of TIMINGS. Workers
    run in one plan, so the phase time is that of the slowest. first: the name
    of the first phase, which ends when the accumulator is written."""

    def __init__(self, rows: list[tuple], seed: int, first: str = "backward"):
        self.rows, self.seed, self.first, self.at = rows, seed, first, time.perf_counter()

    def lap(self, t: int, phase: str) -> None:
        now = time.perf_counter()
        self.rows.append((self.seed, t, -1, phase, 1000 * (now - self.at)))
        self.at = now


def step(state: State, grads: DataFrame, model: Model, sparsifier: Sparsifier, cfg: RunConfig, clock: Clock | None = None) -> tuple[State, DataFrame, Selection]:
    """One iteration. Returns the next state, the accumulator, and what was
    selected. A committed error of the state is deleted on the way."""
    lap = (lambda p: clock.lap(state.t, p)) if clock else (lambda p: None)
    t, lr = state.t, cfg.lr_at(state.t)
    acc = feedback.accumulate(state.error if cfg.error_feedback else None, grads, lr, cfg.lr_mode)
    acc = commit(model.tag(acc), "acc")
    discard(state.error)  # the accumulator holds it
    lap(clock.first if clock else "")
    sparsifier.planned = lambda: lap("partition")
    if cfg.norm_of == "gradient" and sparsifier.name == "fragmented":
        chosen = sparsifier.select(acc, model, t, seen=model.tag(feedback.accumulate(None, grads, lr, cfg.lr_mode)))
    else:
        chosen = sparsifier.select(acc, model, t)
    indices = None
    if chosen.picks is not None:
        chosen = replace(chosen, picks=commit(chosen.picks, "picks"))
        indices = exchange.union_indices(chosen.picks, chosen.disjoint)
    lap("selection")
    mean = exchange.average(acc, indices, cfg.n_workers, chosen.at_most)
    params = commit(exchange.apply_update(state.params, mean, lr, cfg.lr_mode), "params")
    lap("communication")
    error = commit(feedback.residual(acc, indices), "error") if cfg.error_feedback else None
    lap("residual")
    return State(params, error, t + 1), acc, chosen


def _costs(chosen: Selection, name: str, cfg: RunConfig, n_g: int) -> tuple[float, float]:
    """Model cost of a selection, and the most that one worker sends."""
    k = cfg.resolve_k(n_g)
    if chosen.quotas is None:
        searched = {"dense": 0.0, "equal_slices": measures.trivial_cost(cfg.n_workers, k, n_g) or 0.0}.get(name, measures.global_cost(k, n_g))
        return searched, float({"dense": n_g, "equal_slices": -(-k // cfg.n_workers)}.get(name, k))
    got = measures.selection_cost(measures.worker_costs(chosen.quotas, chosen.owner, cfg.n_workers, cfg.cost_model)).first()
    return float(got["cost"]), float(got["kappa"])


def run(workload: Workload, name: str, cfg: RunConfig, spark: SparkSession, iterations: int, evaluate_each: int = 1, save_to: str | None = None, resume: int | None = None, label: str | None = None, costs: bool = False) -> RunResult:
    """Train for `iterations`, from the saved iteration `resume` if given.
    costs: also note the model cost and the most that one worker sends."""
    sparsifier = SPARSIFIERS[name](cfg)
    manifest = commit(workload.manifest(spark), "manifest")
    model = Model.of(manifest, cfg)
    model = replace(model, fragments=commit(model.fragments, "fragments"))
    state = State(commit(workload.init_params(spark), "params"), None)
    if resume is not None:
        discard(state.params)
        params = read_state(spark, f"{save_to}/params", resume)
        error = read_state(spark, f"{save_to}/error", resume) if cfg.error_feedback else None
        state = State(params, error, resume)
    result = RunResult(state)
    note = lambda t, metric, value: result.metrics.append((label or name, name, cfg.n_workers, cfg.density or cfg.resolve_k(model.n_g) / model.n_g, t, metric, None if value is None else float(value)))
    inside = getattr(workload, "clock", None)
    clock = Clock(result.timings, cfg.seed, "backward" if inside is None else "accumulate")
    for t in range(state.t, iterations):
        before = state
        state, acc, chosen = step(state, workload.gradients(state.params, t), model, sparsifier, cfg, clock)
        got = model.n_g if chosen.picks is None else chosen.picks.agg(F.count_distinct("param_idx")).first()[0]
        note(t, "selected", got)
        note(t, "density", got / model.n_g)
        kept = acc if cfg.error_at == "accumulator" else state.error
        note(t, "error", 0.0 if kept is None else measures.mean_error(kept, cfg.n_workers).first()["error"])
        if costs:
            for metric, value in zip(("cost", "kappa"), _costs(chosen, name, cfg, model.n_g), strict=True):
                note(t, metric, value)
        if (t + 1) % evaluate_each == 0 or t + 1 == iterations:
            for r in workload.evaluate(state.params).collect():
                note(t, r["metric"], r["value"])
        if save_to:
            write_state(state.params, f"{save_to}/params", state.t)
            if state.error is not None:
                write_state(state.error, f"{save_to}/error", state.t)
        # the new state is written: nothing reads what it was made of
        discard(acc, chosen.picks, chosen.quotas, chosen.bins, before.params)
        before = acc = chosen = kept = None
        collect_garbage(spark)
        clock.at = time.perf_counter()
        result.state = state
    if inside is not None:
        result.timings += [(cfg.seed, *lap) for lap in inside.value]
    return result
