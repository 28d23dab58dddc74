"""Selectors: the fragmented scheme and what it is compared with.

Each takes the accumulator of all workers, with frag_id where it needs one,
and returns a Selection. picks of None stands for all entries.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gradsift.config import RunConfig
from gradsift.operators import fragment, pack, quota, select
from gradsift.sources.state import commit


@dataclass(frozen=True)
class Selection:
    picks: DataFrame | None
    quotas: DataFrame | None = None
    bins: DataFrame | None = None
    owner: DataFrame | None = None
    disjoint: bool = False
    at_most: int | None = None


@dataclass(frozen=True)
class Model:
    """What selectors know of the model: layers, their fragments, length, and
    the number of fragments."""

    manifest: DataFrame
    fragments: DataFrame
    n_g: int
    n_fragments: int

    @classmethod
    def of(cls, manifest: DataFrame, cfg: RunConfig) -> Model:
        fragments = fragment.split_oversized(manifest, cfg.n_workers, cfg.stages)
        # sizes of the layers: as many as the model has, whatever the data
        sizes = [r["size"] for r in manifest.select("size").collect()]
        n, n_g = cfg.n_workers, sum(sizes)
        pieces = [min(n, z) if cfg.stages == 2 and z * n > n_g else 1 for z in sizes]
        return cls(manifest, fragments, n_g, sum(pieces) if cfg.stages else 1)

    def tag(self, rows: DataFrame) -> DataFrame:
        """rows with frag_id."""
        return fragment.tag(rows, self.fragments, fragment.cell_width(self.n_g, self.n_fragments))


_PICKS = ["worker", "param_idx", "v", "rank"]


class Sparsifier:
    name = ""

    def __init__(self, cfg: RunConfig):
        self.cfg = cfg
        #: called when it is known who searches what, before the search
        self.planned = lambda: None

    def select(self, acc: DataFrame, model: Model, t: int) -> Selection:
        raise NotImplementedError


class Dense(Sparsifier):
    """No sparsification: everything is exchanged."""

    name = "dense"

    def select(self, acc: DataFrame, model: Model, t: int) -> Selection:
        return Selection(None)


class GlobalTopK(Sparsifier):
    """Every worker selects k from its whole vector; the union is exchanged."""

    name = "global_topk"

    def select(self, acc: DataFrame, model: Model, t: int) -> Selection:
        k = self.cfg.resolve_k(model.n_g)
        picks = select.topk_by_group(acc.withColumn("quota", F.lit(k)), ["worker"], F.abs("v"), "quota", self.cfg.kernel, k)
        return Selection(picks.select(*_PICKS), at_most=k * self.cfg.n_workers)


class CyclicTopK(Sparsifier):
    """One worker in turn selects k for all; the others wait."""

    name = "cyclic_topk"

    def select(self, acc: DataFrame, model: Model, t: int) -> Selection:
        k = self.cfg.resolve_k(model.n_g)
        led = acc.where(F.col("worker") == self.cfg.leader_of(t)).withColumn("quota", F.lit(k))
        picks = select.topk_by_group(led, ["worker"], F.abs("v"), "quota", self.cfg.kernel, k)
        return Selection(picks.select(*_PICKS), disjoint=True, at_most=k)


class Fragmented(Sparsifier):
    """The proposed scheme: fragments, quotas by norm, bins by cost, rotating
    leader and bins, top-k inside the own fragments."""

    name = "fragmented"

    def plan(self, acc: DataFrame, model: Model, t: int) -> tuple[DataFrame, DataFrame, DataFrame]:
        """Quotas of every worker, bins of the leader, owner of fragments."""
        cfg, k = self.cfg, self.cfg.resolve_k(model.n_g)
        norms = quota.fragment_norms(acc, model.fragments, cfg.n_workers)
        # a row for each worker and fragment, asked for three times from here on
        quotas = commit(quota.assign(norms, k, cfg.rounding, cfg.cap, cfg.min_quota, cfg.quota_policy, cfg.refill), "quotas")
        led = quotas.where(F.col("worker") == cfg.leader_of(t))
        bins = commit(pack.pack(pack.fragment_costs(led, cfg.cost_model), cfg.n_workers, cfg.pack_policy, model.n_fragments), "bins")
        self.planned()
        owner = pack.rotate(bins, t, cfg.n_workers)
        if cfg.quota_scope == "leader":
            quotas = owner.join(F.broadcast(led.drop("worker")), "frag_id").select(*quotas.columns)
        return quotas, bins, owner

    def select(self, acc: DataFrame, model: Model, t: int, seen: DataFrame | None = None) -> Selection:
        """seen: what norms and quotas are taken of, if not the accumulator."""
        quotas, bins, owner = self.plan(acc if seen is None else seen, model, t)
        k = self.cfg.resolve_k(model.n_g)
        # no quota exceeds k or the minimum, which bounds every group
        picks = select.layerwise(acc, quotas, owner, self.cfg.kernel, max(k, self.cfg.min_quota))
        return Selection(picks, quotas, bins, owner, disjoint=True, at_most=2 * k)


class EqualSlices(Sparsifier):
    """The trivial partition: n equal slices of the vector, k/n from each."""

    name = "equal_slices"

    def select(self, acc: DataFrame, model: Model, t: int) -> Selection:
        n, k = self.cfg.n_workers, self.cfg.resolve_k(model.n_g)
        cut = F.floor(F.col("param_idx") * n / F.lit(model.n_g)).cast("int")
        own = acc.withColumn("slice", cut).where(F.col("slice") == F.pmod(F.col("worker") + F.lit(t % n), F.lit(n)))
        own = own.withColumn("quota", F.lit(k // n) + (F.col("slice") < k % n).cast("int"))
        picks = select.topk_by_group(own, ["slice"], F.abs("v"), "quota", self.cfg.kernel, -(-k // n))
        return Selection(picks.select(*_PICKS), disjoint=True, at_most=k)


class RandomK(Sparsifier):
    """Extension: k indices at random, the same on all workers."""

    name = "random_k"

    def select(self, acc: DataFrame, model: Model, t: int) -> Selection:
        k = self.cfg.resolve_k(model.n_g)
        order = F.xxhash64(F.lit(self.cfg.seed + t), F.col("param_idx"))
        chosen = acc.sparkSession.range(model.n_g).select(F.col("id").alias("param_idx")).orderBy(order, "param_idx").limit(k)
        return Selection(chosen.select(F.lit(self.cfg.leader_of(t)).alias("worker"), "param_idx", F.lit(0.0).alias("v"), F.lit(0).alias("rank")), disjoint=True, at_most=k)


class Threshold(Sparsifier):
    """Extension: every worker sends what exceeds a fixed magnitude."""

    name = "threshold"

    def __init__(self, cfg: RunConfig, magnitude: float = 1.0):
        super().__init__(cfg)
        self.magnitude = magnitude

    def select(self, acc: DataFrame, model: Model, t: int) -> Selection:
        return Selection(acc.where(F.abs("v") >= self.magnitude).select("worker", "param_idx", "v", F.lit(0).alias("rank")))


SPARSIFIERS: dict[str, type[Sparsifier]] = {s.name: s for s in (Dense, GlobalTopK, CyclicTopK, Fragmented, EqualSlices, RandomK, Threshold)}
