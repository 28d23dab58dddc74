"""Units, properties and counter-examples of the selection operators."""

import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from gradsift import checks
from gradsift.config import RunConfig
from gradsift.operators import exchange, feedback, fragment, pack, quota, select, shards
from gradsift.operators.sparsifiers import SPARSIFIERS, Fragmented, Model
from gradsift.plans import measures, simulate
from gradsift.plans.queries import EXAMPLE, example


def rows_of(df, *names):
    return sorted(tuple(r[n] for n in names) for r in df.collect())


def random_case(rng, n_layers, most, n):
    sizes = [rng.randint(1, most) for _ in range(n_layers)]
    acc = np.array([[rng.choice([0, 1, -1, rng.gauss(0, 2.0 ** -(i % 5))]) for i, s in enumerate(sizes) for _ in range(s)] for _ in range(n)])
    return sizes, acc


def as_df(spark, acc):
    return spark.createDataFrame([(w, i, float(v)) for w, row in enumerate(acc) for i, v in enumerate(row)], "worker int, param_idx long, v double")


# -- the worked example -----------------------------------------------------------


def test_worked_example(spark):
    cfg, model, acc = example(spark)
    assert rows_of(model.fragments, "frag_id", "start", "size") == [(0, 0, 6), (1, 6, 6), (2, 12, 3), (3, 15, 3), (4, 18, 2)]
    norms = quota.fragment_norms(acc, model.fragments, 2)
    assert rows_of(norms.where("worker = 0"), "frag_id", "norm") == [(0, 10.0), (1, 5.0), (2, 3.0), (3, 0.0), (4, 13.0)]
    capped = quota.assign(norms, 8)
    assert [q for _, q in rows_of(capped.where("worker = 0"), "frag_id", "quota")] == [3, 2, 1, 0, 2]
    assert [q for _, q in rows_of(quota.assign(norms, 8, cap=False).where("worker = 0"), "frag_id", "quota")] == [3, 1, 1, 0, 3]
    chosen = Fragmented(cfg).select(acc, model, 3)
    assert {r.worker: r.frag_ids for r in chosen.owner.groupBy("worker").agg(F.array_sort(F.collect_list("frag_id")).alias("frag_ids")).collect()} == {1: [0], 0: [1, 2, 3, 4]}
    assert rows_of(chosen.picks, "worker", "param_idx") == [(0, 6), (0, 7), (0, 12), (0, 18), (0, 19), (1, 0), (1, 1), (1, 2)]
    got = measures.selection_cost(measures.worker_costs(chosen.quotas, chosen.owner, 2)).first()
    assert got["cost"] == pytest.approx(6.591674, abs=1e-6) and got["kappa"] == 5
    assert measures.global_cost(8, 20) / got["cost"] == pytest.approx(6.309298, abs=1e-5)
    assert measures.trivial_cost(2, 8, 20) == pytest.approx(13.862944, abs=1e-6)
    assert measures.trivial_speedup(2, 8) == pytest.approx(3.0)
    assert measures.payload_bytes(chosen.bins).first()["bytes"] == 20
    best = SPARSIFIERS["global_topk"](cfg).select(acc, model, 3).picks
    assert {i for _, i in rows_of(best, "worker", "param_idx")} == {0, 1, 6, 7, 12, 14, 18, 19}
    assert measures.recall(chosen.picks, best.where("worker = 0")).first()["recall"] == pytest.approx(7 / 8)


# -- properties ---------------------------------------------------------------------


@pytest.mark.parametrize("seed", range(4))
def test_dataframe_operators_equal_the_numpy_form(spark, seed):
    rng = random.Random(seed)
    n = rng.choice([1, 2, 3, 5])
    sizes, acc = random_case(rng, rng.randint(1, 6), 25, n)
    k = rng.randint(1, sum(sizes))
    cfg = RunConfig(n_workers=n, k=k)
    manifest = fragment.build_manifest(spark, [(f"l{i}", s) for i, s in enumerate(sizes)])
    model = Model.of(manifest, cfg)
    frags = simulate.fragments(sizes, n)
    assert (model.n_g, model.n_fragments) == (sum(sizes), len(frags))
    assert [(a, s) for _, a, s in rows_of(model.fragments, "frag_id", "start", "size")] == frags
    rows = fragment.tag(as_df(spark, acc), model.fragments)
    assert rows_of(rows, "worker", "param_idx", "frag_id") == rows_of(fragment.tag_by_range(as_df(spark, acc), model.fragments), "worker", "param_idx", "frag_id")
    for name in ("global_topk", "cyclic_topk", "fragmented", "equal_slices"):
        for t in (0, 1):
            mine = {i for (i,) in rows_of(SPARSIFIERS[name](cfg).select(rows, model, t).picks, "param_idx")}
            theirs = simulate.choose(name, acc, frags, k, t, cfg).indices
            assert mine == set(theirs.tolist()), (name, t)


def test_fragments_tile_the_vector_and_respect_the_bound():
    rng = random.Random(1)
    for _ in range(5000):
        n = rng.choice([1, 2, 3, 4, 8, 16])
        sizes = [rng.randint(1, 300) for _ in range(rng.randint(1, 15))]
        frags, total = simulate.fragments(sizes, n), sum(sizes)
        assert [a for a, _ in frags] == np.cumsum([0] + [s for _, s in frags])[:-1].tolist() and sum(s for _, s in frags) == total
        assert all(1 <= s <= math.ceil(total / n) for _, s in frags)
    assert simulate.fragments([10], 3) == [(0, 4), (4, 3), (7, 3)]
    assert simulate.fragments([5, 5], 2) == [(0, 5), (5, 5)]
    assert len(simulate.fragments([3], 8)) == 3


def test_quota_and_packing_invariants():
    rng = random.Random(2)
    short = 0
    for _ in range(500):
        L, n = rng.randint(1, 20), rng.choice([1, 2, 4, 8])
        sizes = np.array([rng.randint(1, 200) for _ in range(L)])
        norms = np.array([rng.choice([0.0, rng.random(), 10 * rng.random()]) for _ in range(L)])
        k = rng.randint(1, int(sizes.sum()))
        q = simulate.quotas(norms, sizes, k, RunConfig(k=k))
        assert q.sum() <= k and (q <= sizes).all() and (q[norms == 0] == 0).all()
        short += q.sum() < k
        cost = simulate.costs(sizes, q)
        bins = simulate.packed(cost, n)
        loads = np.bincount(bins, weights=cost, minlength=n)
        assert loads.max() <= cost.sum() / n + cost.max() + 1e-3
    assert short < 500


def test_sequential_quota_is_proportional_without_rounding(spark):
    rows = [(0, i, 10**9, float(w)) for i, w in enumerate([5, 3, 9, 1, 0])]
    norms = spark.createDataFrame(rows, "worker int, frag_id int, size long, norm double")
    exact = {f: s for f, s in rows_of(quota.proportional(norms, 10**6), "frag_id", "share")}
    for f, q in rows_of(quota.assign(norms, 10**6), "frag_id", "quota"):
        assert abs(q - exact[f]) <= 1


def test_refill_uses_the_room_left(spark):
    norms = spark.createDataFrame([(0, 0, 2, 1.0), (0, 1, 50, 9.0), (0, 2, 1, 0.5)], "worker int, frag_id int, size long, norm double")
    assert sum(q for (q,) in rows_of(quota.assign(norms, 50, refill=True), "quota")) == 50


@pytest.mark.parametrize("kernel", ["two_phase", "threshold", "arrow"])
def test_kernels_agree(spark, kernel, monkeypatch):
    monkeypatch.setattr(select, "BLOCK_WIDTH", 16)
    rng = random.Random(3)
    rows = [(g, i, float(rng.choice([0, 1, -1, 2, rng.gauss(0, 3)])), q) for g, q in ((0, 7), (1, 0), (2, 100), (3, None), (4, 1)) for i in range(60)]
    df = spark.createDataFrame(rows, "g int, param_idx long, v double, quota long")
    pick = lambda kern: rows_of(select.topk_by_group(df, ["g"], F.abs("v"), "quota", kern), "g", "param_idx", "rank")
    assert pick(kernel) == pick("window")


def test_large_quotas_are_cut_by_buckets(spark, monkeypatch):
    """Beyond the planner's limit the histogram takes over, and no session
    setting changes."""
    name = "spark.sql.optimizer.windowGroupLimitThreshold"
    before = spark.conf.get(name, None)
    rng = random.Random(6)
    rows = [(g, i, rng.choice([0.0, 2.0**rng.randint(-40, 40), -(2.0 ** rng.randint(-3, 3)), rng.gauss(0, 1)])) for g in range(3) for i in range(900)]
    df = spark.createDataFrame(rows, "worker int, param_idx long, v double").withColumn("quota", F.lit(300))
    plain = rows_of(select.topk_by_group(df, ["worker"], F.abs("v"), "quota", most=300), "worker", "param_idx", "rank")
    monkeypatch.setattr(select, "PLANNER_LIMIT", 100)
    large = select.topk_by_group(df, ["worker"], F.abs("v"), "quota", most=300)
    assert rows_of(large, "worker", "param_idx", "rank") == plain and len(plain) == 900
    order = sorted((r for r in rows if r[0] == 1), key=lambda r: (-abs(r[2]), r[1]))
    assert [i for g, i, _ in sorted(plain, key=lambda r: (r[0], r[2])) if g == 1] == [i for _, i, _ in order[:300]]
    assert spark.conf.get(name, None) == before


def test_packing_fold_and_heap_agree(spark):
    rng = random.Random(4)
    costs = spark.createDataFrame([(i, rng.choice([0.0, 1.5, rng.random() * 100])) for i in range(60)], "frag_id int, cost double")
    for n in (1, 3, 8):
        folded = rows_of(pack.pack(costs, n, fragments=60), "frag_id", "bin", "pack_order")
        assert folded == rows_of(pack.pack(costs, n, fragments=pack.FOLD_LIMIT + 1), "frag_id", "bin", "pack_order")


def test_rotation_gives_every_worker_every_bin_once(spark):
    bins = spark.createDataFrame([(b, b, 0.0, b) for b in range(4)], "bin int, frag_id int, cost double, pack_order int")
    seen = [(t, w, f) for t in range(4) for w, f in rows_of(pack.rotate(bins, t, 4), "worker", "frag_id")]
    assert len({(w, f) for _, w, f in seen}) == 16 and all(f == (t + w) % 4 for t, w, f in seen)
    cfg = RunConfig(n_workers=4, k=1)
    assert [cfg.leader_of(t) for t in range(5)] == [0, 1, 2, 3, 0]


# -- exchange and feedback ------------------------------------------------------------


def test_conservation_of_mass(spark):
    cfg, model, acc = example(spark)
    picks = Fragmented(cfg).select(acc, model, 0).picks
    indices = exchange.union_indices(picks, disjoint=True)
    sent = exchange.average(acc, indices, 2).agg(F.sum("mean")).first()[0] * 2
    kept = feedback.residual(acc, indices).agg(F.sum("v")).first()[0]
    assert sent + kept == sum(EXAMPLE) * 2
    assert checks.repeated_picks(picks) == 0
    with pytest.raises(AssertionError):
        checks.assert_disjoint(picks.unionByName(picks))


def test_rate_inside_or_outside_gives_the_same_model(spark):
    grads = spark.createDataFrame([(w, i, float(i + w)) for w in range(2) for i in range(6)], "worker int, param_idx long, v double")
    params = spark.range(6).select(F.col("id").alias("param_idx"), F.lit(1.0).alias("value"))
    out = []
    for mode in ("accumulate", "update"):
        acc = feedback.accumulate(None, grads, 0.5, mode)
        out.append(rows_of(exchange.apply_update(params, exchange.average(acc, None, 2), 0.5, mode), "param_idx", "value"))
    assert out[0] == out[1]


def test_union_bounds(spark):
    same = as_df(spark, np.tile(np.arange(1.0, 21), (4, 1)))
    apart = spark.createDataFrame([(w, 5 * w + j, 1.0 + j) for w in range(4) for j in range(5)], "worker int, param_idx long, v double")
    cfg = RunConfig(n_workers=4, k=5)
    model = Model.of(fragment.build_manifest(spark, [("a", 20)]), cfg)
    for acc, want in ((same, 1.0), (apart, 4.0)):
        picks = SPARSIFIERS["global_topk"](cfg).select(acc, model, 0).picks
        assert measures.build_up(picks, 5).first()["build_up"] == want


def test_shards_and_batches_partition_the_rows(spark):
    rows = spark.range(500).withColumnRenamed("id", "key")
    assert shards.assign(rows, "key", 7).where("worker between 0 and 6").count() == 500
    assert sum(shards.batch(rows, "key", t, 4).count() for t in range(4)) == 500


# -- counter-examples and edges ---------------------------------------------------------


def test_speedup_bound_is_not_a_theorem():
    third = 333_333
    cfg = RunConfig(n_workers=2, k=99_999)
    sizes = np.array([third] * 3)
    q = simulate.quotas(np.ones(3), sizes, 99_999, cfg)
    loads = np.bincount(simulate.packed(simulate.costs(sizes, q), 2), weights=simulate.costs(sizes, q))
    f = measures.global_cost(99_999, 3 * third) / loads.max()
    assert q.tolist() == [33_333] * 3 and f == pytest.approx(1.658236, abs=1e-5) and f < 2
    assert measures.trivial_speedup(2, 99_999) == pytest.approx(2.128126, abs=1e-5)
    one = simulate.costs(np.array([50, 50]), simulate.quotas(np.array([1.0, 0.0]), np.array([50, 50]), 20, RunConfig(n_workers=2, k=20)))
    assert one.max() == pytest.approx(149.786614, abs=1e-5) and one.max() > measures.trivial_cost(2, 20, 100)


def test_trivial_speedup_exceeds_n_and_grows():
    for k in (2, 10, 1000):
        per = [measures.trivial_speedup(n, k) / n for n in (1, 2, 4, 8, 16, 32) if k > n]
        assert all(p >= 1 for p in per) and per == sorted(per)
    assert measures.trivial_speedup(4, 4) is None and measures.trivial_speedup(8, 4) is None


def test_zero_accumulator_selects_nothing(spark):
    cfg = RunConfig(n_workers=2, k=3)
    model = Model.of(fragment.build_manifest(spark, [("a", 6), ("b", 2)]), cfg)
    acc = fragment.tag(as_df(spark, np.zeros((2, 8))), model.fragments)
    chosen = Fragmented(cfg).select(acc, model, 0)
    assert chosen.picks.count() == 0
    cost = measures.selection_cost(measures.worker_costs(chosen.quotas, chosen.owner, 2)).first()["cost"]
    assert cost == 0


def test_bad_settings_and_values(spark):
    for bad in ({}, {"k": 1, "density": 0.1}, {"density": 0.0}, {"k": 0}, {"k": 1, "rounding": "up"}, {"k": 1, "n_workers": 0}):
        with pytest.raises(ValueError):
            RunConfig(**bad)
    assert RunConfig(density=1.0).resolve_k(7) == 7 and RunConfig(k=99).resolve_k(7) == 7 and RunConfig(density=0.001).resolve_k(10) == 1
    acc = spark.createDataFrame([(0, 0, float("nan"))], "worker int, param_idx long, v double")
    with pytest.raises(ValueError):
        checks.finite(acc)
    assert checks.index_range(spark.createDataFrame([(9,), (-1,), (3,)], "param_idx long"), 9) == 2
    with pytest.raises(ValueError):
        fragment.build_manifest(spark, [("a", 0)])


def test_rate_decay():
    cfg = RunConfig(k=1, lr=1.0, decay_steps=(3, 5), gamma=0.1)
    assert [cfg.lr_at(t) for t in (0, 3, 5)] == pytest.approx([1.0, 0.1, 0.01])
