"""Runs: golden iterations, restart, nets, experiments, streaming, SQL, plans."""

import glob
import os
import pathlib
import shutil
import subprocess
import sys

import duckdb
import numpy as np
import pyarrow.compute as pc
import pytest
from pyspark.errors import AnalysisException
from pyspark.sql import functions as F

import __spark_entry__
from gradsift import functions, sources
from gradsift.config import RunConfig
from gradsift.operators import fragment
from gradsift.operators.sparsifiers import Fragmented, Model
from gradsift.plans import experiments, measures, oracles, queries, simulate, train
from gradsift.streaming import loop
from gradsift.workloads import base_rates, training_sets
from gradsift.workloads.additive import Additive
from gradsift.workloads.nets import Perceptron, Recommender, Recurrent


def test_entry_has_rows(spark):
    assert __spark_entry__.entry(spark).count() == 4


@pytest.mark.parametrize("name", ["fragments_n16", "quota_sequential", "bins_greedy", "picks_fragmented", "exchange_mean", "residual_after_1", "train3_fragmented", "worked_example_picks", "events_session", "jaccard_pairs"])
def test_queries_match_their_oracles(spark, sf, name):
    con = duckdb.connect()
    for f in glob.glob(f"{sf}/*.parquet"):
        con.execute(f"create view {os.path.basename(f)[:-8]} as select * from '{f}'")
    df = queries.QUERIES[name](spark, sf)
    r = con.execute(oracles.ORACLE[name])
    order = [[c[0] for c in r.description].index(c) for c in df.columns]
    key = lambda row: str([round(x, 9) if isinstance(x, float) else x for x in row])
    want = sorted(key([row[i] for i in order]) for row in r.fetchall())
    assert sorted(key(list(row)) for row in df.collect()) == want


@pytest.mark.parametrize("name", ["idle_by_n", "worked_example_quotas", "worked_example_picks"])
def test_queries_read_their_tables(spark, sf, tmp_path, name):
    """They match their SQL on given tables, and fail where there are none."""
    test_queries_match_their_oracles(spark, sf, name)
    with pytest.raises(AnalysisException):
        queries.QUERIES[name](spark, str(tmp_path)).collect()


def test_every_query_but_net_training_has_an_oracle():
    assert set(queries.QUERIES) - set(oracles.ORACLE) == set(queries.TRAINED)


def vectors_of(spark, n, **options):
    return training_sets.vectors(spark, "/root/testdata/sf0.001").dealt(n, 8, **options)


def test_a_set_of_many_batches_has_few_folders(spark):
    """Every batch is found, and no more than FOLDERS folders are written."""
    work = vectors_of(spark, 4).dealt(2, 1)
    assert work.batches > training_sets.FOLDERS
    folders = {os.path.basename(os.path.dirname(f)) for f in work.train.inputFiles()}
    assert 1 < len(folders) <= training_sets.FOLDERS
    found = 0
    for t in (0, 1, work.batches // 2, work.batches - 1):
        span = training_sets.shards.span_of(F.lit(t), work.batches, training_sets.FOLDERS)
        found += work.train.where((F.col("batch") == t) & (F.col("span") == span)).count()
    assert found == work.train.where(F.col("batch").isin(0, 1, work.batches // 2, work.batches - 1)).count()


def test_forward_pass_alone_gives_the_loss():
    rng = np.random.default_rng(2)
    s = rng.integers(0, 30, (600, 9))
    net = Recurrent(30, 8, 16)
    flat = 3 * net.init(1)
    assert abs(net.nll(flat, s[:, :-1], s[:, 1:]) - net.loss(flat, (s[:, :-1], s[:, 1:]))[0]) < 1e-6


@pytest.mark.parametrize("name,options", [("fragmented", {}), ("fragmented", {"quota_scope": "leader", "stages": 1, "lr_mode": "update"}), ("global_topk", {}), ("cyclic_topk", {"error_feedback": False}), ("dense", {})])
def test_training_of_a_net_equals_the_numpy_form(spark, name, options):
    """Parameters, picks, error and cost of three iterations, gradients by
    worker on Spark against a loop over the same rows."""
    cfg = RunConfig(n_workers=4, density=0.02, lr=0.5, decay_steps=(2,), **options)
    work = vectors_of(spark, 4)
    assert work.batches == 12 and work.train.where("batch < 0 or batch > 11 or worker < 0 or worker > 3").count() == 0
    rows = work.train.toArrow().sort_by("key")

    def batch_of(w, t):
        part = rows.filter((pc.field("worker") == w) & (pc.field("batch") == t % work.batches))
        return work.unpack(part) if part.num_rows else None

    flat, noted = simulate.simulate(work.net, batch_of, name, cfg, 3)
    got = train.run(work, name, cfg, spark, 3, 3, costs=True)
    assert np.allclose(work.replica(got.state.params), flat, atol=1e-12)
    mine = {(m[4], m[5]): m[6] for m in got.metrics}
    for t, metric, value in noted:
        assert mine[t, metric] == pytest.approx(value, rel=1e-6, abs=1e-9), (t, metric)
    assert mine[2, "accuracy"] == pytest.approx(np.mean([(work.net.predict(flat, x[None]) == y)[0] for x, y in zip(*training_sets.labelled(work.test.toArrow()), strict=True)]))


def test_old_state_is_deleted(spark, tmp_path):
    before = set(glob.glob(sources.shared_dir(spark).removeprefix("file:") + "/*"))
    train.run(vectors_of(spark, 2), "fragmented", RunConfig(n_workers=2, density=0.05), spark, 2, 2)
    left = {os.path.basename(f).rsplit("-", 1)[0] for f in set(glob.glob(sources.shared_dir(spark).removeprefix("file:") + "/*")) - before}
    assert left <= {"train", "manifest", "fragments", "params", "error"}


def test_sets_hold_whole_texts_and_all_rows(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    work = training_sets.langid(spark, sf)
    assert work.train.count() + work.test.count() == docs.where("lang is not null").count()
    texts = spark.createDataFrame([(1, "ab" * 40), (2, ""), (3, None), (4, "é")], "doc_id long, text string")
    known = training_sets.alphabet(texts)
    assert known == sorted(map(ord, "abé"))
    windows = sorted(tuple(r.s) for r in training_sets.symbol_windows(texts, known).where("doc_id = 1").collect())
    code = [1] + [known.index(ord(c)) + 2 for c in "ab" * 40]
    assert windows == sorted(tuple((code[i : i + 33] + [1] * 33)[:33]) for i in (0, 32, 64))
    x = training_sets.bigram_features(spark.createDataFrame([(1, "a", "Aba"), (2, "a", ""), (3, None, "x")], "doc_id long, lang string, text string")).collect()
    assert sorted((r.key, round(float(np.linalg.norm(r.x)), 5)) for r in x) == [(1, 1.0), (2, 0.0)]
    work = training_sets.recommend(spark, sf)
    assert work.test.count() == base_rates.purchases(spark, sf)[1].count()
    assert work.test.where("size(items) > 100 or size(items) < 2").count() == 0


def test_recommender_without_a_replica(spark, sf, monkeypatch):
    """Gradients, hit rate and initial values are those of the net that holds
    all factors, to the last bit, while nothing holds them."""
    work = training_sets.recommend(spark, sf).dealt(4, 256)
    flat = work.net.init(work.seed)
    drawn = work.init_params(spark).toPandas().sort_values("param_idx")
    assert (drawn.param_idx == range(work.net.n_g)).all() and (drawn.value == flat).all()
    params = sources.commit(work.init_params(spark), "params")
    rows = lambda df: sorted(map(tuple, df.collect()))
    rate = lambda table: (lambda total, n: total / n)(*training_sets.hits(work.net, flat, table))
    want, rate = [rows(training_sets.NetWorkload.gradients(work, params, t)) for t in (0, 1)], rate(work.test.toArrow())
    for limit, value in (("MOST_PARAMS", 1000), ("TILE_USERS", 40), ("TILE_ITEMS", 60), ("PAIRS", 1000)):
        monkeypatch.setattr(training_sets, limit, value)
    assert [rows(work.gradients(params, t)) for t in (0, 1)] == want and want[0] != want[1]
    assert work.evaluate(params).first()["value"] == rate
    few = [(u, i) for u, i in ((3, [5]), (4, [6, 7]))]
    alone = training_sets.replace(work, test=spark.createDataFrame(few, "user long, items array<long>"))
    assert alone.evaluate(params).first()["value"] == 1.0
    odd = training_sets.replace(work, test=spark.createDataFrame([(3, [work.items])], "user long, items array<long>"))
    with pytest.raises(Exception, match="do not number"):
        odd.evaluate(params).collect()


def test_forward_loss_is_the_training_loss():
    rng = np.random.default_rng(3)
    net = Recurrent(9, 5, 6)
    flat, s, y = net.init(1), rng.integers(0, 9, (4, 7)), rng.integers(0, 9, (4, 7))
    assert net.nll(flat, s, y) == pytest.approx(net.loss(flat, (s, y))[0])


def test_forward_loss_of_large_outputs_and_odd_symbols():
    """Outputs too large for plain exponentials, alone and beside others; a
    symbol that the net does not have is an error and no other symbol."""
    rng = np.random.default_rng(4)
    net, s = Recurrent(9, 5, 6), rng.integers(0, 9, (300, 8))
    for scale in (1, 30, 100):
        flat = net.init(1)
        net.cut(flat)[-2][:] *= scale
        net.cut(flat)[-1][:] = scale * np.arange(9) / 9
        assert net.nll(flat, s[:, :-1], s[:, 1:]) == pytest.approx(net.loss(flat, (s[:, :-1], s[:, 1:]))[0], rel=1e-6)
    for odd in (-1, 9):
        with pytest.raises(IndexError):
            net.nll(flat, np.full((2, 3), odd), np.zeros((2, 3), int))


def test_windows_of_a_set_are_packed(spark, sf):
    """A byte a symbol where that is enough, and the symbols are those of the
    windows as lists, in a set and when it is dealt."""
    lists = lambda rows: {r.key: tuple(r.s) for r in rows.collect()}
    unpacked = lambda table: dict(zip(table.column("key").to_pylist(), (tuple(map(int, [*s, y[-1]])) for s, y in zip(*training_sets.symbols(table), strict=True)), strict=True))
    docs, work = spark.read.parquet(f"{sf}/documents.parquet"), training_sets.charlm(spark, sf, 8)
    assert {len(s) for s in work.train.toArrow().column("s").to_pylist()} == {training_sets.STEPS + 1}
    known = training_sets.alphabet(docs.where("doc_id % 5 <> 4"))
    want = lists(training_sets.symbol_windows(docs.where("doc_id % 5 <> 4"), known))
    assert want == unpacked(work.train.toArrow()) == unpacked(work.dealt(2, 32).train.toArrow())
    assert lists(training_sets.symbol_windows(docs.where("doc_id % 5 = 4"), known)) == unpacked(work.test.toArrow())
    wide = spark.createDataFrame([(1, "".join(map(chr, range(0x4E00, 0x4E00 + 300)))), (2, "x")], "doc_id long, text string")
    known = training_sets.alphabet(wide.where("doc_id = 1"))
    assert lists(training_sets.symbol_windows(wide, known)) == unpacked(training_sets.symbol_windows(wide, known, packed=True).toArrow())


def test_scale_sweep_leaves_no_windows(spark, sf):
    before = set(glob.glob(sources.shared_dir(spark).removeprefix("file:") + "/*"))
    rows = experiments.scale_sweep(spark, sf, 1, workers=(2,), hidden=8)
    left = {os.path.basename(f).rsplit("-", 1)[0] for f in set(glob.glob(sources.shared_dir(spark).removeprefix("file:") + "/*")) - before}
    assert left <= {"manifest", "fragments", "params", "error"}
    assert {r.metric for r in rows.collect()} == {"selected", "density", "error", "cost", "kappa", "perplexity"}


def test_breakdown_leaves_no_windows(spark, sf):
    before = set(glob.glob(sources.shared_dir(spark).removeprefix("file:") + "/*"))
    rows = experiments.breakdown(spark, sf, iterations=1, seeds=1, names=("cyclic_topk",))
    left = {os.path.basename(f).rsplit("-", 1)[0] for f in set(glob.glob(sources.shared_dir(spark).removeprefix("file:") + "/*")) - before}
    assert left <= {"manifest", "fragments", "params", "error"}
    assert {r.phase for r in rows.collect()} == {"forward", "backward", "accumulate", "selection", "communication", "residual"}


def test_breakdown_and_search_time_are_numbers(spark, sf):
    rows = experiments.breakdown(spark, sf, "vectors", iterations=1, seeds=1, names=("fragmented",)).collect()
    ms = {r.phase: r.ms for r in rows}
    assert set(ms) == {"forward", "backward", "accumulate", "partition", "selection", "communication", "residual"} and min(ms.values()) > 0
    assert 0 < rows[0].partition_share < 1
    rows = experiments.selection_time(spark, workers=(1, 4), net=Recurrent(40, 16, 64)).collect()
    assert {r.n for r in rows} == {1, 4} and all(r.ms > 0 for r in rows)


GOLDEN = {
    "fragmented": ([367, 321, 368], [0.164042, 0.318317, 0.405160], [14.431610, 14.431224, 14.430574]),
    "global_topk": ([1035, 1144, 1227], [0.106035, 0.173797, 0.206321], [14.431355, 14.430628, 14.429787]),
}


@pytest.mark.parametrize("name", list(GOLDEN))
def test_three_golden_iterations(spark, name):
    got = queries.train_metrics(spark, "/root/testdata/sf0.01", name).orderBy("iteration").collect()
    assert ([r["selected"] for r in got], [r["error"] for r in got], [r["rmse"] for r in got]) == GOLDEN[name]


def test_restart_from_saved_state_gives_the_same_model(spark, sf, tmp_path):
    cfg = RunConfig(n_workers=2, density=0.1, lr=2.0**-10)
    work = Additive.load(spark, sf, 2)
    straight = train.run(work, "fragmented", cfg, spark, 3)
    train.run(work, "fragmented", cfg, spark, 2, save_to=str(tmp_path))
    resumed = train.run(work, "fragmented", cfg, spark, 3, save_to=str(tmp_path), resume=2)
    rows = lambda r: sorted(map(tuple, r.state.params.collect()))
    assert rows(straight) == rows(resumed)
    assert {p for _, _, _, p, _ in straight.timings} == {"backward", "partition", "selection", "communication", "residual"}


@pytest.mark.parametrize("net,batch", [(Perceptron((10, 8, 6, 4)), "xy"), (Recurrent(9, 5, 6), "seq"), (Recommender(6, 8, 4), "pairs")])
def test_gradients_by_finite_differences(net, batch):
    rng = np.random.default_rng(0)
    data = {
        "xy": (rng.normal(size=(7, 10)), rng.integers(0, 4, 7)),
        "seq": (rng.integers(0, 9, (4, 7)), rng.integers(0, 9, (4, 7))),
        "pairs": (rng.integers(0, 6, 12), rng.integers(0, 8, 12), rng.integers(0, 2, 12).astype(float)),
    }[batch]
    flat = net.init(1) + rng.normal(0, 0.05, net.n_g)
    _, g = net.loss(flat, data)
    for i in rng.choice(net.n_g, 30, replace=False):
        e = np.zeros(net.n_g)
        e[i] = 1e-5
        assert (net.loss(flat + e, data)[0] - net.loss(flat - e, data)[0]) / 2e-5 == pytest.approx(g[i], abs=1e-7)


def test_reported_behaviour_on_language_identification(spark):
    """16 workers: global top-k builds up and has the least error, the other
    two hold the set density at a similar error."""
    rows = experiments.compare(spark, "/root/testdata/sf0.01", "langid", 8)
    got = {(r["run"], r["metric"]): r for r in experiments.summary(rows, 4).collect()}
    density = lambda run: got[run, "density"]["late_mean"]
    assert density("global_topk") > 3 * 0.01
    assert density("cyclic_topk") == pytest.approx(0.01, rel=0.05) and density("fragmented") == pytest.approx(0.01, rel=0.1)
    error = lambda run: got[run, "error"]["late_mean"]
    assert error("dense") == 0 and error("global_topk") < 0.8 * error("cyclic_topk")
    assert error("fragmented") == pytest.approx(error("cyclic_topk"), rel=0.5)
    assert got["fragmented", "kappa"]["late_mean"] < got["global_topk", "kappa"]["late_mean"]
    assert got["fragmented", "cost"]["most"] < got["global_topk", "cost"]["least"] / 16


def test_cost_falls_with_workers():
    rng = np.random.default_rng(1)
    net = Perceptron((64, 64, 64, 10))
    scale = np.concatenate([np.full(s, 2.0**-i) for i, (_, s) in enumerate(net.sizes)])
    whole = measures.global_cost(90, net.n_g)
    speed = []
    for n in (2, 4, 8, 16):
        cfg = RunConfig(n_workers=n, k=90)
        acc = rng.normal(size=(n, net.n_g)) * scale
        speed.append(whole / simulate.choose("fragmented", acc, simulate.fragments([s for _, s in net.sizes], n), 90, 0, cfg).cost)
    assert all(f > n for f, n in zip(speed, (2, 4, 8, 16), strict=True)) and speed == sorted(speed)


def test_stream_equals_batch_and_replay_is_skipped(spark, sf, tmp_path):
    events = spark.read.parquet(f"{sf}/events.parquet").select(*[F.col(f.name).cast(f.dataType) for f in loop.EVENTS])
    for i in range(3):
        events.where((F.col("event_id") >= 334 * i) & (F.col("event_id") < 334 * (i + 1))).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    cfg = RunConfig(n_workers=2, density=0.05, lr=2.0**-12)
    online = loop.OnlineTrainer(str(tmp_path / "online"), cfg)
    loop.train_stream(loop.read_events(spark, str(tmp_path / "in")), online, str(tmp_path / "ckpt")).awaitTermination()
    batch = loop.OnlineTrainer(str(tmp_path / "batch"), cfg)
    for t in range(3):
        part = events.where((F.col("event_id") >= 334 * t) & (F.col("event_id") < 334 * (t + 1)))
        batch(part, t)
    rows = lambda o: {r.param_idx: round(r.value, 9) for r in sources.read_state(spark, f"{o.path}/params", 3).collect()}
    assert rows(online) == rows(batch)
    before = rows(online)
    online(events, 0)
    assert rows(online) == before
    assert loop.fresh(loop.read_events(spark, str(tmp_path / "in"))).isStreaming
    assert loop.clicks_to_purchases(events).where("bought < clicked").count() == 0


def test_sql_functions_and_views(spark):
    functions.register(spark)
    cfg, model, acc = queries.example(spark)
    functions.sqlapi.iteration_views(spark, model.manifest, acc.drop("frag_id"), cfg, 3)
    assert spark.sql("select count(*) from picks").first()[0] == 8
    assert sorted(map(tuple, spark.sql("select * from split_layer(5, 10, 3, 20)").collect())) == [(0, 5, 4), (1, 9, 3), (2, 12, 3)]
    assert len(spark.sql("select * from pack_bins(array(0,1,2), array(5d, 3d, 3d), 2)").collect()) == 3
    blocks = sources.tables.block(acc.drop("frag_id"), 8)
    from gradsift.functions.udfs import block_norm, block_norm_expr

    assert all(abs(a - b) < 1e-6 for a, b in blocks.select(block_norm("vals"), block_norm_expr(F.col("vals"))).collect())
    assert sources.tables.unblock(blocks).count() == 40


def test_dump_formats_round_trip(spark, tmp_path):
    acc = queries.example(spark)[2].drop("frag_id")
    for fmt in ("parquet", "orc", "csv", "json"):
        acc.write.format(fmt).save(str(tmp_path / fmt))
        assert sources.read_gradients(spark, str(tmp_path / fmt), fmt).subtract(acc).count() == 0
    rows = sources.synthetic_gradients(spark, fragment.build_manifest(spark, [("a", 50), ("b", 50)]), 3)
    assert rows.count() == 300


def test_plan_of_the_selection(spark, sf):
    """No Python in the default path; the bins are broadcast."""
    work = Additive.load(spark, sf, 4)
    cfg = RunConfig(n_workers=4, density=0.1)
    model = Model.of(work.manifest(spark), cfg)
    picks = Fragmented(cfg).select(fragment.tag(work.first_gradients(), model.fragments), model, 0).picks
    plan = picks._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan and "Python" not in plan and "Arrow" not in plan and "CartesianProduct" not in plan


def test_timing_measures(spark):
    rows = [(s, i, w, "selection", float(w + i)) for s in range(2) for i in range(3) for w in range(2)]
    t = spark.createDataFrame(rows, "seed int, iteration int, worker int, phase string, ms double")
    assert measures.time_breakdown(t).first()["ms"] == 2.0
    assert measures.overhead_share(t).first()["share"] == 0.0
    assert measures.wall_speedup(spark.createDataFrame([(1, 8.0), (4, 2.0)], "n int, ms double")).where("n = 4").first()["speedup"] == 4.0


def test_training_measures(spark):
    m = spark.createDataFrame([("a", 0, 0.2), ("a", 1, 0.6), ("a", 2, 0.5), ("dense", 0, 0.3), ("dense", 1, 0.6), ("dense", 2, 0.7)], "run string, epoch int, value double")
    assert [r["best"] for r in measures.best_so_far(m).where("run = 'a'").orderBy("epoch").collect()] == [0.2, 0.6, 0.6]
    assert measures.epochs_to(m, 0.7, 0.11).where("run = 'a'").first()["epoch"] == 1
    assert measures.relative_to_dense(m).where("run = 'a' and epoch = 1").first()["gap"] == 0
    p = spark.createDataFrame([(0, 1, 5), (1, 1, 5), (1, 2, 9)], "iteration int, frag_id int, param_idx long")
    assert tuple(measures.staleness(p, 10, 2).first()) == (1.0, 1, 8)


def test_entry_without_the_corpus_folders(tmp_path):
    """Queries and SQL of the rest work when the corpus operators are gone."""
    root = pathlib.Path(__spark_entry__.__file__).parent
    for left_over in ("", "gradsift/llm/__pycache__"):
        copy = tmp_path / f"copy{len(left_over)}"
        shutil.copytree(root, copy, ignore=shutil.ignore_patterns("llm", ".git", "__pycache__", ".pytest_cache", ".hypothesis"))
        if left_over:
            (copy / left_over).mkdir(parents=True)
        code = "import __spark_entry__ as e; q, o = e.queries(), e.oracle_sql(); assert 'flagship' in q and set(o) <= set(q); assert not [n for n in q if n.startswith('op') or n == 'pipeline']"
        subprocess.run([sys.executable, "-c", code], cwd=copy, check=True, timeout=120, env={**os.environ, "PYTHONPATH": str(copy)})
