"""Net workloads on whole tables: rows dealt to workers and batches.

A set is made by one pass over whole texts, or by joins, and written once,
in order of its batches, with a folder for each span of them: a set has as
many batches as its rows allow, but no more than FOLDERS folders. An iteration
reads the pages of its batch and little else. Gradients are computed by worker where the rows are: the batch of one
worker is the group of one task. The model's parameters travel to the tasks;
in data-parallel training every worker holds a replica, so they fit one. The
factors of users and items, as many as the tables' rows, do not: they stay in
the table of parameters, and a task gets those that its rows name.
"""

from __future__ import annotations

import json
import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.accumulators import Accumulator, AccumulatorParam
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gradsift import schemas
from gradsift.operators import shards
from gradsift.operators.fragment import build_manifest
from gradsift.sources import commit, discard, load
from gradsift.workloads.base_rates import candidates, purchases
from gradsift.workloads.nets import Net, Perceptron, Recommender, Recurrent, drawn

BUCKETS = 256
STEPS = 32
#: Windows that are laid at once.
WINDOWS = 1 << 14
NEGATIVES = 4
#: Folders of a written set.
FOLDERS = 32
#: A replica larger than this does not belong into one task.
MOST_PARAMS = 50_000_000
#: Held-out pairs are judged in tiles of so many users and items at most, but
#: in TILES of them at least.
TILE_USERS, TILE_ITEMS, TILES = 1 << 17, 1 << 18, 4
#: Pairs of a tile that are judged at once.
PAIRS = 1 << 16
UNNUMBERED = "a pair names a user or item that the tables do not number"

Arrays = tuple[np.ndarray, ...]


class _Joined(AccumulatorParam):
    def zero(self, value: list) -> list:
        return []

    def addInPlace(self, a: list, b: list) -> list:
        a += b
        return a


def timed_loss(clock: Accumulator | None, t: int, worker: int, net: Net, flat: np.ndarray, batch: Arrays) -> np.ndarray:
    """The gradient of a worker's batch in iteration t."""
    laps = [time.perf_counter()]
    mark = lambda: laps.append(time.perf_counter())
    _, g = net.loss(flat, batch, mark)
    mark()
    if clock is not None:
        clock.add([(t, worker, phase, 1000 * (b - a)) for phase, a, b in zip(("forward", "backward"), laps[:-1], laps[1:], strict=True)])
    return g


def _matrix(table: pa.Table, name: str) -> np.ndarray:
    column = table.column(name).combine_chunks()
    return column.flatten().to_numpy(zero_copy_only=False).reshape(len(column), -1)


def _vector(table: pa.Table, name: str) -> np.ndarray:
    return table.column(name).to_numpy()


def labelled(table: pa.Table) -> Arrays:
    return _matrix(table, "x").astype(np.float64), _vector(table, "y")


def symbols(table: pa.Table) -> Arrays:
    """Windows of STEPS + 1 symbols that are packed."""
    packed = table.column("s").to_pylist()
    width = len(packed[0]) // (STEPS + 1) if packed else 1
    s = np.frombuffer(b"".join(packed), f"<u{width}").astype(np.int32).reshape(-1, STEPS + 1)
    return s[:, :-1], s[:, 1:]


def pairs(table: pa.Table) -> Arrays:
    return _vector(table, "user"), _vector(table, "item"), _vector(table, "y")


def right_classes(net: Net, flat: np.ndarray, table: pa.Table) -> tuple[float, int]:
    x, y = labelled(table)
    return float((net.predict(flat, x) == y).sum()), len(y)


def symbol_loss(net: Net, flat: np.ndarray, table: pa.Table) -> tuple[float, int]:
    s, y = symbols(table)
    return net.nll(flat, s, y) * y.size, y.size


def hits(net: Net, flat: np.ndarray, table: pa.Table) -> tuple[float, int]:
    """Held-out items, the first of each list, among the ten best; ties count
    against them."""
    found = 0
    for user, items in zip(table.column("user").to_pylist(), table.column("items").to_pylist(), strict=True):
        score = net.score(flat, np.full(len(items), user), np.array(items))
        found += int((score[1:] >= score[0]).sum() < 10)
    return float(found), table.num_rows


@dataclass(frozen=True)
class NetWorkload:
    """A net, its training rows (key, worker, batch and the net's columns) and
    its held-out rows. clock, if given, collects (iteration, worker, phase,
    ms) of the forward and backward passes."""

    net: Net
    train: DataFrame
    test: DataFrame
    metric: str
    unpack: Callable[[pa.Table], Arrays]
    judge: Callable[[Net, np.ndarray, pa.Table], tuple[float, int]]
    n_workers: int = 1
    batches: int = 1
    seed: int = 42
    clock: Accumulator | None = field(default=None, compare=False)

    def dealt(self, n_workers: int, local_batch: int, seed: int = 42) -> NetWorkload:
        """The set with its rows dealt to workers, and to batches of about
        local_batch rows a worker."""
        rows = self.train.count()
        batches = max(1, round(rows / (n_workers * local_batch)))
        train = shards.assign(self.train.drop("worker", "batch", "span"), "key", n_workers)
        train = shards.numbered(train, "key", batches, seed)
        train = train.withColumn("span", shards.span_of(F.col("batch"), batches, FOLDERS)).sortWithinPartitions("span", "batch")
        return replace(self, train=commit(train, "train", "span", ("key", "s")), n_workers=n_workers, batches=batches, seed=seed)

    def timed(self, spark: SparkSession) -> NetWorkload:
        return replace(self, clock=spark.sparkContext.accumulator([], _Joined()))

    def manifest(self, spark: SparkSession) -> DataFrame:
        return build_manifest(spark, self.net.sizes)

    def init_params(self, spark: SparkSession) -> DataFrame:
        """net.init(seed), drawn where it is written."""
        by_value()

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for p in batch.to_pylist():
                    yield pa.RecordBatch.from_pydict({"param_idx": np.arange(p["start"], p["start"] + p["size"]), "value": drawn(p["size"], p["scale"], json.loads(p["state"]))})

        pieces = [(start, size, scale, json.dumps(state)) for start, size, scale, state in self.net.pieces(self.seed)]
        return spark.createDataFrame(pieces, "start long, size long, scale double, state string").mapInArrow(run, schemas.PARAMS)

    def replica(self, params: DataFrame) -> np.ndarray:
        """The parameters as one array."""
        if self.net.n_g > MOST_PARAMS:
            raise ValueError("the model does not fit a worker")
        rows = params.toArrow()
        flat = np.zeros(self.net.n_g)
        flat[rows.column("param_idx").to_numpy()] = rows.column("value").to_numpy()
        return flat

    def batch(self, t: int) -> DataFrame:
        """The rows of batch t."""
        return shards.batch_of(self.train.where(F.col("span") == shards.span_of(F.lit(t % self.batches), self.batches, FOLDERS)), t, self.batches)

    def gradients(self, params: DataFrame, t: int) -> DataFrame:
        """(worker, param_idx, v) of batch t, without zeros."""
        by_value()
        flat, net, unpack, clock = self.replica(params), self.net, self.unpack, self.clock

        def run(key: tuple, table: pa.Table) -> pa.Table:
            worker = key[0].as_py()
            g = timed_loss(clock, t, worker, net, flat, unpack(table.sort_by("key")))
            at = np.flatnonzero(g)
            return pa.table({"worker": np.full(len(at), worker, np.int32), "param_idx": at, "v": g[at]})

        return self.batch(t).groupBy("worker").applyInArrow(run, schemas.GRADS)

    def evaluate(self, params: DataFrame) -> DataFrame:
        """(metric, value) over all held-out rows."""
        by_value()
        flat, net, judge = self.replica(params), self.net, self.judge

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                total, n = judge(net, flat, pa.Table.from_batches([batch]))
                yield pa.RecordBatch.from_pydict({"total": [total], "n": [n]}, schema=pa.schema([("total", pa.float64()), ("n", pa.int64())]))

        sums = self.test.mapInArrow(run, "total double, n long").agg((F.sum("total") / F.sum("n")).alias("mean"))
        value = F.exp("mean") if self.metric == "perplexity" else F.col("mean")
        return sums.select(F.lit(self.metric).alias("metric"), value.alias("value"))


def _own_net(mine: np.ndarray, its: np.ndarray, rest: np.ndarray) -> tuple[Recommender, np.ndarray]:
    """A recommender of some users and items, and its parameters. mine, its:
    a row of both layers for each of them."""
    w = mine.shape[1] // 2
    parts = [mine[:, :w], its[:, :w], mine[:, w:], its[:, w:], rest]
    return Recommender(len(mine), len(its), w), np.concatenate([p.reshape(-1) for p in parts])


@dataclass(frozen=True)
class FactorWorkload(NetWorkload):
    """Recommendation. Users and items are entities, users first; each layer of
    factors is a run of WIDTH values an entity, and what follows the factors is
    small. No task and no driver holds all factors: gradients are computed on
    the entities of a batch, and held-out pairs are judged in tiles of users
    and items."""

    users: int = 0
    items: int = 0

    @property
    def n_factors(self) -> int:
        return 2 * (self.users + self.items) * Recommender.WIDTH

    def factors(self, params: DataFrame) -> DataFrame:
        """(entity, v): the values of an entity in both layers."""
        w, both, at = Recommender.WIDTH, self.users + self.items, F.col("param_idx")
        run = F.floor(at / w).cast("long")
        place = F.floor(run / both).cast("int") * w + (at % w).cast("int")
        rows = params.where(at < self.n_factors).select((run % both).alias("entity"), place.alias("place"), "value").repartition("entity")
        return rows.groupBy("entity").agg(F.array(*[F.max(F.when(F.col("place") == j, F.col("value"))) for j in range(2 * w)]).alias("v"))

    def rest(self, params: DataFrame) -> np.ndarray:
        """What follows the factors; its length is the same for all tables."""
        rows = params.where(F.col("param_idx") >= self.n_factors).toArrow().sort_by("param_idx")
        return _vector(rows, "value")

    def gradients(self, params: DataFrame, t: int) -> DataFrame:
        by_value()
        rest, unpack, clock, users, both, w = self.rest(params), self.unpack, self.clock, self.users, self.users + self.items, Recommender.WIDTH
        n_factors, n_g = self.n_factors, self.net.n_g

        def run(key: tuple, table: pa.Table, known: pa.Table) -> pa.Table:
            worker, known = key[0].as_py(), known.sort_by("entity")
            u, i, y = unpack(table.sort_by("key"))
            named, e, v = np.unique(np.concatenate([u, i + users])), _vector(known, "entity"), _matrix(known, "v")
            if u.max() >= users or i.min() < 0 or not np.array_equal(named, e):
                raise ValueError(UNNUMBERED)
            cut = int(np.searchsorted(e, users))
            net, flat = _own_net(v[:cut], v[cut:], rest)
            g = timed_loss(clock, t, worker, net, flat, (np.searchsorted(e, u), np.searchsorted(e, i + users) - cut, y))
            first = (e[:, None] * w + np.arange(w)).reshape(-1)
            places, at = np.concatenate([first, first + both * w, np.arange(n_factors, n_g)]), np.flatnonzero(g)
            return pa.table({"worker": np.full(len(at), worker, np.int32), "param_idx": places[at], "v": g[at]})

        rows = self.batch(t)
        named = rows.select(F.col("worker").alias("of"), F.explode(F.array("user", F.col("item") + users)).alias("entity")).distinct()
        known = self.factors(params).join(named, "entity").select("of", "entity", "v")
        return rows.groupBy("worker").cogroup(known.groupBy("of")).applyInArrow(run, schemas.GRADS)

    def evaluate(self, params: DataFrame) -> DataFrame:
        """Share of the users whose held-out item, the first of the list, is
        among the ten best; ties count against it. Its score goes with the
        user to the tiles, which return how many others reach it."""
        by_value()
        rest = self.rest(params)

        def own(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                table, at = pa.Table.from_batches([batch]), np.arange(batch.num_rows)
                if table.column("mine").null_count or table.column("its").null_count:
                    raise ValueError(UNNUMBERED)
                if not len(at):
                    continue
                net, flat = _own_net(_matrix(table, "mine"), _matrix(table, "its"), rest)
                yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("user", "items", "mine")), pa.array(net.score(flat, at, at))], names=["user", "items", "mine", "own"])

        def reached(key: tuple, judged: pa.Table, known: pa.Table) -> pa.Table:
            if not judged.num_rows:
                return pa.table({"user": judged.column("user"), "n": np.zeros(0, np.int64)})
            known = known.sort_by("item")
            net, flat = _own_net(_matrix(judged, "mine"), _matrix(known, "its"), rest)
            lists = judged.column("items").combine_chunks()
            counts, picked = lists.value_lengths().to_numpy(), np.searchsorted(_vector(known, "item"), lists.flatten().to_numpy())
            user, bar = np.repeat(np.arange(len(counts)), counts), _vector(judged, "own")
            n = np.zeros(len(counts), np.int64)
            for lo in range(0, len(user), PAIRS):
                u, i = user[lo : lo + PAIRS], picked[lo : lo + PAIRS]
                n += np.bincount(u[net.score(flat, u, i) >= bar[u]], minlength=len(n))
            return pa.table({"user": judged.column("user"), "n": n})

        blocks = -(-self.items // TILE_ITEMS)
        groups = max(-(-self.users // TILE_USERS), -(-TILES // blocks))
        known = self.factors(params)
        mine = known.where(F.col("entity") < self.users).select(F.col("entity").alias("user"), F.col("v").alias("mine"))
        its = known.where(F.col("entity") >= self.users).select((F.col("entity") - self.users).alias("item"), F.col("v").alias("its"))
        held = self.test.withColumn("item", F.col("items")[0]).join(its, "item", "left").join(mine, "user", "left").select("user", "items", "mine", "its")
        held = held.mapInArrow(own, "user long, items array<long>, mine array<double>, own double")
        count = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
        inside = F.filter(F.slice("items", 2, F.size("items")), lambda item: F.floor(item / TILE_ITEMS) == F.col("block"))
        judged = held.select("*", count(blocks).alias("block")).select(F.pmod("user", F.lit(groups)).cast("int").alias("group"), "block", "user", "mine", "own", inside.alias("items"))
        # a user without others in any block is judged, too
        judged = judged.where((F.size("items") > 0) | (F.col("block") == 0))
        tiles = its.select(count(groups).alias("group"), F.floor(F.col("item") / TILE_ITEMS).cast("int").alias("block"), "item", "its")
        found = judged.groupBy("group", "block").cogroup(tiles.groupBy("group", "block")).applyInArrow(reached, "user long, n long")
        hit = (F.sum("n") < 10).cast("double").alias("hit")
        return found.groupBy("user").agg(hit).agg(F.avg("hit").alias("value")).select(F.lit(self.metric).alias("metric"), "value")


def by_value() -> None:
    """Send this library's functions to the workers by value."""
    import gradsift

    cloudpickle.register_pickle_by_value(gradsift)


def _held(column: str):
    return F.col(column) % 5 == 4


def bigram_features(docs: DataFrame, buckets: int = BUCKETS) -> DataFrame:
    """(key, lang, x): hashed pairs of neighbouring lower-cased characters of
    the whole text, scaled to length 1; texts without a pair are all zero."""
    by_value()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = np.zeros((batch.num_rows, buckets), np.float32)
            for i, t in enumerate(batch.column("text").to_pylist()):
                c = np.frombuffer((t or "").lower().encode("utf-32-le"), np.uint32).astype(np.uint64)
                h = (c[:-1] * np.uint64(0x9E3779B1) + c[1:]) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(32)
                n = np.bincount((h % np.uint64(buckets)).astype(np.int64), minlength=buckets)
                out[i] = n / max(np.sqrt(float(n @ n)), 1.0)
            x = pa.ListArray.from_arrays(np.arange(0, out.size + 1, buckets, dtype=np.int32), pa.array(out.reshape(-1)))
            yield pa.RecordBatch.from_arrays([batch.column("key"), batch.column("lang"), x], names=["key", "lang", "x"])

    rows = docs.where("lang is not null").select(F.col("doc_id").alias("key"), "lang", "text")
    return rows.mapInArrow(run, "key long, lang string, x array<float>")


def langid(spark: SparkSession, sf_dir: str) -> NetWorkload:
    """Which language a document is in. The languages are listed on the
    driver; there are as many as classes of the net."""
    docs = load(spark, sf_dir, "documents")
    names = sorted(r["lang"] for r in docs.select("lang").where("lang is not null").distinct().collect())
    y = F.array_position(F.array(*[F.lit(n) for n in names]), F.col("lang")) - 1
    rows = commit(bigram_features(docs).select("key", "x", y.cast("long").alias("y")), "langid")
    return NetWorkload(Perceptron((BUCKETS, 64, 64, len(names))), rows.where(~_held("key")), rows.where(_held("key")), "accuracy", labelled, right_classes)


def vectors(spark: SparkSession, sf_dir: str) -> NetWorkload:
    """Embeddings: gradient shapes of a dense net; the labels are noise."""
    rows = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("key"), F.col("embedding").alias("x"), F.col("label").cast("long").alias("y"))
    got = rows.agg(F.max(F.size("x")).alias("width"), (F.max("y") + 1).alias("kinds")).first()
    return NetWorkload(Perceptron((got["width"], 64, 64, got["kinds"])), rows.where(~_held("key")), rows.where(_held("key")), "accuracy", labelled, right_classes)


#: Code points that there can be.
CODES = 0x110000


def _codes(text: str | None) -> np.ndarray:
    """Code points of the lower-cased text."""
    return np.frombuffer((text or "").lower().encode("utf-32-le"), np.uint32)


def alphabet(docs: DataFrame) -> list[int]:
    """Code points of the lower-cased texts: no more than there are."""
    by_value()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = np.zeros(CODES, bool)
        for batch in batches:
            for t in batch.column("text").to_pylist():
                seen[_codes(t)] = True
        yield pa.RecordBatch.from_pydict({"c": np.flatnonzero(seen)}, schema=pa.schema([("c", pa.int64())]))

    return sorted(r["c"] for r in docs.select("text").mapInArrow(run, "c long").distinct().collect())


def symbol_windows(docs: DataFrame, known: list[int], steps: int = STEPS, packed: bool = False) -> DataFrame:
    """(key, doc_id, s): windows of steps + 1 symbols of whole texts, each
    beginning with the last symbol of the one before, so that every symbol is
    predicted once; 0 is an unknown symbol, 1 stands before a text and behind
    it to the end of its last window. packed: a window is binary, its symbols
    in as few bytes each as the alphabet needs."""
    by_value()
    kind = np.min_scalar_type(len(known) + 1).newbyteorder("<") if packed else np.dtype(np.int32)

    def laid(ids: list[int], rows: list[np.ndarray]) -> pa.RecordBatch:
        n, s = [len(r) for r in rows], np.concatenate(rows)
        if packed:
            ends = np.arange(len(s) + 1, dtype=np.int32) * s[0].nbytes
            s = pa.Array.from_buffers(pa.binary(), len(s), [None, pa.py_buffer(ends), pa.py_buffer(s)])
        else:
            s = pa.ListArray.from_arrays(np.arange(0, s.size + 1, steps + 1, dtype=np.int32), pa.array(s.reshape(-1)))
        at = np.concatenate([np.arange(k) for k in n])
        return pa.RecordBatch.from_arrays([pa.array(np.repeat(np.array(ids, np.int64), n)), pa.array(at), s], names=["doc_id", "at", "s"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        symbol = np.zeros(CODES, kind)
        symbol[np.array(known, np.int64)] = np.arange(2, len(known) + 2)
        ids, rows, waiting = [], [], 0
        for batch in batches:
            for doc, t in zip(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist(), strict=True):
                c = _codes(t)
                if not len(c):
                    continue
                s = np.ones(-(-len(c) // steps) * steps + 1, kind)
                s[1 : len(c) + 1] = symbol[c]
                ids.append(doc)
                rows.append(np.lib.stride_tricks.sliding_window_view(s, steps + 1)[::steps])
                waiting += len(rows[-1])
                if waiting >= WINDOWS:
                    yield laid(ids, rows)
                    ids, rows, waiting = [], [], 0
        if rows:
            yield laid(ids, rows)

    rows = docs.where("doc_id is not null").select("doc_id", "text").mapInArrow(run, f"doc_id long, at long, s {'binary' if packed else 'array<int>'}")
    return rows.select(F.xxhash64("doc_id", "at").alias("key"), "doc_id", "s")


def charlm(spark: SparkSession, sf_dir: str, hidden: int = 64) -> NetWorkload:
    """Which character comes next. Every run goes through the held-out windows
    with little to read and much to compute, so they are spread over tasks."""
    docs = load(spark, sf_dir, "documents")
    train, test = docs.where(~_held("doc_id")), docs.where(_held("doc_id"))
    known = alphabet(train)
    windows = lambda part: symbol_windows(part, known, packed=True).select("key", "s")
    train, test = commit(windows(train), "charlm", unlike=("key", "s")), commit(windows(test).repartition("key"), "held", unlike=("key", "s"))
    return NetWorkload(Recurrent(len(known) + 2, 32, hidden), train, test, "perplexity", symbols, symbol_loss)


def recommend(spark: SparkSession, sf_dir: str) -> NetWorkload:
    """Bought pairs against drawn ones that were not bought. A user is judged
    on the candidates that it has, which can be fewer than 100 where there
    are few items."""
    train, held = purchases(spark, sf_dir)
    train = commit(train, "bought")
    users, items = load(spark, sf_dir, "customer").count(), load(spark, sf_dir, "part").count()
    draw = F.explode(F.sequence(F.lit(0), F.lit(NEGATIVES - 1))).alias("j")
    drawn = train.select("user", "item", draw).select("user", F.pmod(F.xxhash64("user", "item", "j"), F.lit(items)).alias("item"))
    drawn = drawn.distinct().join(train, ["user", "item"], "left_anti")
    rows = train.withColumn("y", F.lit(1.0)).unionByName(drawn.withColumn("y", F.lit(0.0)))
    first = F.array_sort(F.collect_list(F.struct((~F.col("held_out")).alias("other"), "item")))
    test = candidates(train, held, items).groupBy("user").agg(F.transform(first, lambda c: c["item"]).alias("items"))
    rows, test = commit(rows.select(F.xxhash64("user", "item").alias("key"), "user", "item", "y"), "pairs"), commit(test, "candidates")
    discard(train)
    return FactorWorkload(Recommender(users, items), rows, test, "hit_rate", pairs, hits, users=users, items=items)


SETS = {"langid": langid, "vectors": vectors, "charlm": charlm, "recommend": recommend}
