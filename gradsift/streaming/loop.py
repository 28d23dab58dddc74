"""The loop in online form: a micro-batch is an iteration.

Events give the gradient of an additive model of their value (user, type,
hour of day, and k of props). Every batch runs one iteration of accumulation,
selection, exchange and update; state is a versioned table, so a batch that
is played again after a failure finds its version and is skipped.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming import StreamingQuery

from gradsift.config import RunConfig
from gradsift.operators import exchange, feedback, fragment
from gradsift.operators.sparsifiers import SPARSIFIERS, Model
from gradsift.sources import commit, discard, read_state, write_state

EVENTS = T.StructType(
    [T.StructField("event_id", T.LongType()), T.StructField("ts", T.TimestampType()), T.StructField("user_id", T.LongType()), T.StructField("event_type", T.StringType()), T.StructField("value", T.DoubleType()), T.StructField("props", T.StringType())]
)
TYPES = ("click", "error", "login", "purchase", "view")
#: Slots of each layer; ids are taken modulo these.
LAYERS = (("user", 2048), ("type", len(TYPES) + 1), ("hour", 24), ("k", 128), ("bias", 1))


def terms(events: DataFrame, n_workers: int) -> DataFrame:
    """(worker, value, idx array): the parameters that predict each event."""
    starts, at = {}, 0
    for name, size in LAYERS:
        starts[name], at = at, at + size
    kind = F.coalesce(F.nullif(F.array_position(F.array(*[F.lit(t) for t in TYPES]), F.col("event_type")), F.lit(0)), F.lit(len(TYPES) + 1)) - 1
    k = F.coalesce(F.from_json("props", "k INT")["k"], F.lit(0))
    own = {"user": F.pmod("user_id", F.lit(2048)), "type": kind, "hour": F.hour("ts"), "k": F.pmod(k, F.lit(128)), "bias": F.lit(0)}
    idx = F.array(*[(own[name] + starts[name]).cast("long") for name, _ in LAYERS])
    return events.select(F.pmod("event_id", F.lit(n_workers)).cast("int").alias("worker"), "event_id", "value", idx.alias("idx"))


def gradients(events: DataFrame, params: DataFrame, n_workers: int) -> DataFrame:
    rows = terms(events, n_workers)
    each = rows.select("worker", "event_id", "value", F.explode("idx").alias("param_idx"))
    predicted = each.join(F.broadcast(params), "param_idx").groupBy("worker", "event_id").agg((F.sum("value_p") - F.first("value")).alias("r"))
    flat = rows.select("worker", "event_id", F.explode("idx").alias("param_idx"))
    return flat.join(predicted, ["worker", "event_id"]).groupBy("worker", "param_idx").agg(F.sum("r").alias("v"))


@dataclass
class OnlineTrainer:
    """foreachBatch sink with versioned state under `path`."""

    path: str
    cfg: RunConfig
    name: str = "fragmented"

    def model(self, spark: SparkSession) -> Model:
        return Model.of(fragment.build_manifest(spark, list(LAYERS)), self.cfg)

    def _has(self, spark: SparkSession, t: int) -> bool:
        jvm = spark._jvm
        p = jvm.org.apache.hadoop.fs.Path(f"{self.path}/params/iteration={t}/_SUCCESS")
        return p.getFileSystem(spark._jsc.hadoopConfiguration()).exists(p)

    def start_state(self, spark: SparkSession) -> None:
        if not self._has(spark, 0):
            n_g = sum(size for _, size in LAYERS)
            write_state(spark.createDataFrame([], "worker int, param_idx long, v double"), f"{self.path}/error", 0)
            write_state(spark.range(n_g).select(F.col("id").alias("param_idx"), F.lit(0.0).alias("value")), f"{self.path}/params", 0)

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        spark, t = batch.sparkSession, batch_id
        self.start_state(spark)
        if self._has(spark, t + 1):
            return
        cfg, model = self.cfg, self.model(spark)
        params, error = read_state(spark, f"{self.path}/params", t), read_state(spark, f"{self.path}/error", t)
        grads = gradients(batch, params.withColumnRenamed("value", "value_p"), cfg.n_workers)
        acc = commit(model.tag(feedback.accumulate(error, grads, cfg.lr_at(t), cfg.lr_mode)), "acc")
        chosen = SPARSIFIERS[self.name](cfg).select(acc, model, t)
        indices = None if chosen.picks is None else exchange.union_indices(chosen.picks, chosen.disjoint)
        mean = exchange.average(acc, indices, cfg.n_workers, chosen.at_most)
        # the error first: a batch counts as done once its params are there
        write_state(feedback.residual(acc, indices), f"{self.path}/error", t + 1)
        write_state(exchange.apply_update(params, mean, cfg.lr_at(t), cfg.lr_mode), f"{self.path}/params", t + 1)
        discard(acc, chosen.quotas)


def read_events(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def fresh(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Events once each, behind a watermark. A late gradient before it still
    enters: it is part of the next error."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def train_stream(events: DataFrame, trainer: OnlineTrainer, checkpoint: str) -> StreamingQuery:
    return events.writeStream.foreachBatch(trainer).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def clicks_to_purchases(events: DataFrame, within: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """Purchases that follow a click of the same user in time: an interval
    join of the stream with itself."""
    clicks = events.where("event_type = 'click'").select(F.col("user_id").alias("u"), F.col("ts").alias("clicked")).withWatermark("clicked", late)
    bought = events.where("event_type = 'purchase'").select("user_id", F.col("ts").alias("bought"), "value").withWatermark("bought", late)
    return bought.join(clicks, F.expr(f"u = user_id and bought >= clicked and bought <= clicked + interval {within}")).select("user_id", "clicked", "bought", "value")
