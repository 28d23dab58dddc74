"""Base rates that the nets are read against: popularity and bigram counts."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from gradsift.plans import measures
from gradsift.sources import load

#: Candidates drawn for a user until NEGATIVES remain, by a fixed stride.
DRAWS, NEGATIVES = 150, 99
STRIDE_USER, STRIDE_DRAW = 7919, 104729
SMOOTHING = 0.1


def purchases(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """(user, item) pairs of training and held-out; held out is the lowest
    item of each user's last order, whose other items are dropped."""
    orders = load(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").alias("user"), "o_orderdate")
    lines = load(spark, sf_dir, "lineitem").select("l_orderkey", F.col("l_partkey").alias("item"))
    last = orders.groupBy("user").agg(F.max(F.struct("o_orderdate", "l_orderkey"))["l_orderkey"].alias("last"))
    rows = lines.join(orders, "l_orderkey").join(last, "user")
    train = rows.where("l_orderkey <> last").select("user", "item").distinct()
    held = rows.where("l_orderkey = last").groupBy("user").agg(F.min("item").alias("item"))
    return train, held


def candidates(train: DataFrame, held: DataFrame, n_items: int) -> DataFrame:
    """(user, item, held_out): the held-out item and NEGATIVES others that
    the user has not bought."""
    draw = F.explode(F.sequence(F.lit(0), F.lit(DRAWS - 1))).alias("draw")
    drawn = held.select("user", F.col("item").alias("own"), draw).withColumn("item", F.pmod(F.col("user") * STRIDE_USER + F.col("draw") * STRIDE_DRAW, F.lit(n_items)))
    fresh = drawn.where("item <> own").join(train, ["user", "item"], "left_anti")
    first = fresh.groupBy("user", "item").agg(F.min("draw").alias("draw"))
    order = F.row_number().over(Window.partitionBy("user").orderBy("draw"))
    negatives = first.withColumn("at", order).where(F.col("at") <= NEGATIVES).select("user", "item", F.lit(False).alias("held_out"))
    return negatives.unionByName(held.select("user", "item", F.lit(True).alias("held_out")))


def popularity_hits(spark: SparkSession, sf_dir: str) -> DataFrame:
    train, held = purchases(spark, sf_dir)
    popular = train.groupBy("item").agg(F.count("*").alias("score"))
    scores = candidates(train, held, load(spark, sf_dir, "part").count()).join(popular, "item", "left")
    got = measures.hit_rate(scores.withColumn("score", F.coalesce("score", F.lit(0))))
    return got.select(F.round("hit_rate", 6).alias("hit_rate"))


def bigrams(docs: DataFrame) -> DataFrame:
    """(a, b, n) counts of neighbouring lower-cased characters."""
    c = F.split(F.lower("text"), "")
    pairs = docs.select(c.alias("c")).where(F.size("c") > 1).select(F.inline(F.arrays_zip(F.slice("c", 1, F.size("c") - 1).alias("a"), F.slice("c", 2, F.size("c") - 1).alias("b"))))
    return pairs.groupBy("a", "b").agg(F.count("*").alias("n"))


def bigram_base(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Held-out perplexity of smoothed character bigram counts."""
    docs = load(spark, sf_dir, "documents").select("doc_id", "text")
    seen = bigrams(docs.where("doc_id % 5 <> 4"))
    held = bigrams(docs.where("doc_id % 5 = 4")).withColumnRenamed("n", "times")
    first = seen.groupBy("a").agg(F.sum("n").alias("na"))
    size = seen.select("b").distinct().agg((F.count("*") + 1).alias("v"))
    rows = held.join(F.broadcast(seen), ["a", "b"], "left").join(F.broadcast(first), "a", "left").join(F.broadcast(size), how="cross")
    p = (F.coalesce("n", F.lit(0)) + SMOOTHING) / (F.coalesce("na", F.lit(0)) + SMOOTHING * F.col("v"))
    nll = rows.select((-F.log(p) * F.col("times")).alias("nll"), F.col("times").alias("n"))
    return measures.perplexity(nll).select(F.round("perplexity", 4).alias("perplexity"))
