"""Additive model of lineitem quantities: the exact carrier of all selectors.

Quantity is predicted by a bias and an effect each of part, customer,
supplier and ship month. The gradient of half the squared loss with respect
to one effect is the sum of the residuals of its rows, so at the start model
(bias 25) it is an exact integer, and stays a multiple of a power of two under
such rates. One row gives five terms and one grouped sum, combined map-side.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gradsift import schemas
from gradsift.operators.fragment import build_manifest
from gradsift.sources import load

BIAS = 25.0
FIRST_YEAR = 1995
FAMILIES = ("part", "customer", "supplier", "month", "bias")


@dataclass(frozen=True)
class Additive:
    rows: DataFrame
    sizes: tuple[tuple[str, int], ...]
    n_workers: int

    @classmethod
    def load(cls, spark: SparkSession, sf_dir: str, n_workers: int) -> Additive:
        month = (F.year("l_shipdate") - FIRST_YEAR) * 12 + F.month("l_shipdate") - 1
        items = load(spark, sf_dir, "lineitem").select("l_orderkey", F.col("l_partkey").alias("part"), F.col("l_suppkey").alias("supplier"), month.cast("long").alias("month"), F.col("l_quantity").alias("quantity"))
        orders = load(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").alias("customer"))
        rows = items.join(orders, "l_orderkey").select(F.pmod("l_orderkey", F.lit(n_workers)).cast("int").alias("worker"), "part", "customer", "supplier", "month", F.lit(0).cast("long").alias("bias"), "quantity")
        months = items.agg((F.max("month") + 1).alias("n")).first()["n"]
        count = {name: load(spark, sf_dir, name).count() for name in FAMILIES[:3]} | {"month": months, "bias": 1}
        return cls(rows, tuple((name, count[name]) for name in FAMILIES), n_workers)

    @property
    def starts(self) -> dict[str, int]:
        out, at = {}, 0
        for name, size in self.sizes:
            out[name] = at
            at += size
        return out

    @property
    def n_g(self) -> int:
        return sum(size for _, size in self.sizes)

    def manifest(self, spark: SparkSession) -> DataFrame:
        return build_manifest(spark, list(self.sizes))

    def init_params(self, spark: SparkSession) -> DataFrame:
        at = self.starts["bias"]
        return spark.range(self.n_g).select(F.col("id").alias("param_idx"), F.when(F.col("id") == at, F.lit(BIAS)).otherwise(F.lit(0.0)).alias("value"))

    def _terms(self, rows: DataFrame, residual) -> DataFrame:
        cells = F.array(*[F.struct((F.col(name) + start).alias("param_idx"), residual.alias("r")) for name, start in self.starts.items()])
        return rows.select("worker", F.inline(cells))

    def first_gradients(self) -> DataFrame:
        """(worker, param_idx, v bigint) at the start model."""
        r = (F.lit(BIAS) - F.col("quantity")).cast("long")
        return self._terms(self.rows, r).groupBy("worker", "param_idx").agg(F.sum("r").alias("v"))

    def predicted(self, params: DataFrame) -> DataFrame:
        """Rows with their prediction: each family is joined by itself, so no
        join needs the whole vector, and a small family is broadcast."""
        out = self.rows.withColumn("prediction", F.lit(0.0))
        for (name, size), start in zip(self.sizes, self.starts.values(), strict=True):
            own = params.where((F.col("param_idx") >= start) & (F.col("param_idx") < start + size)).select((F.col("param_idx") - start).alias(name), F.col("value").alias("_value"))
            own = F.broadcast(own) if size <= 1_000_000 else own
            out = out.join(own, name).withColumn("prediction", F.col("prediction") + F.col("_value")).drop("_value")
        return out

    def gradients(self, params: DataFrame, t: int = 0) -> DataFrame:
        rows = self.predicted(params)
        return self._terms(rows, F.col("prediction") - F.col("quantity")).groupBy("worker", "param_idx").agg(F.sum("r").alias("v"))

    def evaluate(self, params: DataFrame) -> DataFrame:
        e = F.col("prediction") - F.col("quantity")
        return self.predicted(params).agg(F.sqrt(F.avg(e * e)).alias("value")).select(F.lit("rmse").alias("metric"), "value")


def empty_error(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([], schemas.GRADS)
