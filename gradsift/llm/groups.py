"""Distributed union-find: connected components by star contraction.

Alternates two steps on the edge table until it stops changing: every vertex
hands its larger neighbours to the smallest vertex that it sees (large star),
then its smaller ones and itself (small star). Both need only a minimum per
vertex, which is pre-aggregated, and a join that Spark can split where one
vertex has a great share of the edges. What is left is a star for each
component. Each round is written to the shared folder, and the round before
is deleted. The rounds grow with the logarithm of the longest chain; should
MOST_ROUNDS not settle them, an error is raised rather than a part returned.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gradsift.llm.shared import discard, written

MOST_ROUNDS = 60


def _pairs(edges: DataFrame) -> DataFrame:
    return edges.where(F.col("u") != F.col("v")).distinct()


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.select("u", "v").unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
    return _pairs(both.where(F.col("v") > F.col("u")).join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")))


def _small_star(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    least = down.groupBy("u").agg(F.min("v").alias("m"))
    moved = down.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return _pairs(moved.unionByName(least.select("u", F.col("m").alias("v"))))


def _digest(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())


def components(edges: DataFrame) -> DataFrame:
    """(vertex, root) of every vertex with an edge; root is the smallest
    vertex of the component. edges: columns u and v, both bigint."""
    now = written(_pairs(edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))), "edges")
    seen = _digest(now)
    for _ in range(MOST_ROUNDS):
        before, now = now, written(_small_star(_large_star(now)), "edges")
        discard(before)
        got = _digest(now)
        if got == seen:
            break
        seen = got
    else:
        raise RuntimeError(f"components have not settled after {MOST_ROUNDS} rounds")
    roots = now.groupBy("u").agg(F.min("v").alias("root"))
    return roots.select(F.col("u").alias("vertex"), "root").unionByName(roots.select(F.col("root").alias("vertex"), "root").distinct())
