"""Vectorised functions over array blocks, aggregates, table functions.

Built-in expressions are the default path everywhere; each function here has
a built-in twin that it is tested against.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf


def _of(**fields: T.DataType) -> T.StructType:
    return T.StructType([T.StructField(n, t) for n, t in fields.items()])


@pandas_udf(T.DoubleType())
def block_norm(vals: pd.Series) -> pd.Series:
    """L2 norm of every array."""
    return vals.map(lambda v: float(np.sqrt(np.sum(np.square(np.asarray(v, float))))))


@pandas_udf(T.ArrayType(T.IntegerType()))
def block_topk(vals: pd.Series, k: pd.Series) -> pd.Series:
    """Positions of the k largest magnitudes of every array, largest first,
    ties by position."""
    return pd.Series([np.argsort(-np.abs(np.asarray(v, float)), kind="stable")[: int(n)].astype(np.int32) for v, n in zip(vals, k, strict=True)])


def block_norm_expr(vals: Column) -> Column:
    """The built-in twin of block_norm."""
    return F.sqrt(F.aggregate(vals, F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double")))


@pandas_udf(T.DoubleType())
def l2_norm(v: pd.Series) -> float:
    """Aggregate: L2 norm of a column."""
    return float(np.sqrt((v.astype(float) ** 2).sum()))


@udtf(returnType=_of(bin=T.IntegerType(), frag_id=T.IntegerType(), pack_order=T.IntegerType()))
class PackBins:
    """TABLE(pack_bins(ids, costs, n)): the greedy packing of one array pair."""

    def eval(self, ids: list, costs: list, n: int) -> Iterator[tuple]:
        heap = [(0, b) for b in range(n)]
        order = sorted(range(len(ids)), key=lambda i: (-round(costs[i] * 1e6), ids[i]))
        for at, i in enumerate(order):
            load, b = heapq.heappop(heap)
            heapq.heappush(heap, (load + round(costs[i] * 1e6), b))
            yield b, ids[i], at


@udtf(returnType=_of(piece=T.IntegerType(), start=T.LongType(), size=T.LongType()))
class SplitLayer:
    """TABLE(split_layer(start, size, n, n_g)): the fragments of one layer."""

    def eval(self, start: int, size: int, n: int, n_g: int) -> Iterator[tuple]:
        parts = n if size * n > n_g else 1
        for piece in range(parts):
            own = size // parts + (piece < size % parts)
            if own:
                yield piece, start + piece * (size // parts) + min(piece, size % parts), own
