"""Schemas of the tables that operators exchange."""

from pyspark.sql.types import ArrayType, BooleanType, DoubleType, FloatType, IntegerType, LongType, StringType, StructField, StructType


def _of(**fields) -> StructType:
    return StructType([StructField(n, t) for n, t in fields.items()])


I, L, D, S = IntegerType(), LongType(), DoubleType(), StringType()

MANIFEST = _of(layer_id=I, layer_name=S, start=L, size=L)
FRAGMENTS = _of(frag_id=I, layer_id=I, piece=I, start=L, size=L)
PARAMS = _of(param_idx=L, value=D)
GRADS = _of(worker=I, param_idx=L, v=D)
BLOCKS = _of(worker=I, block=I, base=L, vals=ArrayType(FloatType()))
QUOTAS = _of(worker=I, frag_id=I, size=L, norm=D, priority=I, quota=L)
BINS = _of(bin=I, frag_id=I, cost=D, pack_order=I)
OWNER = _of(worker=I, frag_id=I)
PICKS = _of(worker=I, frag_id=I, param_idx=L, v=D, rank=I)
METRICS = _of(run=S, sparsifier=S, n=I, density=D, iteration=I, metric=S, value=D)
TIMINGS = _of(seed=I, iteration=I, worker=I, phase=S, ms=D)
CANDIDATES = _of(user=L, item=L, score=D, held_out=BooleanType())
