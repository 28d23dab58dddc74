"""Importance resampling with hashed n-gram models and Gumbel top-k.

Two generative models of hashed n-grams are counted: the raw one over all
documents, the target one over a bounded sample of the labelled good ones. A
document's log weight is the sum over its n-grams of the log ratio; adding
Gumbel noise, drawn from a hash of the id, and taking the k largest samples k
documents without replacement in proportion to their weights.

The counts are two vectors of fixed length, summed inside each task before
they meet. The k-th largest score is found by a radix search over histograms
of fixed length, so nothing is sorted. Rows with exactly that score are taken
in the order of a hash of id and text, found by the same search, so that the
sample has exactly k rows; only rows that are equal in id and text can be more
than there is room for, and then as many as there is room for are taken in the
order in which they were written.

Defined results: null and empty texts have weight 0, the log of 1; null ids
draw the noise of null; an empty table gives no rows; without labelled good
rows the ratio is 1 for all.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from gradsift.llm.domains import sample_of
from gradsift.llm.shared import written
from gradsift.llm.textkit import ALNUM_WORDS, BLANK_WORDS, annotate, chunks, mix, words_of

#: The models: word class, length of n-gram, buckets, and strength of the
#: prior (pseudo-counts in the proportions of the raw model). Words between
#: blanks tell junk, words of letters tell vocabulary.
ORDERS = (("blank", 1, 10_000, 1.0), ("alnum", 1, 10_000, 1.0), ("alnum", 2, 1 << 16, 300.0))
CLASSES = {"blank": BLANK_WORDS, "alnum": ALNUM_WORDS}
TARGET_ROWS = 20_000
FRACTION = 0.82
SEED = 17
DIGIT = 13


def ngrams(data: np.ndarray, offsets: np.ndarray, orders: tuple) -> tuple[int, np.ndarray, np.ndarray]:
    """Number of texts, and (bucket, text) of all n-grams; the buckets of the
    orders stand side by side."""
    words = {kind: words_of(data, offsets, CLASSES[kind], lower=True) for kind, *_ in orders}
    base, bucket, doc = 0, [], []
    for kind, n, size, _ in orders:
        w = words[kind]
        at, h = w.windows(n, 80 + n)
        bucket.append(base + (h % np.uint64(size)).astype(np.int64))
        doc.append(w.doc[at])
        base += size
    return len(offsets) - 1, np.concatenate(bucket), np.concatenate(doc)


def models(docs: DataFrame, labels: DataFrame, key: str, text: str, orders: tuple = ORDERS, target_rows: int = TARGET_ROWS) -> np.ndarray:
    """Log ratio of target to raw probability by bucket."""
    good = F.when((F.col("quality") == 1) & (F.col("toxic") == 0), 1)
    chosen = F.broadcast(sample_of(labels, key, good, target_rows))
    rows = docs.select(F.col(key).cast("long").alias("id"), F.col(text).alias("text")).join(chosen, "id", "left").select("text", "label")
    total = sum(size for _, _, size, _ in orders)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros((2, total), np.int64)
        for batch in batches:
            for part, data, offsets in chunks(batch, "text"):
                _, bucket, doc = ngrams(data, offsets, orders)
                counts[0] += np.bincount(bucket, minlength=total)
                good = np.array(part.column("label").is_valid())[doc]
                counts[1] += np.bincount(bucket[good], minlength=total)
        some = np.flatnonzero(counts[0])
        yield pa.RecordBatch.from_arrays([pa.array(some), pa.array(counts[0][some]), pa.array(counts[1][some])], names=["bucket", "raw", "target"])

    raw, target = np.zeros(total), np.zeros(total)
    for r in rows.mapInArrow(run, "bucket long, raw long, target long").groupBy("bucket").agg(F.sum("raw").alias("raw"), F.sum("target").alias("target")).collect():
        raw[r["bucket"]], target[r["bucket"]] = r["raw"], r["target"]
    out, base = np.zeros(total), 0
    for _, _, size, prior in orders:
        r, t = raw[base : base + size], target[base : base + size]
        p = (r + 0.5) / (r.sum() + 0.5 * size)
        q = (t + prior * size * p) / (t.sum() + prior * size)
        out[base : base + size] = np.log(q / p) if t.sum() else 0.0
        base += size
    return out


WEIGHTS = T.StructType([T.StructField("n_grams", T.LongType()), T.StructField("log_weight", T.DoubleType())])


def weights(docs: DataFrame, ratio: np.ndarray, key: str, text: str, orders: tuple = ORDERS) -> DataFrame:
    ratio = ratio.astype(np.float32)

    def measure(part: pa.RecordBatch, data: np.ndarray, offsets: np.ndarray) -> dict:
        n, bucket, doc = ngrams(data, offsets, orders)
        return {"n_grams": np.bincount(doc, minlength=n), "log_weight": np.round(np.bincount(doc, weights=ratio[bucket], minlength=n), 6)}

    return annotate(docs.select(F.col(key).alias("id"), F.xxhash64(text).alias("body"), F.col(text).alias("text")), "text", WEIGHTS, lambda: measure, ["id", "body"])


def kth_largest(rows: DataFrame, score: str, k: int) -> int:
    """The k-th largest value of a bigint column (1 <= k <= rows), by digits
    from the top; each pass counts 2**DIGIT cells at most."""
    low, shift = -(1 << 62), 63 - DIGIT
    width = 1 << 63
    while width > 1:
        shift = max(0, width.bit_length() - 1 - DIGIT)
        inside = rows.where((F.col(score) >= F.lit(low)) & (F.col(score) - F.lit(low) < F.lit(width)) if width < 1 << 63 else F.lit(True))
        cells = inside.groupBy(F.shiftrightunsigned(F.col(score) - F.lit(low), shift).alias("cell")).agg(F.count("*").alias("n")).collect()
        for cell, n in sorted(((c["cell"], c["n"]) for c in cells), reverse=True):
            if k <= n:
                low, width = low + (cell << shift), 1 << shift
                break
            k -= n
    return low


def resample(docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", fraction: float = FRACTION, seed: int = SEED, orders: tuple = ORDERS) -> DataFrame:
    """log weight, Gumbel score and kept for every row of docs."""
    rows = weights(docs, models(docs, labels, key, text, orders), key, text, orders)
    u = (F.pmod(F.xxhash64(F.lit(seed), F.col("id")), F.lit(1 << 52)) + F.lit(0.5)) / F.lit(float(1 << 52))
    rows = rows.withColumn("score", F.round(F.col("log_weight") - F.log(-F.log(u)), 6))
    # scores as integers: micro-units, in order; half of a long for the ties
    rows = rows.withColumn("rank_key", F.round(F.col("score") * 1_000_000).cast("long")).withColumn("tie", F.shiftright(F.xxhash64(F.lit(seed + 1), "id", "body"), 2))
    rows = written(rows.withColumn("row", F.monotonically_increasing_id()), "resample")
    k = int(round(fraction * rows.count()))
    kept = _first(rows, k, ["rank_key", "tie", "row"]) if k else F.lit(False)
    return rows.select(F.col("id").alias(key), "n_grams", "log_weight", "score", kept.alias("kept"))


def _first(rows: DataFrame, k: int, columns: list[str]) -> Column:
    """Whether a row is among the k largest by these columns, compared one
    after the other; the last tells all rows apart."""
    edge = kth_largest(rows, columns[0], k)
    c = F.col(columns[0])
    counts = rows.agg(F.count_if(c > edge).alias("above"), F.count_if(c == edge).alias("at")).first()
    if counts["above"] + counts["at"] == k or len(columns) == 1:
        return c >= edge
    return (c > edge) | ((c == edge) & _first(rows.where(c == edge), k - counts["above"], columns[1:]))
