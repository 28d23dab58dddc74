"""A small text classifier: softmax over hashed words and coarse shape bins.

It is fitted on the driver from a bounded sample of labelled rows (SAMPLE
rows at most, chosen by a hash of their id, each with at most BUCKETS
features), and scores whole texts inside one scan.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gradsift.llm.textkit import ALNUM_WORDS, Words, chunks, mix, per_doc, words_of

BUCKETS = 1 << 15
SAMPLE = 4000
SHAPES, BINS = 4, 8
LEAST_SEEN = 6

UPPER = np.zeros(256, bool)
UPPER[0x41:0x5B] = True
MARKS = np.zeros(256, bool)
MARKS[[*range(0x21, 0x30), *range(0x3A, 0x41), *range(0x5B, 0x61), *range(0x7B, 0x7F)]] = True


def features(data: np.ndarray, offsets: np.ndarray) -> tuple[Words, np.ndarray, np.ndarray]:
    """Words, and the (feature, text) pairs of a chunk, each once."""
    w = words_of(data, offsets, ALNUM_WORDS, lower=True)
    n = len(w.counts)
    bucket = (mix(w.hashes, 71) % np.uint64(BUCKETS)).astype(np.int64)
    pairs = np.unique(w.doc.astype(np.int64) * BUCKETS + bucket)
    doc, feature = pairs // BUCKETS, pairs % BUCKETS
    sums = lambda flag: np.diff(np.concatenate([[0], np.cumsum(flag[data])])[offsets])
    size = np.maximum(np.diff(offsets), 1)
    shape = [sums(UPPER) / size * 20, sums(MARKS) / size * 25, per_doc(np.ones(len(doc), np.int64), doc, n) / np.maximum(w.counts, 1) * (BINS - 0.01), np.diff(offsets) / np.maximum(w.counts, 1) - 3]
    extra = [BUCKETS + i * BINS + np.clip(s, 0, BINS - 1).astype(np.int64) for i, s in enumerate(shape)]
    return w, np.concatenate([feature, *extra]), np.concatenate([doc, *[np.arange(n)] * SHAPES])


def sample_of(labels: DataFrame, key: str, label: Column, most: int = SAMPLE) -> DataFrame:
    """(id, label) of at most `most` labelled rows, in the order of a hash."""
    rows = labels.select(F.col(key).cast("long").alias("id"), label.cast("int").alias("label")).where("id is not null and label is not null")
    one = rows.groupBy("id").agg(F.min("label").alias("label"))
    return one.orderBy(F.xxhash64("id"), "id").limit(most)


def examples(docs: DataFrame, labels: DataFrame, key: str, text: str, label: Column, most: int = SAMPLE) -> tuple[list[np.ndarray], np.ndarray]:
    """Feature lists and labels of the sampled rows. The sample is bounded by
    `most` and thus broadcast; the texts are not shuffled."""
    chosen = docs.select(F.col(key).cast("long").alias("id"), F.col(text).alias("text")).join(F.broadcast(sample_of(labels, key, label, most)), "id")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part, data, offsets in chunks(batch, "text"):
                _, feature, doc = features(data, offsets)
                order = np.argsort(doc, kind="stable")
                ends = np.searchsorted(doc[order], np.arange(len(offsets)))
                raw = feature[order].astype(np.int32)
                lists = pa.array([raw[a:b].tobytes() for a, b in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True)], pa.binary())
                yield pa.RecordBatch.from_arrays([part.column("id"), part.column("label"), lists], names=["id", "label", "f"])

    rows = chosen.select("id", "label", "text").mapInArrow(run, "id long, label int, f binary").orderBy("id").collect()
    return [np.frombuffer(r["f"], np.int32) for r in rows], np.array([r["label"] for r in rows], np.int64)


def fit(found: list[np.ndarray], label: np.ndarray, kinds: int, steps: int = 200, rate: float = 0.05, ridge: float = 2e-4) -> tuple[np.ndarray, np.ndarray]:
    """Weights (features x kinds) and intercepts by full-batch Adam."""
    size = BUCKETS + SHAPES * BINS
    if not len(found):
        return np.zeros((size, kinds)), np.zeros(kinds)
    flat = np.concatenate(found)
    seen = np.bincount(flat, minlength=size)
    used = np.flatnonzero(seen >= LEAST_SEEN)
    rename = np.full(size, -1)
    rename[used] = np.arange(len(used))
    doc = np.repeat(np.arange(len(found)), [len(f) for f in found])
    ok = rename[flat] >= 0
    col, doc = rename[flat][ok], doc[ok]
    del flat, ok
    n = len(found)
    truth = np.eye(kinds)[label]
    w, b = np.zeros((len(used), kinds)), np.log(truth.mean(axis=0) + 1e-3)
    moments = [np.zeros_like(w), np.zeros_like(w), np.zeros_like(b), np.zeros_like(b)]
    for t in range(1, steps + 1):
        # features are 0 or 1, so both products are sums over (text, feature) pairs
        z = np.stack([np.bincount(doc, weights=w[col, c], minlength=n) for c in range(kinds)], axis=1) + b
        p = np.exp(z - z.max(axis=1, keepdims=True))
        p /= p.sum(axis=1, keepdims=True)
        error = (p - truth) / n
        gw = np.stack([np.bincount(col, weights=error[doc, c], minlength=len(used)) for c in range(kinds)], axis=1) + ridge * w
        gb = error.sum(axis=0)
        for i, (g, x) in enumerate(((gw, w), (gb, b))):
            m, v = moments[2 * i], moments[2 * i + 1]
            m += 0.1 * (g - m)
            v += 0.001 * (g * g - v)
            x -= rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
    out = np.zeros((size, kinds))
    out[used] = w
    return out, b.astype(float)


def posteriors(feature: np.ndarray, doc: np.ndarray, n: int, w: np.ndarray, b: np.ndarray) -> np.ndarray:
    z = np.stack([np.bincount(doc, weights=w[feature, k], minlength=n) + b[k] for k in range(len(b))], axis=1)
    z = np.exp(z - z.max(axis=1, keepdims=True))
    return z / z.sum(axis=1, keepdims=True)
