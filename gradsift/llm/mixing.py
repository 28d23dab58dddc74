"""Mixing documents to target domain weights with soft membership.

Domains come from a labelled table; a classifier gives every document its
posterior over them. The rate r of a document, how often it is drawn in
expectation, is nonnegative and solves the least squares problem

    minimise  sum over domains k of (S_k - T_k)**2 / M_k,
    S_k = sum over documents of r * tokens * posterior_k,

with M_k the domain's tokens at rate 1 and T_k its target. Projected gradient
starts from rate 1 and steps, in the metric of the token counts, to
max(0, r - posterior . g) with g_k = (S_k - T_k) / M_k; each step needs only
the totals S_k, one aggregate over a table of a few numbers per document. A
document's rate is a fold over the history of g, so rates are never stored
between steps, and a lost executor costs a recomputation only.

Rates without an upper bound keep the number of tokens: T_k is the domain's
share of all of them, and copies is the rate rounded up or down by a hash of
the id. Where documents can only stay or go, rates are projected onto [0, 1],
and T_k is set so that the domain of the largest share is taken whole: the
others get their part in proportion to it, or all that they have, if that is
less. So no domain that is short of tokens makes the others shrink with it.

What is left of the largest |S_k - T_k| / M_k after the last step is returned
by solve; more than TOLERATED is warned of, since targets that no rates reach
are met as closely as the bounds allow. A rate of 1 or more is always kept;
below 1, a document is kept if a hash of its id falls below the rate.

Defined results: null and empty texts have no tokens, carry the prior as
posterior and get the rate that it implies; null ids hash as null; without
labelled rows all posteriors are uniform; repeated rows get equal rates.
"""

from __future__ import annotations

import warnings

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from gradsift.llm import domains
from gradsift.llm.shared import written
from gradsift.llm.textkit import SMALL_CHUNK_BYTES, annotate, select_rows

#: Domains in order of their numbers, and the shares of tokens to aim at.
DOMAINS = ("clean", "low", "toxic")
TARGETS = (0.97, 0.02, 0.01)
STEPS = 24
ENOUGH = 1e-6
TOLERATED = 0.05


def domain_of() -> Column:
    return F.when(F.col("toxic") == 1, 2).when(F.col("quality") == 0, 1).when((F.col("quality") == 1) & (F.col("toxic") == 0), 0)


def _model(docs: DataFrame, labels: DataFrame, key: str, text: str) -> tuple[np.ndarray, np.ndarray]:
    found, label = domains.examples(docs, labels, key, text, domain_of())
    w, b = domains.fit(found, label, len(DOMAINS))
    return w.astype(np.float32), b


def membership(docs: DataFrame, model: tuple[np.ndarray, np.ndarray], key: str, text: str) -> DataFrame:
    """(id, n_tokens, p_<domain>...) of every row of docs."""
    added = T.StructType([T.StructField("n_tokens", T.LongType())] + [T.StructField(f"p_{d}", T.DoubleType()) for d in DOMAINS])

    def measure(part: pa.RecordBatch, data: np.ndarray, offsets: np.ndarray) -> dict:
        w, feature, doc = domains.features(data, offsets)
        p = np.round(domains.posteriors(feature, doc, len(w.counts), *model), 9)
        return {"n_tokens": w.counts} | {f"p_{d}": p[:, k] for k, d in enumerate(DOMAINS)}

    return annotate(docs.select(F.col(key).alias("id"), F.col(text).alias("text")), "text", added, lambda: measure, ["id"], limit=SMALL_CHUNK_BYTES)


def rate_of(history: list[list[float]], most: float | None = None) -> Column:
    rate = F.lit(1.0)
    for g in history:
        rate = F.greatest(F.lit(0.0), rate - sum(F.col(f"p_{d}") * F.lit(v) for d, v in zip(DOMAINS, g, strict=True)))
        rate = rate if most is None else F.least(F.lit(most), rate)
    return rate


def aims(mass: np.ndarray, targets: tuple[float, ...], most: float | None = None) -> np.ndarray:
    """Token totals to aim at, of the domains' tokens at rate 1."""
    share = np.array(targets) / sum(targets)
    if most is None:
        return share * mass.sum()
    main = int(share.argmax())
    return np.minimum(most * mass, share / share[main] * most * mass[main])


def solve(rows: DataFrame, targets: tuple[float, ...] = TARGETS, steps: int = STEPS, most: float | None = None) -> tuple[list[list[float]], float]:
    """The steps g that the rates follow from, and what is left."""

    def totals(history: list[list[float]]) -> np.ndarray:
        r = rows.select("n_tokens", *[f"p_{d}" for d in DOMAINS], rate_of(history, most).alias("rate"))
        got = r.agg(*[F.sum(F.col("n_tokens") * F.col("rate") * F.col(f"p_{d}")).alias(d) for d in DOMAINS]).first()
        return np.array([got[d] or 0.0 for d in DOMAINS])

    mass = totals([])
    if not mass.sum():
        return [], 0.0
    aim, history, left = aims(mass, targets, most), [], 0.0
    for step in range(steps + 1):
        g = (totals(history) - aim) / np.maximum(mass, 1e-9 * mass.sum())
        left = float(np.abs(g).max())
        if left < ENOUGH or step == steps:
            break
        history.append([round(float(v), 12) for v in g])
    if left > TOLERATED:
        warnings.warn(f"the targets are missed by up to {left:.3f} of a domain's tokens", stacklevel=2)
    return history, left


def draw(key: Column, seed: str = "mix") -> Column:
    """A number in [0, 1) from a hash of the id."""
    return F.pmod(F.xxhash64(F.lit(seed), key), F.lit(1 << 53)) / F.lit(float(1 << 53))


def rates(docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", targets: tuple[float, ...] = TARGETS) -> DataFrame:
    """Posteriors, rate, kept and copies of every row of docs."""
    rows = written(membership(docs, _model(docs, labels, key, text), key, text), "membership")
    rate = rate_of(solve(rows, targets)[0])
    out = rows.withColumn("rate", F.round(rate, 9)).withColumn("u", draw(F.col("id")))
    return out.select(F.col("id").alias(key), "n_tokens", *[f"p_{d}" for d in DOMAINS], "rate", (F.col("u") < F.col("rate")).alias("kept"), (F.floor("rate") + (F.col("u") < F.col("rate") - F.floor("rate")).cast("long")).alias("copies"))


def mixed(docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", targets: tuple[float, ...] = TARGETS) -> DataFrame:
    """The rows of docs that rates in [0, 1] keep, unchanged: the classifier
    scores them again beside their texts, so that no text is shuffled."""
    model = _model(docs, labels, key, text)
    history, _ = solve(written(membership(docs, model, key, text), "membership"), targets, most=1.0)
    u = "u"
    while u in (c.lower() for c in docs.columns):
        u += "_"

    def start():
        def decide(part: pa.RecordBatch, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
            w, feature, doc = domains.features(data, offsets)
            p = np.round(domains.posteriors(feature, doc, len(w.counts), *model), 9)
            rate = np.ones(len(p))
            for g in history:
                rate = np.minimum(1.0, np.maximum(0.0, rate - p @ np.array(g)))
            return part.column(part.schema.get_field_index(u)).to_numpy(zero_copy_only=False) < np.round(rate, 9)

        return decide

    return select_rows(docs.withColumn(u, draw(F.col(key))), text, start).drop(u)
