"""Driver queries of the corpus operators, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from gradsift.llm import fertility, mixing, phrases, prefixcount, resample, ring, secretscan, superminhash, urlvocab, wumanber
from gradsift.llm.shared import read


def op1_token_fertility(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fertility.score(read(spark, sf_dir, "documents"), keep=["doc_id"])


def op2_wu_manber(spark: SparkSession, sf_dir: str) -> DataFrame:
    return wumanber.search(read(spark, sf_dir, "documents"), read(spark, sf_dir, "benchmark"), keep=["doc_id"])


def op3_importance_resampling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return resample.resample(read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels"))


def op4_prefix_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return prefixcount.token_counts(read(spark, sf_dir, "documents"), keep=["doc_id"])


def op5_bounded_ring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ring.assign(read(spark, sf_dir, "documents"))


def op6_secret_ownership(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secretscan.scan(read(spark, sf_dir, "documents"))


def op7_soft_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.rates(read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels"))


def op8_superminhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return superminhash.groups(read(spark, sf_dir, "documents"))


def op9_repeated_phrases(spark: SparkSession, sf_dir: str) -> DataFrame:
    return phrases.cut_repeats(read(spark, sf_dir, "documents"), keep=["doc_id"])


def op10_url_vocabulary(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urlvocab.judge(read(spark, sf_dir, "pages"), keep=["page_id"])


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (
        op1_token_fertility,
        op2_wu_manber,
        op3_importance_resampling,
        op4_prefix_token_counts,
        op5_bounded_ring,
        op6_secret_ownership,
        op7_soft_mixing,
        op8_superminhash,
        op9_repeated_phrases,
        op10_url_vocabulary,
    )
}
