"""One- and many-dimensional histograms and samples."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import bucket


def histogram_join(a: DataFrame, ka: str, b: DataFrame, kb: str, step: int) -> DataFrame:
    """Equi-width histograms of both keys; inside a bucket every value is as frequent as any other."""
    table = lambda t, k, s: t.where(F.col(k).isNotNull()).groupBy(F.floor(F.col(k) / step).alias("b")).agg(F.count("*").cast("double").alias(f"n{s}"), F.countDistinct(k).alias(f"v{s}"))
    return table(a, ka, 1).join(table(b, kb, 2), "b").agg(F.round(F.sum(F.col("n1") * F.col("n2") / F.greatest("v1", "v2")), 6).alias("est"))


def equi_depth(df: DataFrame, key: str, buckets: int) -> DataFrame:
    """(bucket, lo, hi, n) of an equi-depth histogram."""
    cuts = sorted(set(df.approxQuantile(key, [i / buckets for i in range(1, buckets)], 0.001)))
    at = F.lit(0)
    for c in cuts:
        at = at + F.when(F.col(key) > c, 1).otherwise(0)
    return df.groupBy(at.alias("bucket")).agg(F.min(key).alias("lo"), F.max(key).alias("hi"), F.count("*").alias("n"))


def sample_join(a: DataFrame, ka: str, b: DataFrame, kb: str, percent: int) -> DataFrame:
    """Correlated sample: both sides keep the keys whose hash falls into the same share, so matches survive together."""
    table = lambda t, k, s: t.where(bucket(F.col(k), "sample", 0, 100) < percent).groupBy(F.col(k).alias("k")).agg(F.count("*").cast("double").alias(f"n{s}"))
    return table(a, ka, 1).join(table(b, kb, 2), "k").agg(F.round(F.sum(F.col("n1") * F.col("n2")) * 100 / percent, 6).alias("est"))


def md_histogram(df: DataFrame, attrs: list[str]) -> DataFrame:
    """Joint histogram: exponential in the number of attributes."""
    total = df.agg(F.count("*").alias("t"))
    return df.groupBy(*attrs).agg(F.count("*").cast("double").alias("n")).join(F.broadcast(total)).select(*attrs, (F.col("n") / F.col("t")).alias("p"))
