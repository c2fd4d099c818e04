"""Accuracy and cost measures over tables of estimates (est, truth)."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def qerror(rows: DataFrame) -> DataFrame:
    """max(est/truth, truth/est) where truth > 0; estimates below 1 count as 1."""
    est = F.greatest("est", F.lit(1.0))
    return rows.where("truth > 0").withColumn("qerror", F.greatest(est / F.col("truth"), F.col("truth") / est))


def relative_error(rows: DataFrame) -> DataFrame:
    return rows.where("truth > 0").withColumn("relerr", (F.col("est") - F.col("truth")) / F.col("truth"))


def _share(test) -> F.Column:
    return F.round(F.avg(F.when(test, 1.0).otherwise(0.0)), 9)


def bias_share(rows: DataFrame, by: Sequence[str] = ()) -> DataFrame:
    return rows.groupBy(*by).agg(_share(F.col("est") > F.col("truth")).alias("over"), _share(F.col("est") < F.col("truth")).alias("under"))


def bound_share(rows: DataFrame, by: Sequence[str] = ()) -> DataFrame:
    return rows.groupBy(*by).agg(_share(F.col("est") >= F.col("truth")).alias("bound_share"))


def l1(exact: DataFrame, approx: DataFrame) -> DataFrame:
    """(rep, l1): sum of absolute differences of two sketches."""
    both = exact.select("rep", "bin", F.col("val").alias("a")).join(approx.select("rep", "bin", F.col("val").alias("b")), ["rep", "bin"], "full_outer")
    return both.groupBy("rep").agg(F.round(F.sum(F.abs(F.coalesce("a", F.lit(0)) - F.coalesce("b", F.lit(0)))), 6).alias("l1"))


def summary(rows: DataFrame, by: Sequence[str]) -> DataFrame:
    """Distribution of the q-error and the share of over-estimates per group."""
    return qerror(rows).groupBy(*by).agg(
        F.count("*").alias("n"), F.median("qerror").alias("q_median"), F.percentile("qerror", 0.95).alias("q95"), F.max("qerror").alias("q_max"),
        _share(F.col("est") > F.col("truth")).alias("over"),
    )
