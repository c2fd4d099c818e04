"""Selectivity leaves: count-min counters over dyadic levels of an attribute's codes."""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import PRIME, bucket, coefficients
from ..functions.predicates import dyadic_cover


def dyadic(df: DataFrame, code: str, bits: int, width: int, by: tuple[str, ...] = ()) -> DataFrame:
    """(level, bin, cnt): level l counts the intervals of 2^l codes; a level of at most ``width`` intervals is exact."""
    return dyadic_of_counts(df.where(F.col(code).isNotNull()).groupBy(*by, code).agg(F.count("*").alias("n")), code, bits, width, by)


def dyadic_of_counts(counts: DataFrame, code: str, bits: int, width: int, by: tuple[str, ...] = ()) -> DataFrame:
    """``dyadic`` of rows counted by code."""
    rows = counts.withColumn("level", F.explode(F.sequence(F.lit(0), F.lit(bits))))
    index = F.call_function("shiftright", F.col(code).cast("long"), F.col("level"))
    binned = index.cast("int")
    for level in range(bits + 1):
        if 1 << (bits - level) > width:
            binned = F.when(F.col("level") == level, bucket(index, f"{code}@{level}", 0, width)).otherwise(binned)
    return rows.groupBy(*by, "level", binned.alias("bin")).agg(F.sum("n").alias("cnt"))


def dyadic_counters(codes: Sequence[int], counts: Sequence[int], bits: int, width: int, name: str = "code") -> dict[tuple[int, int], int]:
    """``dyadic_of_counts`` of few codes, as (level, bin) -> cnt."""
    codes, out = np.asarray(codes, np.int64), {}
    for level in range(bits + 1):
        bins = codes >> level
        if 1 << (bits - level) > width:
            bins = reduce(lambda acc, c, x=bins: (acc * x + c) % PRIME, coefficients("bucket", f"{name}@{level}", 0, 2)) % width
        sums = np.zeros(int(bins.max()) + 1, np.int64)
        np.add.at(sums, bins, counts)
        out |= {(level, int(b)): int(sums[b]) for b in np.flatnonzero(sums)}
    return out


def range_sum(counters: DataFrame, lo: int, hi: int, bits: int, mode: str = "dyadic") -> DataFrame:
    """Rows with a code in lo..hi from exact levels: by dyadic intervals, or code by code."""
    cover = dyadic_cover(lo, hi, bits) if mode == "dyadic" else [(0, i) for i in range(lo, hi + 1)]
    by_level: dict[int, list[int]] = {}
    for level, index in cover:
        by_level.setdefault(level, []).append(index)
    test = reduce(lambda a, b: a | b, [(F.col("level") == lv) & F.col("bin").isin(ix) for lv, ix in by_level.items()], F.lit(False))
    return counters.where(test).agg(F.coalesce(F.sum("cnt"), F.lit(0)).alias("cnt"))


def covers(ranges: DataFrame, bits: int) -> DataFrame:
    """ranges(id, lo, hi) -> (id, level, idx): the dyadic cover of every row, level by level, without Python."""
    levels = ranges.withColumn("level", F.explode(F.sequence(F.lit(0), F.lit(bits))))
    # at level l the part not yet covered by coarser blocks starts and ends at these indexes
    lo = F.ceil(F.col("lo") / F.pow(F.lit(2), "level")).cast("long")
    hi = F.floor((F.col("hi") + 1) / F.pow(F.lit(2), "level")).cast("long") - 1
    up_lo = F.ceil(F.col("lo") / F.pow(F.lit(2), F.col("level") + 1)).cast("long")
    up_hi = F.floor((F.col("hi") + 1) / F.pow(F.lit(2), F.col("level") + 1)).cast("long") - 1
    rows = levels.select("id", "level", lo.alias("a"), hi.alias("b"), up_lo.alias("ua"), up_hi.alias("ub")).where("a <= b")
    inside = (F.col("ua") <= F.col("ub")) & (F.col("level") < bits)
    left = F.when(inside, F.when(F.col("a") < 2 * F.col("ua"), F.array("a")).otherwise(F.array().cast("array<bigint>"))).otherwise(F.sequence("a", "b"))
    right = F.when(inside & (F.col("b") > 2 * F.col("ub") + 1), F.array("b")).otherwise(F.array().cast("array<bigint>"))
    return rows.select("id", "level", F.explode(F.concat(left, right)).alias("idx"))
