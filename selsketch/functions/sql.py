"""SQL surface: hash functions as SQL text and table functions."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from .hashing import PRIME, coefficients
from .predicates import dyadic_cover


@udtf(returnType="level int, idx long")
class DyadicCover:
    """dyadic_cover(lo, hi, bits): the disjoint dyadic intervals of a code range."""

    def eval(self, lo: int, hi: int, bits: int) -> Iterator[tuple[int, int]]:
        yield from dyadic_cover(lo, hi, bits)


def _poly(coeffs: list[int]) -> str:
    out = f"CAST({coeffs[0]} AS BIGINT)"
    for c in coeffs[1:]:
        out = f"(({out}) * pmod(x, {PRIME}L) + {c}) % {PRIME}"
    return out


def register(spark: SparkSession, cls: str = "cust", edge: str = "cust#0", rep: int = 0) -> None:
    """dyadic_cover(...) as a table function; sbs_bucket(x, width) and sbs_sign(x) as SQL functions, which stay in the JVM."""
    spark.udtf.register("dyadic_cover", DyadicCover)
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION sbs_bucket(x BIGINT, width INT) RETURNS INT RETURN CAST(({_poly(coefficients('bucket', cls, rep, 2))}) % width AS INT)")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION sbs_sign(x BIGINT) RETURNS BIGINT RETURN 1 - 2 * (({_poly(coefficients('sign', edge, rep, 4))}) % 2)")
