"""Polynomial hash families modulo a Mersenne prime, as columns inside whole-stage codegen."""

from __future__ import annotations

import hashlib
from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

PRIME = 2147483647
MASTER = 42


def coefficients(role: str, name: str, rep: int, k: int, master: int = MASTER) -> list[int]:
    """k seeded coefficients below the prime; the same on every machine."""
    digest = (hashlib.md5(f"{master}|{role}|{name}|{rep}|{i}".encode()).hexdigest() for i in range(k))
    return [(int(d[:8], 16) >> 1) % PRIME for d in digest]


def seed(role: str, name: Column, rep: int, i: int, master: int = MASTER) -> Column:
    """Coefficient i of the family that a row names, as ``coefficients`` gives it."""
    text = F.concat(F.lit(f"{master}|{role}|"), name, F.lit(f"|{rep}|{i}"))
    return F.shiftright(portable_hash(text), 1) % F.lit(PRIME)


def polynomial(x: Column, coeffs: Sequence[int]) -> Column:
    """Horner's rule; products stay below 2^62."""
    x = F.pmod(x.cast("long"), F.lit(PRIME).cast("long"))
    return reduce(lambda acc, c: (acc * x + F.lit(c)) % F.lit(PRIME), coeffs[1:], F.lit(coeffs[0]).cast("long"))


def bucket(x: Column, cls: str, rep: int, width: int, k: int = 2) -> Column:
    """Bucket hash of an attribute class: 0..width-1."""
    return (polynomial(x, coefficients("bucket", cls, rep, k)) % width).cast("int")


def bucket_of(x: int, cls: str, rep: int, width: int, k: int = 2) -> int:
    """The bucket of one number, as ``bucket`` gives it."""
    return reduce(lambda acc, c: (acc * (x % PRIME) + c) % PRIME, coefficients("bucket", cls, rep, k)) % width


def sign(x: Column, edge: str, rep: int, k: int = 4) -> Column:
    """Sign hash of a join edge: +1 or -1, k-wise independent."""
    return 1 - 2 * (polynomial(x, coefficients("sign", edge, rep, k)) % 2)


def composite(buckets: Sequence[Column], width: int) -> Column:
    """Bin of a tuple of buckets: their sum modulo the width."""
    return buckets[0] if len(buckets) == 1 else F.pmod(reduce(lambda a, b: a + b, buckets), F.lit(width)).cast("int")


def portable_hash(x: Column) -> Column:
    """A text's 32-bit code from MD5, equal in every engine."""
    return F.conv(F.substring(F.md5(x.cast("string")), 1, 8), 16, 10).cast("long")
