"""Attributes as integer codes: a dictionary of words, or equal steps over the range of the values.

A code is exact where it stands for one value.  Where it stands for several (doubles of many digits, wide ranges, texts of many
words), ranges are still sets of codes, and single values are told apart by a second, hashed code.
"""

from __future__ import annotations

import bisect
import datetime as dt
import hashlib
import math
from collections.abc import Mapping
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .predicates import complement, intersected, merged

MOST_WORDS, BITS = 1 << 10, 16
_UNITS = (1.0, 0.1, 0.01)


@dataclass
class Selection:
    """Values of one attribute: those whose code is in ``intervals``, and ``more``, without ``less``."""

    intervals: list[tuple[int, int]]
    more: frozenset = frozenset()
    less: frozenset = frozenset()


@dataclass
class Encoder:
    """``mode``: dictionary (``words`` ascending), hashed (a text by its first two bytes), linear (steps from ``low`` on)."""

    attr: str
    mode: str
    words: list = field(default_factory=list)
    low: float = 0.0
    step: float = 1.0
    top: int = 0
    exact: bool = True
    kind: str = "string"
    expr: str = ""

    @property
    def size(self) -> int:
        return max(len(self.words), 1) if self.mode == "dictionary" else self.top + 1

    @property
    def bits(self) -> int:
        return max(1, (self.size - 1).bit_length())

    def _raw(self) -> Column:
        c = F.expr(self.expr or self.attr)
        if self.kind == "timestamp_ntz":
            return F.timestamp_diff("MICROSECOND", F.lit("1970-01-01 00:00:00").cast("timestamp_ntz"), c)
        if self.kind.startswith("timestamp"):
            return F.unix_micros(c)
        return F.unix_date(c) if self.kind == "date" else c

    def column(self) -> Column:
        """The code of a row, null for null: comparisons and arithmetic inside generated code."""
        c = self._raw()
        if self.mode == "dictionary":

            def tree(lo: int, hi: int) -> Column:
                if lo == hi:
                    return F.lit(lo)
                mid = (lo + hi) // 2
                return F.when(c < F.lit(self.words[mid]), tree(lo, mid)).otherwise(tree(mid + 1, hi))

            # the number of words at or below, less one; unknown words get none
            code = F.when(c.isin(self.words), tree(0, len(self.words)) - 1) if self.words else F.lit(None).cast("int")
        elif self.mode == "hashed":
            code = F.conv(F.rpad(F.hex(F.encode(F.substring(c, 1, 2), "UTF-8")), 4, "0"), 16, 10).cast("int")
        else:
            steps = (c.cast("double") - self.low) / self.step
            code = F.greatest(F.least(F.round(steps) if self.exact else F.floor(steps), F.lit(self.top)), F.lit(0))
        return F.when(c.isNotNull(), code).cast("int")

    def point(self) -> Column:
        """A number that tells single values apart."""
        c = self._raw()
        if self.mode != "linear":
            return F.conv(F.substring(F.md5(c.cast("string")), 1, 8), 16, 10).cast("long")
        return F.round(c.cast("double") * 10_000).cast("long")

    def point_of(self, v) -> int:
        return int(hashlib.md5(str(v).encode()).hexdigest()[:8], 16) if self.mode != "linear" else math.floor(self._plain(v) * 10_000 + 0.5)

    def _plain(self, v) -> float | str:
        if self.mode != "linear" or isinstance(v, int | float):
            return v
        v = dt.datetime.fromisoformat(v) if isinstance(v, str) else v
        v = v if isinstance(v, dt.datetime) else dt.datetime(v.year, v.month, v.day)
        return (v.replace(tzinfo=None) - dt.datetime(1970, 1, 1)) / dt.timedelta(microseconds=1) / (86_400_000_000 if self.kind == "date" else 1)

    def code_of(self, v) -> int | None:
        """The code of a value; None where no row can have it."""
        if self.mode == "dictionary":
            return bisect.bisect_left(self.words, v) if v in self.words else None
        if self.mode == "hashed":
            return int(str(v)[:2].encode().hex().ljust(4, "0")[:4], 16)
        at = (self._plain(v) - self.low) / self.step
        if self.exact:
            return round(at) if abs(at - round(at)) < 1e-6 and 0 <= round(at) <= self.top else None
        return math.floor(at) if 0 <= math.floor(at) <= self.top else None

    def _edges(self, v) -> tuple[int, int]:
        """(first code with a value at or above v, last code with a value at or below v)."""
        if self.mode == "dictionary":
            return bisect.bisect_left(self.words, v), bisect.bisect_right(self.words, v) - 1
        if self.mode == "hashed":
            return self.code_of(v), self.code_of(v)
        at = (self._plain(v) - self.low) / self.step
        if not self.exact:
            return max(math.floor(at), 0), min(math.floor(at), self.top)
        near = round(at) if abs(at - round(at)) < 1e-6 else at
        return max(math.ceil(near), 0), min(math.floor(near), self.top)

    def select(self, op: str, values: tuple) -> Selection:
        top, v = self.size - 1, values
        if op == "<>":
            return self.inverse(self.select("=", values))
        if op in ("=", "in"):
            found = [(x, self.code_of(x)) for x in v]
            if self.exact:
                return Selection(merged([(c, c) for _, c in found if c is not None]))
            return Selection([], frozenset(x for x, c in found if c is not None))
        lo, hi = self._edges(v[0])
        out = {
            "between": lambda: [(lo, self._edges(v[1])[1])], "<=": lambda: [(0, hi)], ">=": lambda: [(lo, top)],
            "<": lambda: [(0, lo - 1 if self.exact else hi)], ">": lambda: [(hi + 1 if self.exact else lo, top)],
        }[op]()
        code = self.code_of(v[0])
        strict = op in ("<", ">") and not self.exact and code is not None
        return Selection(merged(out), less=frozenset([v[0]] if strict else []))

    def intervals(self, op: str, values: tuple) -> list[tuple[int, int]]:
        return self.select(op, values).intervals

    def has(self, s: Selection, v) -> bool:
        code = self.code_of(v)
        return v in s.more or (code is not None and v not in s.less and any(lo <= code <= hi for lo, hi in s.intervals))

    def _made(self, intervals: list[tuple[int, int]], named: frozenset, inside) -> Selection:
        plain = Selection(intervals)
        return Selection(intervals, frozenset(v for v in named if inside(v) and not self.has(plain, v)), frozenset(v for v in named if not inside(v) and self.has(plain, v)))

    def both(self, a: Selection, b: Selection) -> Selection:
        return self._made(intersected(a.intervals, b.intervals), a.more | a.less | b.more | b.less, lambda v: self.has(a, v) and self.has(b, v))

    def either(self, a: Selection, b: Selection) -> Selection:
        return self._made(merged([*a.intervals, *b.intervals]), a.more | a.less | b.more | b.less, lambda v: self.has(a, v) or self.has(b, v))

    def inverse(self, a: Selection) -> Selection:
        return Selection(complement(a.intervals, self.size - 1), a.less, a.more)


def fit(df: DataFrame, attr: str, expr: str = "") -> Encoder:
    return fit_all(df, {attr: expr})[attr]


def fit_all(df: DataFrame, attrs: Mapping[str, str]) -> dict[str, Encoder]:
    """Encoders of attributes (name -> expression or ''): one aggregation finds ranges and units, a second the words of texts
    that have few."""
    kinds = {a: df.select(F.expr(e or a).alias("x")).schema["x"].dataType.simpleString() for a, e in attrs.items()}
    out = {a: Encoder(a, "linear", kind=kinds[a], expr=e) for a, e in attrs.items()}
    texts = [a for a, k in kinds.items() if k in ("string", "boolean") or k.startswith(("char", "varchar"))]
    asked = []
    for i, a in enumerate(out):
        if a in texts:
            asked.append(F.approx_count_distinct(F.expr(attrs[a] or a)).alias(f"n{i}"))
            continue
        x = out[a]._raw().cast("double")
        asked += [F.min(x).alias(f"a{i}"), F.max(x).alias(f"b{i}"), *[F.max(F.abs(x / u - F.round(x / u))).alias(f"u{i}_{j}") for j, u in enumerate(_UNITS)]]
    found = df.agg(*asked).first() if asked else None
    few = [a for i, a in enumerate(out) if a in texts and found[f"n{i}"] <= 2 * MOST_WORDS]
    words: dict[str, list] = {a: [] for a in few}
    if few:
        pair = F.explode(F.array(*[F.struct(F.lit(a).alias("a"), F.expr(attrs[a] or a).cast("string").alias("w")) for a in few]))
        for r in df.select(pair.alias("p")).select("p.*").where("w IS NOT NULL").distinct().collect():  # few attributes, few words
            words[r["a"]].append(r["w"])
    for i, (a, e) in enumerate(out.items()):
        if a in texts:
            if a in words and len(words[a]) <= MOST_WORDS:
                e.mode, e.words = "dictionary", sorted(words[a])
                if kinds[a] == "boolean":
                    e.words = [w == "true" for w in e.words]
            else:
                e.mode, e.top, e.exact = "hashed", (1 << BITS) - 1, False
            continue
        low, high = found[f"a{i}"], found[f"b{i}"]
        if low is None:
            continue
        unit = next((u for j, u in enumerate(_UNITS) if found[f"u{i}_{j}"] < 1e-6 and (high - low) / u < 1 << BITS), None)
        e.low, e.exact = low, unit is not None
        e.step = unit or (high - low) / ((1 << BITS) - 1)
        e.top = round((high - low) / unit) if unit else (1 << BITS) - 1
    return out
