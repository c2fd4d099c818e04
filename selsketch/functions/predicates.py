"""Predicates: a small parser, the exact form as a column, and the approximate form as code intervals per attribute."""

from __future__ import annotations

import re
from dataclasses import dataclass
from itertools import product

from pyspark.sql import Column
from pyspark.sql import functions as F

_TOKEN = re.compile(r"\s*(?:(<=|>=|<>|!=|=|<|>|\(|\)|,)|('(?:[^']|'')*')|(-?\d+(?:\.\d+)?)|([A-Za-z_][A-Za-z_0-9]*))")
MOST_TERMS = 1 << 10


@dataclass(frozen=True)
class Atom:
    """attr op values; op is one of = <> < <= > >= between in null."""

    attr: str
    op: str
    values: tuple


@dataclass(frozen=True)
class Not:
    part: object


@dataclass(frozen=True)
class And:
    parts: tuple


@dataclass(frozen=True)
class Or:
    parts: tuple


def parse(sql: str):
    """The predicate tree of a condition with AND, OR, NOT, comparisons, BETWEEN, IN and IS [NOT] NULL."""
    tokens, at = [], 0
    while at < len(sql.rstrip()):
        m = _TOKEN.match(sql, at)
        if not m:
            raise ValueError(f"cannot read predicate at: {sql[at:]!r}")
        symbol, text, number, word = m.groups()
        tokens.append(("s", symbol) if symbol else ("v", text[1:-1].replace("''", "'")) if text is not None else ("v", float(number) if "." in number else int(number)) if number else ("w", word))
        at = m.end()
    place = 0

    def peek(word: str) -> bool:
        return place < len(tokens) and ((tokens[place][0] == "w" and tokens[place][1].upper() == word) or tokens[place] == ("s", word))

    def take(word: str) -> bool:
        nonlocal place
        place += (hit := peek(word))
        return hit

    def need(word: str) -> None:
        if not take(word):
            raise ValueError(f"expected {word} in {sql!r}")

    def value():
        nonlocal place
        if tokens[place][0] != "v":
            raise ValueError(f"expected a literal in {sql!r}")
        place += 1
        return tokens[place - 1][1]

    def either():
        parts = [both()]
        while take("OR"):
            parts.append(both())
        return parts[0] if len(parts) == 1 else Or(tuple(parts))

    def both():
        parts = [single()]
        while take("AND"):
            parts.append(single())
        return parts[0] if len(parts) == 1 else And(tuple(parts))

    def single():
        nonlocal place
        if take("NOT"):
            return Not(single())
        if take("("):
            inner = either()
            need(")")
            return inner
        attr = tokens[place][1]
        place += 1
        inverted = take("NOT")
        if take("BETWEEN"):
            low = value()
            need("AND")
            atom = Atom(attr, "between", (low, value()))
        elif take("IN"):
            need("(")
            values = [value()]
            while take(","):
                values.append(value())
            need(")")
            atom = Atom(attr, "in", tuple(values))
        elif take("IS"):
            inverted = take("NOT")
            need("NULL")
            atom = Atom(attr, "null", ())
        else:
            op = tokens[place][1]
            if op not in ("=", "<>", "!=", "<", "<=", ">", ">="):
                raise ValueError(f"unknown operator {op!r}")
            place += 1
            atom = Atom(attr, "<>" if op == "!=" else op, (value(),))
        return Not(atom) if inverted else atom

    tree = either()
    if place != len(tokens):
        raise ValueError(f"trailing text in {sql!r}")
    return tree


def to_column(tree) -> Column:
    if isinstance(tree, And | Or):
        out = to_column(tree.parts[0])
        for p in tree.parts[1:]:
            out = out & to_column(p) if isinstance(tree, And) else out | to_column(p)
        return out
    if isinstance(tree, Not):
        return ~to_column(tree.part)
    c = F.col(tree.attr)
    v = tree.values
    return {
        "=": lambda: c == v[0], "<>": lambda: c != v[0], "<": lambda: c < v[0], "<=": lambda: c <= v[0], ">": lambda: c > v[0],
        ">=": lambda: c >= v[0], "between": lambda: c.between(*v), "in": lambda: c.isin(list(v)), "null": lambda: c.isNull(),
    }[tree.op]()


def attributes(tree) -> set[str]:
    if isinstance(tree, Atom):
        return {tree.attr}
    return set().union(*map(attributes, tree.parts)) if isinstance(tree, And | Or) else attributes(tree.part)


_INVERSE = {"=": "<>", "<>": "=", "<": ">=", "<=": ">", ">": "<=", ">=": "<"}


def positive(tree, flip: bool = False):
    """The same predicate with NOT only on BETWEEN, IN and IS NULL atoms."""
    if isinstance(tree, Not):
        return positive(tree.part, not flip)
    if isinstance(tree, And | Or):
        return (And if isinstance(tree, And) != flip else Or)(tuple(positive(p, flip) for p in tree.parts))
    if not flip:
        return tree
    return Atom(tree.attr, _INVERSE[tree.op], tree.values) if tree.op in _INVERSE else Not(tree)


def to_dnf(tree) -> list[list]:
    """Conjunctions of literals whose union is the predicate; a disjunction over one attribute stays one literal."""
    tree = positive(tree)

    def expand(t) -> list[list]:
        if isinstance(t, Or):
            return [[t]] if len(attributes(t)) == 1 else [c for p in t.parts for c in expand(p)]
        if isinstance(t, And):
            return [[x for c in combo for x in c] for combo in product(*(expand(p) for p in t.parts))]
        return [[t]]

    out = expand(tree)
    if len(out) > MOST_TERMS:
        raise ValueError("too many terms")
    return out


def signed_terms(tree) -> list[tuple[int, list]]:
    """Inclusion-exclusion over the conjunctions: (+1 or -1, literals)."""
    terms = to_dnf(tree)
    if len(terms) > 10:
        raise ValueError("too many disjuncts for inclusion-exclusion")
    out = []
    for mask in range(1, 1 << len(terms)):
        chosen = [terms[i] for i in range(len(terms)) if mask >> i & 1]
        out.append((1 if len(chosen) % 2 else -1, [x for t in chosen for x in t]))
    return out


def dyadic_cover(lo: int, hi: int, bits: int) -> list[tuple[int, int]]:
    """Disjoint dyadic intervals (level, index) whose union is lo..hi; at most two per level."""
    out, level = [], 0
    while lo <= hi and level <= bits:
        if lo % 2 == 1:
            out.append((level, lo))
            lo += 1
        if lo <= hi and hi % 2 == 0:
            out.append((level, hi))
            hi -= 1
        lo, hi, level = lo // 2, hi // 2, level + 1
        if lo > hi:
            break
    return out


def merged(intervals: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[list[int]] = []
    for lo, hi in sorted(i for i in intervals if i[0] <= i[1]):
        if out and lo <= out[-1][1] + 1:
            out[-1][1] = max(out[-1][1], hi)
        else:
            out.append([lo, hi])
    return [tuple(x) for x in out]


def intersected(a: list[tuple[int, int]], b: list[tuple[int, int]]) -> list[tuple[int, int]]:
    return merged([(max(x[0], y[0]), min(x[1], y[1])) for x in a for y in b])


def complement(a: list[tuple[int, int]], top: int) -> list[tuple[int, int]]:
    out, at = [], 0
    for lo, hi in merged(a):
        if at < lo:
            out.append((at, lo - 1))
        at = hi + 1
    return [*out, (at, top)] if at <= top else out
