"""SQL text of the hash families and sketches, written apart from the Spark code."""

from __future__ import annotations

from ..functions.hashing import PRIME, coefficients


def poly(x: str, coeffs: list[int]) -> str:
    out = f"{coeffs[0]}::BIGINT"
    for c in coeffs[1:]:
        out = f"(({out}) * ({x})::BIGINT + {c}) % {PRIME}"
    return f"({out})"


def bucket(x: str, cls: str, rep: int, w: int) -> str:
    return f"({poly(x, coefficients('bucket', cls, rep, 2))} % {w})"


def sign(x: str, edge: str, rep: int) -> str:
    return f"(1 - 2 * ({poly(x, coefficients('sign', edge, rep, 4))} % 2))"


def bins(keys: dict[str, str], rep: int, w: int) -> str:
    return "(" + " + ".join(bucket(c, cls, rep, w) for c, cls in keys.items()) + f") % {w}"


def signs_of(signs: dict[str, list[str]], rep: int) -> str:
    return " * ".join(sign(c, e, rep) for c, es in signs.items() for e in es) or "1"


def sketch(table: str, keys: dict[str, str], w: int, reps: int, signs: dict[str, list[str]] | None = None, weight: str = "1") -> str:
    return " UNION ALL ".join(
        f"SELECT {r} AS rep, bin::INTEGER AS bin, sum(s) AS val FROM (SELECT {bins(keys, r, w)} AS bin, {weight} * {signs_of(signs or {}, r)} AS s FROM ({table}) t) u GROUP BY bin HAVING sum(s) <> 0"
        for r in range(reps)
    )


def degree(table: str, keys: dict[str, str], facing: str, w: int, reps: int) -> str:
    return " UNION ALL ".join(
        f"SELECT {r} AS rep, bin::INTEGER AS bin, max(d) AS val FROM (SELECT {bins(keys, r, w)} AS bin, {facing} AS f, count(*) AS d FROM ({table}) t GROUP BY 1, 2) u GROUP BY bin"
        for r in range(reps)
    )


def tensor(table: str, keys: dict[str, str], w: int, reps: int, signs: dict[str, list[str]] | None = None, facing: str | None = None) -> str:
    axes = ", ".join(f"({bucket(c, cls, 0, w)})" for c, cls in keys.items())
    out = []
    for r in range(reps):
        axes = ", ".join(f"({bucket(c, cls, r, w)})::INTEGER AS bin{i + 1}" for i, (c, cls) in enumerate(keys.items()))
        names = ", ".join(f"bin{i + 1}" for i in range(len(keys)))
        if facing:
            out.append(f"SELECT {r} AS rep, {names}, max(d) AS val FROM (SELECT {axes}, {facing} AS f, count(*) AS d FROM ({table}) t GROUP BY ALL) u GROUP BY {names}")
        else:
            out.append(f"SELECT {r} AS rep, {names}, sum(s) AS val FROM (SELECT {axes}, {signs_of(signs or {}, r)} AS s FROM ({table}) t) u GROUP BY {names} HAVING sum(s) <> 0")
    return " UNION ALL ".join(out)
