"""From sketches to join sizes.  Element-wise contractions are sparse equi-joins on (rep, bin); correlations go through FFT in
one Arrow group per sub-join and repetition."""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .sketch import unpacked


def hadamard(tables: Sequence[DataFrame]) -> DataFrame:
    """(rep, est): sum over bins of the product of all vectors; two vectors give the dot product."""
    named = [t.select("rep", "bin", F.col("val").alias(f"v{i}")) for i, t in enumerate(tables)]
    joined = reduce(lambda a, b: a.join(b, ["rep", "bin"]), named)
    return joined.groupBy("rep").agg(F.sum(reduce(lambda a, b: a * b, [F.col(f"v{i}").cast("double") for i in range(len(named))])).alias("est"))


dot = hadamard


def tensor3(a: DataFrame, b: DataFrame, c: DataFrame) -> DataFrame:
    """(rep, est) of the chain a - b - c with b as a matrix over (bin1, bin2)."""
    left = b.join(a.select("rep", F.col("bin").alias("bin1"), F.col("val").alias("va")), ["rep", "bin1"])
    both = left.join(c.select("rep", F.col("bin").alias("bin2"), F.col("val").alias("vc")), ["rep", "bin2"])
    return both.groupBy("rep").agg(F.sum(F.col("va").cast("double") * F.col("val") * F.col("vc")).alias("est"))


def xcorr(a: DataFrame, b: DataFrame, width: int, impl: str = "fft") -> DataFrame:
    """Circular cross-correlation (rep, bin, val): val[k] = sum over i of a[i] b[(i + k) mod width]."""
    if impl == "direct":
        pairs = a.select("rep", F.col("bin").alias("i"), F.col("val").alias("va")).join(b.select("rep", F.col("bin").alias("j"), F.col("val").alias("vb")), "rep")
        out = pairs.groupBy("rep", F.pmod(F.col("j") - F.col("i"), F.lit(width)).cast("int").alias("bin"))
        return out.agg(F.sum(F.col("va").cast("double") * F.col("vb")).alias("val"))
    both = a.select("rep", "bin", F.col("val").cast("double").alias("val"), F.lit(0).alias("side")).union(b.select("rep", "bin", F.col("val").cast("double").alias("val"), F.lit(1).alias("side")))

    def correlate(key, table):
        v = np.zeros((2, width))
        np.add.at(v, (table.column("side").to_numpy(), table.column("bin").to_numpy()), table.column("val").to_numpy())
        out = np.fft.irfft(np.conj(np.fft.rfft(v[0])) * np.fft.rfft(v[1]), width)
        return pa.table({"rep": pa.array([key[0].as_py()] * width, pa.int32()), "bin": pa.array(range(width), pa.int32()), "val": out})

    return both.groupBy("rep").applyInArrow(correlate, "rep int, bin int, val double")


def contract(vectors: dict[str, np.ndarray], classes: dict[str, list[str]], root: str | None = None, spectra: dict[str, np.ndarray] | None = None) -> float:
    """Join size of an acyclic sub-join from dense vectors.  classes: alias -> its shared classes; spectra: transforms of the
    vectors that are known already.

    Messages run along the tree of aliases and classes: a class multiplies what its members send, an alias
    cross-correlates its composite vector with the messages of its other classes.  With ``root`` the tree hangs on that
    alias (degree bounds), else on the class with most members.
    """
    members: dict[str, list[str]] = {}
    for alias, own in classes.items():
        for c in own:
            members.setdefault(c, []).append(alias)
    width = len(next(iter(vectors.values())))

    def from_class(c: str, skip: str) -> np.ndarray:
        out = np.ones(width)
        for alias in members[c]:
            if alias != skip:
                out = out * from_alias(alias, c)
        return out

    def from_alias(alias: str, to: str) -> np.ndarray:
        rest = [c for c in classes[alias] if c != to]
        if not rest:
            return vectors[alias]
        spectrum = spectra[alias] if spectra and alias in spectra else np.fft.rfft(vectors[alias])
        for c in rest:
            spectrum = spectrum * np.conj(np.fft.rfft(from_class(c, alias)))
        return np.fft.irfft(spectrum, width)

    if not members:
        return float(vectors[next(iter(classes))].sum())
    if root is not None:
        if not classes[root]:
            return float(vectors[root].sum())
        first = classes[root][0]
        return float((from_alias(root, first) * from_class(first, root)).sum())
    top = max(sorted(members), key=lambda c: len(members[c]))
    out = np.ones(width)
    for alias in members[top]:
        out = out * from_alias(alias, top)
    return float(out.sum())


def is_acyclic(classes: dict[str, list[str]]) -> bool:
    seen: dict[str, str] = {}

    def find(x: str) -> str:
        while seen.setdefault(x, x) != x:
            x = seen[x]
        return x

    for alias, own in classes.items():
        for c in own:
            a, b = find(f"a:{alias}"), find(f"c:{c}")
            if a == b:
                return False
            seen[a] = b
    return True


def acyclic(rows: DataFrame, plans: dict[str, dict], width: int) -> DataFrame:
    """rows(sub_id, rep, role, alias, bin, val) -> (sub_id, rep, est), all sub-joins of a workload at once.

    plans[sub_id]: {"classes": alias -> classes, "roots": None or the aliases that give one degree-bound term each}.  Roles:
    'main' for the signed or count vector, 'deg:<class>' for a degree vector that faces the class.
    """
    for plan in plans.values():
        if not is_acyclic(plan["classes"]):
            raise ValueError("cyclic join graph: drop an edge or contract tensors")

    def solve(key, table):
        plan = plans[key[0].as_py()]
        role, alias = table.column("role").combine_chunks().dictionary_encode(), table.column("alias").combine_chunks().dictionary_encode()
        names = [(r, a) for r in role.dictionary.to_pylist() for a in alias.dictionary.to_pylist()]
        which = role.indices.to_numpy().astype(np.int64) * len(alias.dictionary) + alias.indices.to_numpy()
        dense = dict(zip(names, _dense(which, len(names), table, width), strict=True))
        zero = np.zeros(width)
        est = estimate(plan, lambda r, a: dense.get((r, a), zero))
        return pa.table({"sub_id": [key[0].as_py()], "rep": pa.array([key[1].as_py()], pa.int32()), "est": [est]})

    return rows.groupBy("sub_id", "rep").applyInArrow(solve, "sub_id string, rep int, est double")


def _dense(which: np.ndarray, n: int, table: pa.Table, width: int) -> list[np.ndarray]:
    """Vector i of the rows (bin, val) whose ``which`` is i, for i below n."""
    order = np.argsort(which, kind="stable")
    cuts = np.searchsorted(which[order], np.arange(1, n))
    bins, vals = table.column("bin").to_numpy()[order], table.column("val").to_numpy()[order]
    return [np.bincount(b, v, width) for b, v in zip(np.split(bins, cuts), np.split(vals, cuts), strict=True)]


def estimate(plan: dict, vector, spectrum=None) -> float:
    """One repetition's estimate of a sub-join.  vector(role, alias) and spectrum(role, alias) give what the plan names.

    A bound is a whole number, and the transforms' rounding error is within the norms of the vectors times a few units of
    precision: rounding down from that much above never falls below it.
    """
    classes = plan["classes"]
    deep = {a for a, own in classes.items() if len(own) > 1} if spectrum else set()
    if not plan.get("roots"):
        return contract({a: vector("main", a) for a in classes}, classes, None, {a: spectrum("main", a) for a in deep})
    terms = []
    for root in plan["roots"]:
        facing = toward(classes, root)
        roles = {a: "main" if a == root else f"deg:{facing[a]}" for a in classes}
        vectors = {a: vector(roles[a], a) for a in classes}
        term = contract(vectors, classes, root, {a: spectrum(roles[a], a) for a in deep})
        if plan.get("integral", True):
            slack = 8 * np.finfo(float).eps * np.log2(max(len(next(iter(vectors.values()))), 2)) * float(np.prod([np.linalg.norm(v) for v in vectors.values()]))
            term = float(np.floor(term + min(slack, 1e-3 * abs(term) + 0.5)))
        terms.append(term)
    return min(terms)


def workload(rows: DataFrame, plans: dict[str, dict[str, dict]], width: int) -> DataFrame:
    """rows(query_id, vec, rep, bins, vals), packed -> (sub_id, rep, est): all sub-joins of a query share its vectors and transforms.

    plans[query_id][sub_id]: as for ``acyclic``, and "vectors": (role, alias) -> vec.
    """
    for subs in plans.values():
        for plan in subs.values():
            if not is_acyclic(plan["classes"]):
                raise ValueError("cyclic join graph: drop an edge or contract tensors")

    def solve(key, table):
        subs, rep = plans[key[0].as_py()], key[1].as_py()
        dense = dict.fromkeys((v for p in subs.values() for v in p["vectors"].values()), np.zeros(width))
        for vec, bins, vals in zip(*(table.column(c).to_pylist() for c in ("vec", "bins", "vals")), strict=True):
            dense[vec] = unpacked(bins, vals, width)
        spectra: dict[int, np.ndarray] = {}

        def spectrum(vec: int) -> np.ndarray:
            if vec not in spectra:
                spectra[vec] = np.fft.rfft(dense[vec])
            return spectra[vec]

        est = [estimate(p, lambda r, a, p=p: dense[p["vectors"][r, a]], lambda r, a, p=p: spectrum(p["vectors"][r, a])) for p in subs.values()]
        return pa.table({"sub_id": list(subs), "rep": pa.array([rep] * len(subs), pa.int32()), "est": est})

    return rows.groupBy("query_id", "rep").applyInArrow(solve, "sub_id string, rep int, est double")


def toward(classes: dict[str, list[str]], root: str) -> dict[str, str]:
    """For each alias but the root the class that leads to it."""
    out, queue = {}, [root]
    while queue:
        alias = queue.pop()
        for c in classes[alias]:
            if out.get(alias) == c:
                continue
            for other, own in classes.items():
                if other != alias and c in own and other not in out and other != root:
                    out[other] = c
                    queue.append(other)
    return out


def reduce_reps(rows: DataFrame, how: str, by: Sequence[str] = ()) -> DataFrame:
    """median, max, q75 or min over repetitions; estimates below 1 count as 1 where ratios need it (see clamp)."""
    agg = {"median": F.median("est"), "max": F.max("est"), "min": F.min("est"), "q75": F.percentile("est", 0.75)}[how]
    return rows.groupBy(*by).agg(agg.alias("est"))


def clamp(rows: DataFrame, least: float = 1.0) -> DataFrame:
    return rows.withColumn("est", F.greatest("est", F.lit(least)))


def split_keys(a: DataFrame, b: DataFrame, rows: int, width: int) -> DataFrame:
    """Composite sketch of two keys kept in different leaves: their circular convolution over the node's row count."""
    both = a.select("rep", "bin", F.col("val").cast("double").alias("val"), F.lit(0).alias("side")).union(b.select("rep", "bin", F.col("val").cast("double").alias("val"), F.lit(1).alias("side")))

    def convolve(key, table):
        v = np.zeros((2, width))
        np.add.at(v, (table.column("side").to_numpy(), table.column("bin").to_numpy()), table.column("val").to_numpy())
        out = np.fft.irfft(np.fft.rfft(v[0]) * np.fft.rfft(v[1]), width) / max(rows, 1)
        return pa.table({"rep": pa.array([key[0].as_py()] * width, pa.int32()), "bin": pa.array(range(width), pa.int32()), "val": out})

    return both.groupBy("rep").applyInArrow(convolve, "rep int, bin int, val double")
