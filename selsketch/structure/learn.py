"""Structure learning on a bounded sample: dependence coefficients, two-way clustering, axis splits that route any row."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..spn.model import Leaf, Product, Relation, Sum, encoded


@dataclass
class Config:
    """threshold < 0 means clustering only; cluster_min = 1 means full independence."""

    threshold: float = 0.0
    cluster_min: float = 0.1
    sample_rows: int = 20_000
    clusterer: str = "hard_em"
    features: int = 20
    spread: float = 1 / 6
    seed: int = 7
    noise_floor: bool = False
    #: Sample rows below which coefficients mean nothing; such a part isn't split, whatever cluster_min is.
    least_rows: int = 50


def sample(df: DataFrame, relation: Relation, rows: int) -> dict[str, np.ndarray]:
    """About ``rows`` rows chosen by a hash of the row, as code and key arrays (nulls are -1)."""
    coded = encoded(df, relation)
    total = coded.count()
    if total > rows:
        coded = coded.where(F.pmod(F.xxhash64(*coded.columns, F.monotonically_increasing_id()), F.lit(1_000_000)) < int(1e6 * rows / total))
    table = coded.toPandas().fillna(-1)  # bounded by the sample size
    return {c: table[c].to_numpy(np.float64) for c in table.columns}


def copula_features(x: np.ndarray, k: int, s: float, rng: np.random.Generator, weight: np.ndarray | None = None) -> np.ndarray:
    """``weight``: how many rows each entry stands for (here and below; none: one)."""
    if weight is None:
        order = np.sort(x)
        u = np.searchsorted(order, x, "right") / len(x)
    else:
        values, at = np.unique(x, return_inverse=True)
        u = (np.cumsum(np.bincount(at, weight, len(values))) / weight.sum())[at]
    return np.sin(np.outer(u, rng.normal(0, s, k)) + rng.normal(0, s, k))


def _white(f: np.ndarray, weight: np.ndarray | None = None) -> np.ndarray:
    """Orthonormal columns that span those of f, from its Gram matrix."""
    f = f - f.mean(0) if weight is None else (f - np.average(f, 0, weight)) * np.sqrt(weight)[:, None]
    d, v = np.linalg.eigh(f.T @ f)
    d = np.sqrt(np.maximum(d, 0))
    keep = d > 1e-4 * d.max(initial=0)
    return f @ (v[:, keep] / d[keep]) if d.max(initial=0) > 0 else f[:, :0]


def _axis(x: np.ndarray, weight: np.ndarray | None = None) -> np.ndarray:
    """Rows along the direction of greatest variance."""
    if weight is not None:
        c = x - np.average(x, 0, weight)
        return c @ np.linalg.eigh(c.T @ (c * weight[:, None]))[1][:, -1]
    c = x - x.mean(0)
    return c @ np.linalg.eigh(c[:5000].T @ c[:5000])[1][:, -1]


def rdc(a: np.ndarray, b: np.ndarray, k: int = 20, s: float = 1 / 6, seed: int = 7, weight: np.ndarray | None = None) -> float:
    """Randomised dependence coefficient in 0..1: largest canonical correlation of random features of the ranks."""
    if (a == a[0]).all() or (b == b[0]).all():
        return 0.0
    rng = np.random.default_rng(seed)
    u, v = _white(copula_features(a, k, s, rng, weight), weight), _white(copula_features(b, k, s, rng, weight), weight)
    if not u.shape[1] or not v.shape[1]:
        return 0.0
    return float(np.clip(np.linalg.svd(u.T @ v, compute_uv=False)[0], 0, 1))


def rdc_matrix(columns: dict[str, np.ndarray], cfg: Config) -> np.ndarray:
    names = list(columns)
    out = np.eye(len(names))
    white = {n: _white(copula_features(c, cfg.features, cfg.spread, np.random.default_rng([cfg.seed, i]))) if len(set(c[:1000])) > 1 or (c != c[0]).any() else np.zeros((len(c), 0)) for i, (n, c) in enumerate(columns.items())}
    for i, a in enumerate(names):
        for j in range(i):
            u, v = white[a], white[names[j]]
            r = float(np.clip(np.linalg.svd(u.T @ v, compute_uv=False)[0], 0, 1)) if u.shape[1] and v.shape[1] else 0.0
            out[i, j] = out[j, i] = r
    if cfg.noise_floor and names:
        rng, first = np.random.default_rng(cfg.seed), columns[names[0]]
        null = [rdc(first, rng.permutation(columns[n]), cfg.features, cfg.spread, t) for t in range(20) for n in names[-1:]]
        out = np.where(out > np.quantile(null, 0.95), out, 0.0)
    return out


def components(matrix: np.ndarray, threshold: float) -> list[list[int]]:
    left, out = set(range(len(matrix))), []
    while left:
        queue, own = [min(left)], set()
        while queue:
            i = queue.pop()
            if i in own:
                continue
            own.add(i)
            queue += [j for j in left if j not in own and matrix[i, j] > threshold]
        left -= own
        out.append(sorted(own))
    return out


def hard_em(x: np.ndarray, rounds: int = 25) -> tuple[np.ndarray, list[float]]:
    """Two clusters of diagonal Gaussians with hard assignment; also the objective after each round."""
    axis = _axis(x)
    label = (axis > np.median(axis)).astype(int)
    trace: list[float] = []
    for _ in range(rounds):
        score = np.empty((len(x), 2))
        for k in (0, 1):
            own = x[label == k]
            if len(own) < max(2, 0.02 * len(x)):
                return (axis > np.median(axis)).astype(int), trace
            var = np.maximum(own.var(0), 1e-6)
            score[:, k] = np.log(len(own) / len(x)) - 0.5 * (np.log(2 * np.pi * var) + (x - own.mean(0)) ** 2 / var).sum(1)
        new = score.argmax(1)
        trace.append(float(score.max(1).sum()))
        moved = (new != label).mean()
        label = new
        if moved < 0.001:
            break
    return label, trace


def k_means(x: np.ndarray, rounds: int = 25, weight: np.ndarray | None = None) -> np.ndarray:
    axis = _axis(x, weight)
    if weight is None:
        middle = np.median(axis)
    else:
        order = np.argsort(axis)
        middle = axis[order[np.searchsorted(np.cumsum(weight[order]), weight.sum() / 2)]]
    label = (axis > middle).astype(int)
    for _ in range(rounds):
        if label.min() == label.max():
            break
        centers = np.stack([np.average(x[label == k], 0, None if weight is None else weight[label == k]) for k in (0, 1)])
        new = ((x[:, None] - centers) ** 2).sum(2).argmin(1)
        if (new == label).all():
            break
        label = new
    return label


def _stump(columns: dict[str, np.ndarray], label: np.ndarray) -> tuple[str, float, np.ndarray] | None:
    """The axis split that agrees best with the clusters: explicit routing for every row of the full table."""
    best = None
    for name, x in columns.items():
        cuts = np.unique(np.quantile(x, np.linspace(0.05, 0.95, 19), method="lower"))
        for t in cuts[cuts < x.max()]:
            left = x <= t
            agree = max((left == (label == 0)).mean(), (left == (label == 1)).mean())
            if best is None or agree > best[0] + 1e-12:
                best = (agree, name, float(t), left)
    return best[1:] if best else None


def learn(columns: dict[str, np.ndarray], relation: Relation, cfg: Config):
    """A tree over the relation's filter attributes and its keys (which stay together in one leaf)."""
    total = len(next(iter(columns.values())))
    keys = tuple(relation.keys)
    code = {f"c_{a}": a for a in relation.encoders}

    def leaf_set(attrs: list[str], with_keys: bool):
        out = [Leaf((code[a],)) for a in attrs] + ([Leaf(keys, key=True)] if with_keys else [])
        return out[0] if len(out) == 1 else Product(out)

    def grow(rows: np.ndarray, attrs: list[str], with_keys: bool):
        if len(attrs) + with_keys <= 1 or not attrs or rows.sum() <= max(cfg.cluster_min * total, cfg.least_rows):
            return leaf_set(attrs, with_keys)
        names = [*attrs, *(keys if with_keys else ())]
        own = {n: columns[n][rows] for n in names}
        matrix = rdc_matrix(own, cfg)
        if with_keys:  # the keys act as one attribute, as dependent as its most dependent member
            k = len(attrs)
            matrix = np.block([[matrix[:k, :k], matrix[:k, k:].max(1, keepdims=True)], [matrix[k:, :k].max(0, keepdims=True), np.ones((1, 1))]])
        if cfg.threshold >= 0:
            parts = components(matrix, cfg.threshold)
            if len(parts) > 1:
                return Product([grow(rows, [attrs[i] for i in p if i < len(attrs)], with_keys and len(attrs) in p) for p in parts])
        rng = np.random.default_rng(cfg.seed)
        x = np.concatenate([copula_features(c, cfg.features, cfg.spread, rng) for c in own.values()], 1)
        if (x.std(0) < 1e-12).all():
            return leaf_set(attrs, with_keys)
        split = _stump(own, {"hard_em": lambda: hard_em(x)[0], "k_means": lambda: k_means(x), "soft_em": lambda: soft_em(x)}[cfg.clusterer]())
        if not split:
            return leaf_set(attrs, with_keys)
        name, cut, left = split
        inside = np.zeros(len(rows), bool)
        inside[np.flatnonzero(rows)[left]] = True
        test = f"{name} <= {int(cut)}"
        return Sum([(test, grow(inside, attrs, with_keys)), ("true", grow(rows & ~inside, attrs, with_keys))])

    return grow(np.ones(total, bool), list(code), True)


def train(df: DataFrame, relation: Relation, cfg: Config):
    return learn(sample(df, relation, cfg.sample_rows), relation, cfg)


def soft_em(x: np.ndarray, rounds: int = 50) -> np.ndarray:
    """Two diagonal Gaussians with soft assignment; rows go to the likelier one at the end."""
    weight = np.eye(2)[k_means(x, 5)].astype(float)
    for _ in range(rounds):
        mass = np.maximum(weight.sum(0), 1e-9)
        mean = weight.T @ x / mass[:, None]
        var = np.maximum(np.stack([(weight[:, k : k + 1] * (x - mean[k]) ** 2).sum(0) / mass[k] for k in (0, 1)]), 1e-6)
        log = np.stack([np.log(mass[k] / len(x)) - 0.5 * (np.log(var[k]) + (x - mean[k]) ** 2 / var[k]).sum(1) for k in (0, 1)], 1)
        new = np.exp(log - log.max(1, keepdims=True))
        new /= new.sum(1, keepdims=True)
        if np.abs(new - weight).max() < 1e-4:
            break
        weight = new
    return weight.argmax(1)
