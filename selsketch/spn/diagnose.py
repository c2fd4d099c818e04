"""Is a model worth using: its distance to the independence worst case, and the choice between stored and inferred sketches."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.predicates import parse
from ..operators import metrics as M
from ..operators import sketch as S
from .model import Model


def diagnose(model: Model, df: DataFrame, independent: Model, predicates: Sequence[str]) -> dict[str, float]:
    """Mean L1 distance of the inferred count vectors, the same under independence, their ratio (near 1: retrain with
    smaller clusters), and in how many selections the model is worse."""
    variant = next(v for v in model.relation.variants if v.kind == "cm")
    keys = {c: model.relation.keys[c] for c in variant.columns}
    own, worst = [], []
    for p in predicates:
        exact = S.countmin(df, keys, model.width, model.reps, p).withColumn("val", F.col("val").cast("double"))
        own.append(M.l1(exact, model.sketch(variant.name, parse(p))).agg(F.avg("l1")).first()[0] or 0.0)
        worst.append(M.l1(exact, independent.sketch(variant.name, parse(p))).agg(F.avg("l1")).first()[0] or 0.0)
    n = max(len(own), 1)
    return {"l1": sum(own) / n, "worst_l1": sum(worst) / n, "ratio": sum(own) / max(sum(worst), 1e-9), "violations": float(sum(a > b + 1e-6 for a, b in zip(own, worst, strict=True)))}


def source(distinct_selections: int, nonzero_counters: int, model: Model) -> str:
    """'exact' where storing a sketch per distinct selection takes less than the model, else 'spn'."""
    return "exact" if 12 * distinct_selections * nonzero_counters <= model.size_bytes() else "spn"
