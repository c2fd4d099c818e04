"""Baselines outside the models: the host's own optimizer with column statistics, and a regression on queries."""

from __future__ import annotations

import contextlib
import io
import re
import uuid
from collections.abc import Iterator, Mapping, Sequence

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from ..functions.predicates import attributes, parse
from ..plans import planner as P
from ..plans import workload as Wl

_SETTINGS = {"spark.sql.cbo.enabled": "true", "spark.sql.cbo.joinReorder.enabled": "true", "spark.sql.cbo.planStats.enabled": "true", "spark.sql.statistics.histogram.enabled": "true"}


@contextlib.contextmanager
def host_statistics(spark: SparkSession, tables: Mapping[str, DataFrame], queries: Sequence[Wl.Query]) -> Iterator[dict[str, DataFrame]]:
    """The tables as catalogue tables with statistics and histograms of every column that the queries join or filter, the
    cost-based optimizer on; both undone after."""
    before = {k: spark.conf.get(k) for k in _SETTINGS}
    mark, made = uuid.uuid4().hex[:8], {}
    used: dict[str, set[str]] = {t: set() for t in tables}
    for a, where in ((a, q.where.get(a.name)) for q in queries for a in q.aliases):
        used[a.table] |= {c.lower() for c in ({col for col, _ in a.keys} | (attributes(parse(where)) if where else set()))}
    try:
        for k, v in _SETTINGS.items():
            spark.conf.set(k, v)
        for name, df in tables.items():
            made[name] = f"host_{mark}_{name}"
            df.select(*[c for c in df.columns if c.lower() in used[name]]).write.saveAsTable(made[name])
            spark.sql(f"ANALYZE TABLE {made[name]} COMPUTE STATISTICS FOR ALL COLUMNS")
        yield {name: spark.table(t) for name, t in made.items()}
    finally:
        for t in made.values():
            spark.sql(f"DROP TABLE IF EXISTS {t}")
        for k, v in before.items():
            spark.conf.set(k, v)


def _explained(df: DataFrame, mode: str) -> str:
    text = io.StringIO()
    with contextlib.redirect_stdout(text):
        df.explain(mode)
    return text.getvalue()


def host_order(q: Wl.Query, tables: Mapping[str, DataFrame]):
    """The tree of joins, nested pairs of aliases, that the optimizer makes of a query whose rows are counted."""
    plan = _explained(P.written(q, tables).groupBy().count(), "extended").split("== Optimized Logical Plan ==")[1].split("== Physical")[0]
    lines = [(len(m[1]), m[2]) for x in plan.splitlines() if (m := re.match(r"([ :+-]*)(\S.*)", x))]

    def tree(i: int):
        """Of the node in line i: joins and aliases alone."""
        end = next((j for j in range(i + 1, len(lines)) if lines[j][0] <= lines[i][0]), len(lines))
        below = [j for j in range(i + 1, end) if lines[j][0] == lines[i + 1][0]]
        if lines[i][1].startswith("Join"):
            return tuple(tree(j) for j in below)
        if any(lines[j][1].startswith("Join") for j in range(i + 1, end)):
            return tree(below[0])
        return re.search(r" AS (\w+?)__", " ".join(x for _, x in lines[i:end]))[1]

    return tree(0)


def host_rows(q: Wl.Query, subset: Sequence[str], tables: Mapping[str, DataFrame]) -> float:
    """The optimizer's row count of a sub-join, as EXPLAIN COST prints it."""
    own = Wl.Query(q.id, [a for a in q.aliases if a.name in subset], q.where)
    found = re.search(r"rowCount=([0-9.E+]+)", _explained(P.written(own, tables), "cost"))
    return float(found[1]) if found else 1.0


def _features(run, q: Wl.Query, subset: Sequence[str], shares: Mapping[tuple[str, str], float], names: Sequence[str]) -> list[float]:
    where = {a.name: shares.get((a.table, q.where.get(a.name, "")), 1.0) for a in q.aliases if a.name in subset}
    return [x for n in names for x in ((1.0, float(np.log(max(where[n], 1e-6)))) if n in where else (0.0, 0.0))]


def examples(queries: Sequence[Wl.Query], per_template: int = 12) -> list[Wl.Query]:
    """Another workload over the same templates (another seed), from which to learn."""
    made = Wl.generate(sorted({q.id.split("#")[0] for q in queries}), per_template, seed=29)
    return [Wl.Query(f"example-{q.id}", q.aliases, q.where) for q in made]


def query_driven(run):
    """Boosted trees on which aliases a sub-join has and how selective their filters are, trained on the true sizes of the run's
    other workload."""
    from pyspark.ml.feature import VectorAssembler
    from pyspark.ml.regression import GBTRegressor
    from pyspark.sql import functions as F

    spark, other = run.spark, run.also
    rows = {t: max(df.count(), 1) for t, df in run.tables.items()}
    known = {(t, w): n / rows[t] for (t, w), n in run.cells.sizes().items()}
    truth = {r["sub_id"]: r["truth"] for r in run.truths.collect()}  # as many rows as sub-joins
    names = sorted({a.name for q in other for a in q.aliases})
    rows = [[*_features(run, q, s, known, names), float(np.log1p(truth[Wl.sub_id(q, s)]))] for q in other for s in q.subjoins()]
    columns = [f"f{i}" for i in range(2 * len(names))]
    ready = VectorAssembler(inputCols=columns, outputCol="features")
    model = GBTRegressor(maxIter=20, maxDepth=4, seed=1).fit(ready.transform(spark.createDataFrame(rows, [*columns, "label"])))
    ask = [(Wl.sub_id(q, s), *_features(run, q, s, known, names)) for q in run.queries for s in q.subjoins()]
    out = model.transform(ready.transform(spark.createDataFrame(ask, ["sub_id", *columns]))).select("sub_id", "prediction").collect()
    found = {r["sub_id"]: float(np.expm1(r["prediction"])) for r in out}
    return lambda q, s: found[Wl.sub_id(q, s)]
