"""True join sizes from frequency vectors: rows are counted per key before they meet, so no join is ever materialised."""

from __future__ import annotations

from collections.abc import Mapping, Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def frequencies(df: DataFrame, classes: Mapping[str, str], where: str | None = None) -> DataFrame:
    """(one column per class, n) of a relation whose column -> class map is ``classes``."""
    df = df.where(where) if where else df
    named = df.select(*[F.col(c).cast("long").alias(cls) for c, cls in classes.items()])
    return named.dropna().groupBy(*classes.values()).agg(F.count("*").cast("decimal(38,0)").alias("n"))


def cardinality(aliases: Mapping[str, tuple[DataFrame, Mapping[str, str], str | None]]) -> DataFrame:
    """One row (card): size of the join of all aliases, each (table, column -> class, predicate).

    Aliases fold in one at a time; classes that no later alias has are summed out at once.
    """
    parts = [(set(classes.values()), frequencies(df, classes, where)) for df, classes, where in aliases.values()]
    return folded(parts).agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("card"))


def folded(parts: Sequence[tuple[set[str], DataFrame]], mask: str | None = None) -> DataFrame:
    """(n), with ``mask`` (mask, n): the join's size from (classes, counts n by class and mask), folded in along shared classes.
    The bits of a mask are several joins at once; joined rows are in those that all of them are in."""
    order, left = [parts[0]], list(parts[1:])
    while left:
        seen = set().union(*(p[0] for p in order))
        nxt = next((i for i, p in enumerate(left) if p[0] & seen), None)
        if nxt is None:
            raise ValueError("the aliases aren't connected")
        order.append(left.pop(nxt))
    have, out = order[0]
    by, exact = [mask] if mask else [], lambda c: F.col(c).cast("decimal(38,0)")
    for i, (own, table) in enumerate(order[1:], 1):
        later = set().union(*(p[0] for p in order[i + 1 :])) if order[i + 1 :] else set()
        named = [df.withColumnsRenamed({c: f"{c}{j}" for c in ("n", *by)}) for j, df in ((1, out), (2, table))]
        both = named[0].join(named[1], sorted(have & own))
        if mask:
            both = both.withColumn(mask, F.col(f"{mask}1").bitwiseAND(F.col(f"{mask}2"))).where(F.col(mask) != 0)
        have = (have | own) & later
        out = both.groupBy(*by, *sorted(have)).agg(F.sum(exact("n1") * exact("n2")).cast("decimal(38,0)").alias("n"))
    return out if len(order) > 1 else out.groupBy(*by).agg(F.sum("n").cast("decimal(38,0)").alias("n"))


def foj_probability(left: DataFrame, right: DataFrame, key: str, where: str) -> DataFrame:
    """Join size as the size of the full outer join times the share of its rows that match and satisfy the predicate."""
    both = left.withColumn("_l", F.lit(1)).join(right.withColumn("_r", F.lit(1)), key, "full_outer")
    hit = F.col("_l").isNotNull() & F.col("_r").isNotNull() & F.expr(where)
    out = both.agg(F.count("*").alias("foj_size"), F.avg(F.when(hit, 1.0).otherwise(0.0)).alias("probability"))
    return out.withColumn("card", F.round(F.col("foj_size") * F.col("probability")).cast("long"))
