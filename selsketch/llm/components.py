"""Connected components of a link table by alternating min-neighbour contraction, all in Spark joins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, hot_join


def components(links: DataFrame, scratch: Scratch, max_rounds: int = 60) -> DataFrame:
    """links(a long, b long) -> (node, component): component is the smallest node reachable.

    Each round makes every node point at the smallest node it knows, then follows pointers once more, so paths shrink
    geometrically.  State lives in written tables.  Nodes without links don't appear; self links and repeats are harmless.
    """
    both = links.select("a", "b").union(links.select("b", "a")).where("a <> b").distinct()
    edges = scratch.save(both, "edges")
    degree = scratch.save(edges.groupBy("a").agg(F.count("*").alias("w")), "degree")
    label = scratch.save(edges.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("l")), "label")
    for _ in range(max_rounds):
        near = hot_join(edges.select(F.col("b").alias("v"), "a"), label.join(degree, "a"), ["a"], "w").groupBy("v").agg(F.min("l").alias("m"))
        step = label.join(near, label.a == near.v).select("a", F.least("l", "m").alias("l"), F.col("l").alias("old"))
        step = scratch.save(step, "step")
        weight = step.groupBy("l").agg(F.count("*").alias("w"))
        heads = scratch.save(weight.join(step.select(F.col("a").alias("l"), F.col("l").alias("top")), "l"), "heads")
        new = hot_join(step, heads, ["l"], "w").select("a", F.least("l", "top").alias("l"), "old")
        new = scratch.save(new, "label")
        scratch.drop(label, step, heads)
        changed = bool(new.where("l <> old").take(1))
        label = new.select("a", "l")
        if not changed:
            return label.select(F.col("a").alias("node"), F.col("l").alias("component"))
    raise RuntimeError("components did not settle")
