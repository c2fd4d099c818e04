"""Dense sketches of many variants equal those of one at a time; every row reaches one leaf per attribute."""

import pytest
from pyspark.sql import functions as F

from selsketch.operators import sketch as S
from selsketch.queries import models as Q
from selsketch.spn.model import fill, memberships, numbered, owner


@pytest.mark.parametrize("chunk", [7, 1 << 18])
def test_variants_together_equal_each_alone(spark, monkeypatch, chunk):
    monkeypatch.setattr(S, "CHUNK", chunk)
    df = spark.range(3000).select((F.col("id") % 2).cast("int").alias("leaf"), F.when(F.col("id") % 50 > 0, F.pmod(F.col("id") * 7919, F.lit(41)) - 20).alias("a"), (F.col("id") % 13).alias("b"))
    keys, signs = {"a": "x", "b": "y"}, {"a": ["x#0", "x#1"], "b": ["y#0"]}
    counts = df.groupBy("leaf", "a", "b").agg(F.count("*").alias("n"))
    vs = [Q.Variant("s", ("a", "b"), tuple((k, tuple(v)) for k, v in signs.items())), Q.Variant("c", ("a",), kind="cm"), Q.Variant("d", ("a",), facing="a", kind="deg"), Q.Variant("da", ("a", "b"), facing="a", kind="deg"), Q.Variant("db", ("a", "b"), facing="b", kind="deg")]
    got = {}
    for r in S.rows_of_packed(S.of_variants(counts, vs, keys, 16, 2, "leaf"), "leaf").collect():
        got.setdefault(r["variant"], {})[r["leaf"], r["rep"], r["bin"]] = r["val"]
    want = {"s": S.signed(df, keys, signs, 16, 2, by=["leaf"]), "c": S.countmin(df, {"a": "x"}, 16, 2, by=["leaf"]), "d": S.degree(df, {"a": "x"}, "a", 16, 2, by=["leaf"]), "da": S.degree(df, keys, "a", 16, 2, by=["leaf"]), "db": S.degree(df, keys, "b", 16, 2, by=["leaf"])}
    for name, rows in want.items():
        assert got[name] == {(r["leaf"], r["rep"], r["bin"]): float(r["val"]) for r in rows.collect()}, name


def test_a_row_has_one_leaf_per_attribute(spark):
    df = spark.createDataFrame([(i % 7, i % 5 if i % 11 else None, i % 3) for i in range(500)], "k long, v int, w int")
    rel = Q.Relation("t", {"k": "k"}, Q.fit_all(df, {"v": "", "w": ""}), [Q.Variant("cm", ("k",), kind="cm")])
    flat = lambda *a: Q.Product([*[Q.Leaf((x,)) for x in a], Q.Leaf(("k",), key=True)])
    tree = numbered(Q.Product([Q.Sum([("c_w <= 0", Q.Leaf(("w",))), ("true", Q.Leaf(("w",)))]), Q.Sum([("c_v <= 1", flat("v")), ("k <= 3", flat("v")), ("true", flat("v"))])]))
    got, rows = fill(df, rel, tree), Q.populate(df, rel, tree, 8, 1)
    coded = df.select("k", *[e.column().alias(f"c_{a}") for a, e in rel.encoders.items()])
    assert owner(tree, "absent") is None
    for i, (_, test) in memberships(tree).items():
        assert got.rows[i] == coded.where(test).count()
    assert rows.sketch("cm").agg(F.sum("val")).first()[0] == 500 and sum(got.nulls.values()) == df.where("v IS NULL").count()
