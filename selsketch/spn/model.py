"""Sum-product networks whose key leaves hold sketches: declaration, population in one scan, inference without a scan.

A sum node splits its rows by conditions over code columns (``c_<attr>``) and keys; a product node splits its attributes.
Because only one branch below a product holds the keys, an inferred sketch is a linear form over key leaves: a scalar pass
on the driver gives one coefficient per leaf, and one broadcast join with the sketch rows does the rest.
"""

from __future__ import annotations

import json
from collections.abc import Mapping, Sequence
from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.encode import Encoder, Selection
from ..functions.hashing import bucket, bucket_of
from ..functions.predicates import And, Atom, Not, Or, dyadic_cover, signed_terms, to_column
from ..operators import leaf as leaves
from ..operators.sketch import of_variants, rows_of_packed
from ..store import saved

#: Counters of one level of a selectivity leaf; attributes of at most so many codes are counted code by code.
LEAF_WIDTH = 1 << 12
#: The level of the counters of single values.
POINTS = -1


@dataclass
class Leaf:
    attrs: tuple[str, ...]
    key: bool = False
    id: int = -1


@dataclass
class Product:
    children: list


@dataclass
class Sum:
    """children: (condition, node); the first condition that holds routes a row, the last child takes the rest."""

    children: list


@dataclass(frozen=True)
class Variant:
    """One sketch of a relation: which key columns, hashed with which signs; ``facing`` makes it a degree vector."""

    name: str
    columns: tuple[str, ...]
    signs: tuple[tuple[str, tuple[str, ...]], ...] = ()
    facing: str = ""
    kind: str = "sbs"


@dataclass
class Relation:
    name: str
    keys: dict[str, str]
    encoders: dict[str, Encoder] = field(default_factory=dict)
    variants: list[Variant] = field(default_factory=list)
    #: Attributes whose leaves keep every value with its count, so that predicates on them are exact however many values there are.
    whole: tuple[str, ...] = ()


def numbered(tree):
    """Gives leaves their ids, depth first."""
    todo, n = [tree], 0
    while todo:
        node = todo.pop()
        if isinstance(node, Leaf):
            node.id = n
            n += 1
        else:
            todo.extend(reversed([c[1] if isinstance(node, Sum) else c for c in node.children]))
    return tree


def memberships(tree) -> dict[int, tuple[Leaf, Column]]:
    """Leaf id -> (leaf, condition that a row belongs to it)."""
    out = {}

    def walk(node, condition: Column) -> None:
        if isinstance(node, Leaf):
            out[node.id] = (node, condition)
        elif isinstance(node, Product):
            for c in node.children:
                walk(c, condition)
        else:
            rest = condition
            for i, (test, child) in enumerate(node.children):
                hit = F.coalesce(F.expr(test), F.lit(False)) if i < len(node.children) - 1 else F.lit(True)
                walk(child, rest & hit)
                rest = rest & ~hit

    walk(tree, F.lit(True))
    return out


@dataclass
class Model:
    relation: Relation
    tree: object
    width: int
    reps: int
    rows: dict[int, int]
    counters: dict[tuple[int, str], dict[tuple[int, int], int]]
    nulls: dict[tuple[int, str], int]
    sketches: DataFrame
    #: The sketches packed, as they were filled (None after loading or updating).
    store: DataFrame | None = None
    #: (leaf, attr, n) of each attribute that is kept whole.
    values: dict[str, DataFrame] = field(default_factory=dict)

    # selectivities -------------------------------------------------------------------------------------------------

    def selection(self, attr: str, literals: Sequence) -> Selection:
        e = self.relation.encoders[attr]
        return reduce(e.both, [self._selection(e, x) for x in literals], Selection([(0, e.size - 1)]))

    def _selection(self, e: Encoder, x) -> Selection:
        if isinstance(x, Or):
            return reduce(e.either, [self._selection(e, p) for p in x.parts])
        if isinstance(x, And):
            return reduce(e.both, [self._selection(e, p) for p in x.parts])
        return e.inverse(self._selection(e, x.part)) if isinstance(x, Not) else e.select(x.op, x.values)

    def _codes(self, leaf: int, attr: str, lo: int, hi: int) -> float:
        """Rows with a code in lo..hi: from exact counts, or from the count-min counters of the dyadic levels."""
        e, own = self.relation.encoders[attr], self.counters.get((leaf, attr), {})
        if e.size <= LEAF_WIDTH:
            return sum(own.get((0, c), 0) for c in range(lo, hi + 1))
        out = 0
        for level, index in dyadic_cover(lo, hi, e.bits):
            whole = 1 << (e.bits - level) <= LEAF_WIDTH
            out += own.get((level, index if whole else bucket_of(index, f"code@{level}", 0, LEAF_WIDTH)), 0)
        return out

    def _value(self, leaf: int, attr: str, v) -> float:
        e = self.relation.encoders[attr]
        point = self.counters.get((leaf, attr), {}).get((POINTS, bucket_of(e.point_of(v), "point", 0, LEAF_WIDTH)), 0)
        return min(point, self._codes(leaf, attr, c, c)) if (c := e.code_of(v)) is not None else 0

    def leaf_probability(self, leaf: Leaf, attr: str, literals: Sequence) -> float:
        total = self.rows.get(leaf.id, 0)
        if not total:
            return 0.0
        null = [x for x in literals if isinstance(x, Atom) and x.op == "null"]
        solid = [x for x in literals if isinstance(x, Not) and isinstance(x.part, Atom) and x.part.op == "null"]
        rest = [x for x in literals if x not in null and x not in solid]
        missing = self.nulls.get((leaf.id, attr), 0)
        if null:
            return 0.0 if rest or solid else missing / total
        if not rest:
            return (total - missing) / total
        if attr in self.values:
            holds = reduce(lambda a, b: a & b, map(to_column, rest))
            return (self.values[attr].where((F.col("leaf") == leaf.id) & holds).agg(F.sum("n")).first()[0] or 0) / total
        s = self.selection(attr, rest)
        n = sum(self._codes(leaf.id, attr, lo, hi) for lo, hi in s.intervals)
        n += sum(self._value(leaf.id, attr, v) for v in s.more) - sum(self._value(leaf.id, attr, v) for v in s.less)
        return min(1.0, max(0.0, min(n, total - missing) / total))

    def node_rows(self, node) -> int:
        if isinstance(node, Leaf):
            return self.rows.get(node.id, 0)
        return sum(self.node_rows(c) for _, c in node.children) if isinstance(node, Sum) else self.node_rows(node.children[0])

    def coefficients(self, predicate=None, product: str = "product") -> tuple[float, dict[int, float]]:
        """(P(predicate), key leaf id -> coefficient); product = 'min' scales by the smallest sibling selectivity."""
        terms = [(1, [])] if predicate is None else signed_terms(predicate)
        total, coefs = 0.0, {}
        for sign, literals in terms:
            by_attr: dict[str, list] = {}
            for x in literals:
                by_attr.setdefault(_attribute(x), []).append(x)
            p, own = self._pass(self.tree, by_attr, product)
            total += sign * p
            for leaf, c in own.items():
                coefs[leaf] = coefs.get(leaf, 0.0) + sign * c
        return total, coefs

    def _pass(self, node, by_attr: Mapping[str, list], product: str) -> tuple[float, dict[int, float]]:
        if isinstance(node, Leaf):
            if node.key:
                return 1.0, {node.id: 1.0}
            hit = [self.leaf_probability(node, a, by_attr[a]) for a in node.attrs if a in by_attr]
            return reduce(lambda a, b: a * b, hit, 1.0), {}
        if isinstance(node, Product):
            done = [self._pass(c, by_attr, product) for c in node.children]
            join = (lambda ps: reduce(lambda a, b: a * b, ps, 1.0)) if product == "product" else (lambda ps: min(ps, default=1.0))
            coefs = {}
            for i, (_, own) in enumerate(done):
                factor = join([p for j, (p, _) in enumerate(done) if j != i])
                coefs |= {k: v * factor for k, v in own.items()}
            return join([p for p, _ in done]), coefs
        size = self.node_rows(node)
        total, coefs = 0.0, {}
        for _, child in node.children:
            p, own = self._pass(child, by_attr, product)
            total += p * self.node_rows(child) / size if size else 0.0
            coefs |= own  # leaf sketches are raw counts, so children add up unweighted
        return total, coefs

    # sketches ------------------------------------------------------------------------------------------------------

    def sketch(self, variant: str, predicate=None, product: str = "product", clamp: bool = True) -> DataFrame:
        """(rep, bin, val) of the selection."""
        _, coefs = self.coefficients(predicate, product)
        table = self.sketches.sparkSession.createDataFrame([(k, float(v)) for k, v in coefs.items() if v], "leaf int, coef double")
        rows = self.sketches.where(F.col("variant") == variant)
        out = rows.join(F.broadcast(table), "leaf").groupBy("rep", "bin").agg(F.sum(F.col("coef") * F.col("val")).alias("val"))
        kind = next(v for v in self.relation.variants if v.name == variant)
        if kind.facing and clamp:
            most = self.sketches.where(F.col("variant") == f"{variant}|whole").select("rep", "bin", F.col("val").alias("most"))
            out = out.join(most, ["rep", "bin"]).select("rep", "bin", F.least("val", F.col("most").cast("double")).alias("val"))
        return out

    def count(self, predicate=None, product: str = "product") -> float:
        return self.node_rows(self.tree) * self.coefficients(predicate, product)[0]

    def key_leaves(self) -> list[Leaf]:
        return [leaf for leaf, _ in memberships(self.tree).values() if leaf.key]

    # storage -------------------------------------------------------------------------------------------------------

    def save(self, path: str) -> None:
        spark = self.sketches.sparkSession
        for attr, rows in self.values.items():
            rows.write.mode("overwrite").parquet(f"{path}/values/{attr}")
        self.sketches.write.mode("overwrite").partitionBy("variant").parquet(f"{path}/sketches")
        enc = {k: vars(v) for k, v in self.relation.encoders.items()}
        head = {"name": self.relation.name, "keys": self.relation.keys, "whole": list(self.relation.whole), "encoders": enc, "variants": [vars(v) for v in self.relation.variants], "tree": _dump(self.tree), "width": self.width, "reps": self.reps, "rows": list(self.rows.items()), "nulls": [[*k, v] for k, v in self.nulls.items()], "counters": [[*k, *n, c] for k, d in self.counters.items() for n, c in d.items()]}
        spark.createDataFrame([(json.dumps(head, default=str),)], "head string").coalesce(1).write.mode("overwrite").json(f"{path}/head")

    @staticmethod
    def load(spark: SparkSession, path: str) -> Model:
        head = json.loads(spark.read.json(f"{path}/head").first()["head"])
        variants = [Variant(v["name"], tuple(v["columns"]), tuple((a, tuple(b)) for a, b in v["signs"]), v["facing"], v["kind"]) for v in head["variants"]]
        relation = Relation(head["name"], head["keys"], {k: Encoder(**v) for k, v in head["encoders"].items()}, variants, tuple(head["whole"]))
        counters: dict = {}
        for leaf, attr, level, bin_, cnt in head["counters"]:
            counters.setdefault((leaf, attr), {})[level, bin_] = cnt
        return Model(relation, numbered(_undump(head["tree"])), head["width"], head["reps"], {int(k): v for k, v in head["rows"]}, counters, {(a, b): c for a, b, c in head["nulls"]}, spark.read.parquet(f"{path}/sketches"), values={a: spark.read.parquet(f"{path}/values/{a}") for a in relation.whole})

    def size_bytes(self) -> int:
        """Bytes of sparse sketch rows (12 each) and of selectivity counters (8 each)."""
        return 12 * self.sketches.count() + 8 * sum(map(len, self.counters.values()))


def _attribute(x) -> str:
    return _attribute(x.parts[0]) if isinstance(x, And | Or) else _attribute(x.part) if isinstance(x, Not) else x.attr


def _dump(node) -> dict:
    if isinstance(node, Leaf):
        return {"leaf": list(node.attrs), "key": node.key}
    if isinstance(node, Product):
        return {"product": [_dump(c) for c in node.children]}
    return {"sum": [[t, _dump(c)] for t, c in node.children]}


def _undump(x: dict):
    if "leaf" in x:
        return Leaf(tuple(x["leaf"]), x["key"])
    return Product([_undump(c) for c in x["product"]]) if "product" in x else Sum([(t, _undump(c)) for t, c in x["sum"]])


def encoded(df: DataFrame, relation: Relation, points: bool = False, extra: Sequence[Column] = ()) -> DataFrame:
    """Keys and codes c_<attr> of the rows; ``points``: also p_<attr>, the counter of the single value where codes aren't exact."""
    codes = [e.column().alias(f"c_{a}") for a, e in relation.encoders.items()]
    if points:
        codes += [bucket(e.point(), "point", 0, LEAF_WIDTH).alias(f"p_{a}") for a, e in relation.encoders.items() if not e.exact]
    return df.select(*[F.col(k).cast("long").alias(k) for k in relation.keys], *codes, *extra)


@dataclass
class Filled:
    """What a scan leaves of a table: row, null and code counts of the leaves, and ``counts`` (leaf, *keys, n), saved."""

    rows: dict[int, int]
    counters: dict[tuple[int, str], dict[tuple[int, int], int]]
    nulls: dict[tuple[int, str], int]
    counts: DataFrame
    values: dict[str, DataFrame]


def owner(tree, attr: str | None) -> Column | None:
    """The id of the leaf that holds an attribute of a row (None: its keys).  A row reaches one such leaf."""
    if isinstance(tree, Leaf):
        return F.lit(tree.id) if (tree.key if attr is None else not tree.key and attr in tree.attrs) else None
    if isinstance(tree, Product):
        return next((found for c in tree.children if (found := owner(c, attr)) is not None), None)
    below = [(test, owner(child, attr)) for test, child in tree.children]
    if all(c is None for _, c in below):
        return None
    out = below[-1][1] if below[-1][1] is not None else F.lit(None).cast("int")
    for test, c in reversed(below[:-1]):
        out = F.when(F.expr(test), c if c is not None else F.lit(None).cast("int")).otherwise(out)
    return out


def fill(df: DataFrame, relation: Relation, tree) -> Filled:
    """Routes every row once per attribute and counts codes and keys by leaf."""
    rows = encoded(df, relation, True)
    of = [(a, leaf) for a in relation.encoders if (leaf := owner(tree, a)) is not None]
    key = owner(tree, None)
    routed = rows.select(*rows.columns, key.alias("leaf"), *[leaf.alias(f"_l{i}") for i, (_, leaf) in enumerate(of)])
    counts = saved(routed.groupBy("leaf", *relation.keys).agg(F.count("*").alias("n")), "leaf-counts")
    entry = lambda leaf, attr, level, code: F.struct(F.col(leaf).alias("leaf"), F.lit(attr).alias("attr"), F.lit(level).alias("level"), code.alias("code"))
    each = [entry(f"_l{i}", i, 0, F.col(f"c_{a}")) for i, (a, _) in enumerate(of)]
    each += [F.when(F.col(f"p_{a}").isNotNull(), entry(f"_l{i}", i, POINTS, F.col(f"p_{a}"))) for i, (a, _) in enumerate(of) if not relation.encoders[a].exact]
    values = {}
    for a in relation.whole:
        raw = encoded(df, relation, extra=(F.expr(relation.encoders[a].expr or a).alias("_v"),)).select(owner(tree, a).alias("leaf"), F.col("_v").alias(a))
        values[a] = saved(raw.groupBy("leaf", a).agg(F.count("*").alias("n")), "leaf-values")
    out = Filled({leaf.id: 0 for leaf in _leaves(tree)}, {}, {}, counts, values)
    for r in counts.groupBy("leaf").agg(F.sum("n").alias("n")).collect():  # one row per key leaf
        out.rows[r["leaf"]] = r["n"]
    if not each:
        return out
    codes = routed.select(F.explode(F.array_compact(F.array(*each))).alias("x")).groupBy("x.leaf", "x.attr", "x.level", "x.code").agg(F.count("*").alias("n"))
    first = {leaf.id: leaf.attrs[0] for leaf in _leaves(tree) if not leaf.key}
    # the codes of an attribute are bounded (BITS), as are the counters of its single values, so few counters reach the driver
    found = codes.toArrow()
    wide: dict[tuple[int, str], list[tuple[int, int]]] = {}
    for leaf, i, level, code, n in zip(*(found.column(c).to_pylist() for c in ("leaf", "attr", "level", "code", "n")), strict=True):
        attr = of[i][0]
        if level == 0 and first[leaf] == attr:
            out.rows[leaf] += n
        if code is None:
            out.nulls[leaf, attr] = n
        elif level == 0 and relation.encoders[attr].size > LEAF_WIDTH:
            wide.setdefault((leaf, attr), []).append((code, n))
        else:
            out.counters.setdefault((leaf, attr), {})[level, code] = n
    for (leaf, attr), own in wide.items():
        mine = out.counters.setdefault((leaf, attr), {})
        mine |= leaves.dyadic_counters([c for c, _ in own], [n for _, n in own], relation.encoders[attr].bits, LEAF_WIDTH)
    return out


def _leaves(tree) -> list[Leaf]:
    if isinstance(tree, Leaf):
        return [tree]
    return [x for c in tree.children for x in _leaves(c[1] if isinstance(tree, Sum) else c)]


def populate(df: DataFrame, relation: Relation, tree, width: int, reps: int, save_to: str | None = None, filled: Filled | None = None) -> Model:
    """Fills every leaf: key counts per leaf in one shuffle, from which all variants and repetitions derive, and code counts.
    ``filled``: those counts of the same tree and encoders, where another model has them."""
    tree = numbered(tree)
    filled = filled or fill(df, relation, tree)
    store = of_variants(filled.counts, relation.variants, relation.keys, width, reps, "leaf")
    if facing := [replace(v, name=f"{v.name}|whole") for v in relation.variants if v.facing]:
        whole = filled.counts.groupBy(*relation.keys).agg(F.sum("n").alias("n")).withColumn("leaf", F.lit(-1))
        store = store.unionByName(of_variants(whole, facing, relation.keys, width, reps, "leaf"))
    if save_to:
        store.write.mode("overwrite").parquet(save_to)
        store = df.sparkSession.read.parquet(save_to)
    copy = lambda d: {k: dict(v) for k, v in d.items()}
    return Model(relation, tree, width, reps, dict(filled.rows), copy(filled.counters), dict(filled.nulls), rows_of_packed(store, "leaf"), store, dict(filled.values))


def update(model: Model, delta: DataFrame, sign: int = 1) -> Model:
    """The model after inserting (or deleting) the rows of delta.  Degree variants aren't linear; rebuild those."""
    new = populate(delta, model.relation, _undump(_dump(model.tree)), model.width, model.reps)
    degrees = [v.name for v in model.relation.variants if v.facing]
    fresh = new.sketches.withColumn("val", F.col("val") * sign)
    both = model.sketches.unionByName(fresh).where(~F.col("variant").isin([*degrees, *[f"{d}|whole" for d in degrees]]) if degrees else F.lit(True))
    model.store = None
    model.sketches = both.groupBy("leaf", "variant", "rep", "bin").agg(F.sum("val").alias("val")).where("val <> 0")
    for a, rows in new.values.items():
        model.values[a] = model.values[a].unionByName(rows.withColumn("n", F.col("n") * sign)).groupBy("leaf", a).agg(F.sum("n").alias("n"))
    for i, n in new.rows.items():
        model.rows[i] = model.rows.get(i, 0) + sign * n
    for k, n in new.nulls.items():
        model.nulls[k] = model.nulls.get(k, 0) + sign * n
    for k, own in new.counters.items():
        for node, n in own.items():
            mine = model.counters.setdefault(k, {})
            mine[node] = mine.get(node, 0) + sign * n
    return model


__all__ = ["Leaf", "Model", "Product", "Relation", "Sum", "Variant", "encoded", "leaves", "memberships", "numbered", "populate", "update"]
