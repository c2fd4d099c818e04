"""Workloads: join graphs, generated queries, connected sub-joins, and estimates of all of them in batch."""

from __future__ import annotations

import random
import re
from collections.abc import Mapping, Sequence
from dataclasses import dataclass, field
from functools import reduce
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.predicates import attributes, parse
from ..operators import contract as C
from ..operators import exact as X
from ..operators.sketch import of_variants, packed, unpacked
from ..spn.model import Model, Variant
from ..store import each, saved


@dataclass(frozen=True)
class Alias:
    """One occurrence of a relation: its table and its join columns, column -> class."""

    name: str
    table: str
    keys: tuple[tuple[str, str], ...]


@dataclass
class Query:
    id: str
    aliases: list[Alias]
    where: dict[str, str] = field(default_factory=dict)

    def classes(self, subset: Sequence[str] | None = None) -> dict[str, list[str]]:
        """alias -> classes that at least two aliases of the subset share."""
        own = {a.name: [c for _, c in a.keys] for a in self.aliases if subset is None or a.name in subset}
        seen = [c for cs in own.values() for c in cs]
        return {a: [c for c in cs if seen.count(c) > 1] for a, cs in own.items()}

    def connected(self, subset: Sequence[str]) -> bool:
        classes = self.classes(subset)
        left, queue = set(subset[1:]), [subset[0]]
        while queue:
            a = queue.pop()
            near = {b for b in left if set(classes[a]) & set(classes[b])}
            left -= near
            queue += near
        return not left

    def subjoins(self) -> list[tuple[str, ...]]:
        names = [a.name for a in self.aliases]
        return [s for n in range(2, len(names) + 1) for s in combinations(names, n) if self.connected(s)]


def path_signs(query: Query, subset: Sequence[str]) -> dict[str, dict[str, tuple[str, ...]]]:
    """alias -> class -> edges whose signs it takes: the members of a class lie on a path in canonical order."""
    out: dict[str, dict[str, tuple[str, ...]]] = {a: {} for a in subset}
    classes = query.classes(subset)
    for c in sorted({c for cs in classes.values() for c in cs}):
        members = [a for a in subset if c in classes[a]]
        for i, a in enumerate(members):
            out[a][c] = tuple(f"{c}#{j}" for j in (i - 1, i) if 0 <= j < len(members) - 1)
    return out


def variants_for(query: Query, subset: Sequence[str], alias: Alias, method: str) -> list[tuple[str, Variant]]:
    """(role, variant) of the sketches that a sub-join needs of one alias."""
    use = query.classes(subset)[alias.name]
    columns = tuple(col for col, c in alias.keys if c in use)
    if method == "sbs":
        signs = path_signs(query, subset)[alias.name]
        own = tuple((col, signs[c]) for col, c in alias.keys if c in use)
        return [("main", Variant("s:" + ";".join(f"{col}:{','.join(e)}" for col, e in own), columns, own))]
    out = [("main", Variant("c:" + ",".join(columns), columns, kind="cm"))]
    return out + [(f"deg:{c}", Variant(f"d:{col}|" + ",".join(columns), columns, facing=col, kind="deg")) for col, c in alias.keys if c in use]


def needed_variants(queries: Sequence[Query], table: str, methods: Sequence[str] = ("sbs", "dbs")) -> list[Variant]:
    found = {v.name: v for q in queries for s in q.subjoins() for a in q.aliases if a.table == table and a.name in s for m in methods for _, v in variants_for(q, s, a, m)}
    return [found[k] for k in sorted(found)]


def sub_id(query: Query, subset: Sequence[str]) -> str:
    return f"{query.id}:{'-'.join(subset)}"


def selections(queries: Sequence[Query]) -> dict[str, list[str]]:
    """table -> its distinct selections ('' where a table isn't filtered)."""
    out: dict[str, list[str]] = {}
    for q in queries:
        for a in q.aliases:
            if (where := q.where.get(a.name, "")) not in out.setdefault(a.table, []):
                out[a.table].append(where)
    return out


def counted(queries: Sequence[Query], tables: Mapping[str, DataFrame]) -> dict[str, DataFrame]:
    """table -> (sel, one column per join column, n), saved: one scan of a table tests all its selections and counts keys."""
    chosen = selections(queries)

    def make(table: str) -> DataFrame:
        found = chosen[table]
        keys = sorted({col for q in queries for a in q.aliases if a.table == table for col, _ in a.keys})
        hits = F.array_compact(F.array(*[F.when(F.expr(s) if s else F.lit(True), F.lit(i)) for i, s in enumerate(found)]))
        rows = tables[table].select(*[F.col(k).cast("long").alias(k) for k in keys], F.explode(hits).alias("sel"))
        return saved(rows.groupBy("sel", *keys).agg(F.count("*").alias("n")), f"counts-{table}")

    return each(tables[next(iter(chosen))].sparkSession, chosen, make) if chosen else {}


#: Selections in a column of bits, and sub-joins that are counted at once.
BITS, AT_ONCE = 60, 16


def _bit(i: int) -> Column:
    return F.shiftrightunsigned(F.col(f"h{i // BITS}"), i % BITS).bitwiseAND(F.lit(1).cast("long"))


@dataclass
class Cells:
    """Rows of each table counted by their join columns and by the selections they are in, bits of h0, h1 and so on, saved.  However
    many selections there are, a row of the table is counted once."""

    chosen: Mapping[str, Sequence[str]]
    rows: Mapping[str, DataFrame]

    def bits(self, table: str, wheres: Sequence[str]) -> Column:
        """Up to BITS selections as one number, the first in its lowest bit."""
        return reduce(Column.bitwiseOR, [F.shiftleft(_bit(self.chosen[table].index(w)), j) for j, w in enumerate(wheres)])

    def within(self, table: str, wheres: Sequence[str]) -> DataFrame:
        """The rows that are in any of the selections."""
        tests = [self.bits(table, wheres[i : i + BITS]) != 0 for i in range(0, len(wheres), BITS)]
        return self.rows[table].where(reduce(Column.__or__, tests))

    def sizes(self) -> dict[tuple[str, str], int]:
        """(table, selection) -> its rows."""
        out = {}
        for t, found in self.chosen.items():
            row = self.rows[t].agg(*[F.sum(_bit(i) * F.col("n")).alias(f"n{i}") for i in range(len(found))]).first()
            out |= {(t, w): row[i] or 0 for i, w in enumerate(found)}
        return out


def cells(queries: Sequence[Query], tables: Mapping[str, DataFrame]) -> Cells:
    """One scan of a table tests all its selections and counts its keys."""
    chosen = selections(queries)

    def make(table: str) -> DataFrame:
        found = chosen[table]
        keys = sorted({col for q in queries for a in q.aliases if a.table == table for col, _ in a.keys})
        flag = lambda s, i: F.when(F.expr(s) if s else F.lit(True), F.lit(1 << i).cast("long")).otherwise(F.lit(0).cast("long"))
        own = {f"h{j}": reduce(Column.bitwiseOR, [flag(s, i) for i, s in enumerate(found[j * BITS : (j + 1) * BITS])]) for j in range(-(-len(found) // BITS))}
        seen = tables[table].select(*[F.col(k).cast("long").alias(k) for k in keys], *[c.alias(h) for h, c in own.items()])
        if "" not in found:
            seen = seen.where(reduce(Column.__or__, [F.col(h) != 0 for h in own]))
        return saved(seen.groupBy(*own, *keys).agg(F.count("*").alias("n")), f"cells-{table}")

    return Cells(chosen, each(tables[next(iter(chosen))].sparkSession, chosen, make) if chosen else {})


def shape(query: Query, subset: Sequence[str]) -> tuple:
    """What sub-joins must share to be counted in one plan: tables and join columns of their aliases."""
    classes = query.classes(subset)
    return tuple((a.name, a.table, tuple((col, c) for col, c in a.keys if c in classes[a.name])) for a in query.aliases if a.name in subset)


def truths(queries: Sequence[Query], tables: Mapping[str, DataFrame], counts: Cells | None = None) -> DataFrame:
    """(sub_id, truth) of every connected sub-join, by frequency vectors, saved.  Sub-joins of one shape share a plan, in which
    the rows of a key are held once for all the sub-joins that they are in."""
    counts = counts or cells(queries, tables)
    shapes: dict[tuple, list[tuple[str, list[str]]]] = {}
    for q in queries:
        for s in q.subjoins():
            shapes.setdefault(shape(q, s), []).append((sub_id(q, s), [q.where.get(a.name, "") for a in q.aliases if a.name in s]))
    spark, parts = next(iter(counts.rows.values())).sparkSession, []
    for own, all_subs in shapes.items():
        for subs in (all_subs[i : i + AT_ONCE] for i in range(0, len(all_subs), AT_ONCE)):
            factors = []
            for i, (_, table, keys) in enumerate(own):
                classes = [c for _, c in keys]
                rows = counts.rows[table].select(*[F.col(col).alias(c) for col, c in keys], counts.bits(table, [w[i] for _, w in subs]).alias("subs"), "n").dropna(subset=classes).where("subs <> 0")
                # rows of several keys rarely have all of them in common
                factors.append((set(classes), rows if len(keys) > 1 else rows.groupBy(*classes, "subs").agg(F.sum("n").alias("n"))))
            names = F.array_compact(F.array(*[F.when(F.col("subs").bitwiseAND(F.lit(1 << j).cast("long")) != 0, F.lit(name)) for j, (name, _) in enumerate(subs)]))
            size = X.folded(factors, "subs").select(F.explode(names).alias("sub_id"), "n").groupBy("sub_id").agg(F.sum("n").alias("n"))
            use = spark.createDataFrame([(name,) for name, _ in subs], "sub_id string")
            parts.append(use.join(size, "sub_id", "left").select("sub_id", F.coalesce(F.col("n").cast("double"), F.lit(0.0)).alias("truth")))
    made = [saved(reduce(DataFrame.union, parts[i : i + 8]), "truths") for i in range(0, len(parts), 8)]
    return reduce(DataFrame.union, made)


def _needs(queries: Sequence[Query], method: str) -> list[tuple[Query, tuple[str, ...], Alias, str, Variant]]:
    return [(q, s, a, role, v) for q in queries for s in q.subjoins() for a in q.aliases if a.name in s for role, v in variants_for(q, s, a, method)]


def exact_sketches(queries: Sequence[Query], counts: Mapping[str, DataFrame], method: str, width: int, reps: int) -> DataFrame:
    """(table, sel, variant, rep, bins, vals), packed: each distinct selection and variant once, from the saved counts."""
    found: dict[str, tuple[dict[str, Variant], dict[str, str]]] = {}
    for _, _, a, _, v in _needs(queries, method):
        variants, keys = found.setdefault(a.table, ({}, {}))
        variants[v.name] = v
        keys.update({k: c for k, c in a.keys if k in v.columns})
    need = _needed(counts, queries, method)
    rows = []
    for t, (variants, keys) in found.items():
        used = counts[t].groupBy("sel", *keys).agg(F.sum("n").alias("n")) if set(keys) < set(counts[t].columns) - {"sel", "n"} else counts[t]
        rows.append(of_variants(used, [variants[k] for k in sorted(variants)], keys, width, reps, "sel").withColumn("table", F.lit(t)))
    return reduce(DataFrame.unionByName, rows).join(F.broadcast(need), ["table", "sel", "variant"], "left_semi").select(*_PACKED)  # a row for each selection and variant


def _needed(counts: Mapping[str, DataFrame], queries: Sequence[Query], method: str) -> DataFrame:
    chosen = selections(queries)
    needed = sorted({(a.table, chosen[a.table].index(q.where.get(a.name, "")), v.name) for q, _, a, _, v in _needs(queries, method)})
    return next(iter(counts.values())).sparkSession.createDataFrame(needed, "table string, sel int, variant string")


def coefficient_rows(queries: Sequence[Query], models: Mapping[str, Model], product: str) -> list[tuple]:
    """(table, sel, leaf, coef) of each distinct selection, however many sub-joins use it."""
    out = []
    for table, found in selections(queries).items():
        for i, where in enumerate(found):
            _, coefs = models[table].coefficients(parse(where) if where else None, product)
            out += [(table, i, leaf, float(c)) for leaf, c in coefs.items() if c]
    return out


def stored(models: Mapping[str, Model]) -> DataFrame:
    """(table, leaf, variant, rep, bins, vals): the leaf sketches of all models, packed."""
    own = {t: packed(m.sketches, "leaf") if m.store is None else m.store for t, m in models.items()}
    return reduce(DataFrame.unionByName, [df.withColumn("table", F.lit(t)) for t, df in own.items()])


def inferred_sketches(store: DataFrame, queries: Sequence[Query], models: Mapping[str, Model], method: str, product: str = "product", merge: str = "sum") -> DataFrame:
    """What exact_sketches gives, inferred from the stored leaves without touching the tables; ``merge``
    is how degrees of leaves add up (sum, or the rejected max).  One weighted sum of dense leaves per variant and repetition."""
    chosen = selections(queries)
    sels: dict[tuple[str, str], set[int]] = {}
    for q, _, a, _, v in _needs(queries, method):
        sels.setdefault((a.table, v.name), set()).add(chosen[a.table].index(q.where.get(a.name, "")))
    coefs: dict[tuple[str, int], list[tuple[int, float]]] = {}
    for table, sel, leaf, c in coefficient_rows(queries, models, product):
        coefs.setdefault((table, sel), []).append((leaf, c))
    width = next(iter(models.values())).width

    def infer(key, rows):
        table, variant, rep = (k.as_py() for k in key)
        dense = {leaf: unpacked(b, v, width) for leaf, b, v in zip(*(rows.column(c).to_pylist() for c in ("leaf", "bins", "vals")), strict=True)}
        most, out = dense.pop(-1, None), []
        for sel in sorted(sels.get((table, variant), ())):
            val = np.zeros(width)
            for leaf, c in coefs.get((table, sel), ()):
                if leaf in dense:
                    val = val + c * dense[leaf] if merge == "sum" else np.maximum(val, c * dense[leaf])
            if most is not None:  # a degree never exceeds that of the whole relation
                val = np.minimum(val, most)
            bins = np.flatnonzero(val).astype(np.int32)
            out.append((table, sel, variant, rep, bins.tobytes(), val[bins].tobytes()))
        return pa.table([pa.array([r[i] for r in out], t) for i, t in enumerate(_TYPES)], names=_PACKED)

    named = store.withColumn("variant", F.regexp_replace("variant", r"\|whole$", "")).where(F.col("variant").isin(sorted({v for _, v in sels})))
    return _spread(named, "table", "variant", "rep").groupBy("table", "variant", "rep").applyInArrow(infer, "table string, sel int, variant string, rep int, bins binary, vals binary")


_PACKED = ["table", "sel", "variant", "rep", "bins", "vals"]
_TYPES = [pa.string(), pa.int32(), pa.string(), pa.int32(), pa.binary(), pa.binary()]


def _spread(rows: DataFrame, *by: str) -> DataFrame:
    """Few rows of much work each: as many parts as there are cores, whatever their bytes."""
    return rows.repartition(4 * rows.sparkSession.sparkContext.defaultParallelism, *by)


def estimates(sketches: DataFrame, queries: Sequence[Query], method: str, width: int, integral: bool) -> DataFrame:
    """(sub_id, rep, est) of every connected sub-join from the sketches of the workload's selections."""
    chosen = selections(queries)
    vectors: dict[str, dict[tuple, int]] = {}
    plans: dict[str, dict[str, dict]] = {}
    for q, s, a, role, v in _needs(queries, method):
        own = vectors.setdefault(q.id, {})
        vec = own.setdefault((a.table, chosen[a.table].index(q.where.get(a.name, "")), v.name), len(own))
        plan = plans.setdefault(q.id, {}).setdefault(sub_id(q, s), {"classes": q.classes(s), "roots": list(s) if method == "dbs" else None, "integral": integral, "vectors": {}})
        plan["vectors"][role, a.name] = vec
    use = sketches.sparkSession.createDataFrame([(i, vec, *key) for i, own in vectors.items() for key, vec in own.items()], "query_id string, vec int, table string, sel int, variant string")
    rows = sketches.join(F.broadcast(use), ["table", "sel", "variant"])  # a row for each query and selection
    return C.workload(_spread(rows.select("query_id", "rep", "vec", "bins", "vals"), "query_id", "rep"), plans, width)


def estimate_exact(queries: Sequence[Query], counts: Mapping[str, DataFrame], method: str, width: int, reps: int) -> DataFrame:
    """(sub_id, rep, est) from sketches built over the filtered tables."""
    return estimates(exact_sketches(queries, counts, method, width, reps), queries, method, width, True)


def estimate_spn(spark: SparkSession, queries: Sequence[Query], models: Mapping[str, Model], method: str, product: str = "product") -> DataFrame:
    """(sub_id, rep, est) without touching the tables: all selections of the workload in one weighted aggregate."""
    return estimates(inferred_sketches(stored(models), queries, models, method, product), queries, method, next(iter(models.values())).width, False)


# templates ------------------------------------------------------------------------------------------------------------

_A = lambda name, table, **keys: Alias(name, table, tuple(keys.items()))
ALIASES = {
    "r": _A("r", "region", r_regionkey="region"),
    "n": _A("n", "nation", n_nationkey="nation", n_regionkey="region"),
    "c": _A("c", "customer", c_custkey="cust", c_nationkey="nation"),
    "s": _A("s", "supplier", s_suppkey="supp", s_nationkey="nation"),
    "p": _A("p", "part", p_partkey="part"),
    "o": _A("o", "orders", o_custkey="cust", o_orderkey="order"),
    "o2": _A("o2", "orders", o_custkey="cust"),
    "l": _A("l", "lineitem", l_orderkey="order", l_partkey="part", l_suppkey="supp"),
    "l2": _A("l2", "lineitem", l_partkey="part"),
    "e": _A("e", "events", user_id="cust"),
    "e2": _A("e2", "events", user_id="cust"),
    "d": _A("d", "documents", doc_id="id"), "lb": _A("lb", "labels", doc_id="id"), "em": _A("em", "embeddings", vec_id="id"),
    "pg": _A("pg", "pages", page_id="id"), "bm": _A("bm", "benchmark", item_id="id"),
    "cv": _A("cv", "conversations", conv_id="conv"), "cv2": _A("cv2", "conversations", conv_id="conv"),
    "os": _A("os", "orders_skew", cust_skew="cust", o_orderkey="order"), "es": _A("es", "events_skew", user_skew="cust"),
    "ls": _A("ls", "lineitem_skew", l_orderkey="order", part_skew="part"), "ps": _A("ps", "part_skew", part_id="part"),
}
STAR = ["c-o", "c-e", "o-e", "c-o-e", "c-o-e-o2", "c-o-e-o2-e2", "p-l", "l-l2", "p-l-l2", "s-l", "n-c", "n-s", "c-s", "n-c-s", "d-lb", "d-lb-em", "d-lb-em-pg-bm", "cv-cv2"]
CHAIN = ["c-o-l", "n-c-o", "n-c-o-l", "r-n-c-o-l", "o-l-p", "o-l-s", "o-l-p-s", "c-o-l-p-s", "n-c-o-l-p-s", "r-n-c-o-l-p-s", "e-c-o-l", "r-n-s-l-p", "n-s-l-o", "e-o-l-p"]
SKEW = ["os-es", "c-os-es", "os-ls-ps", "es-os-ls-ps"]
POOL = {
    "customer": ["c_mktsegment = 'BUILDING'", "c_mktsegment IN ('BUILDING', 'MACHINERY')", "c_acctbal > 2000", "c_acctbal BETWEEN 0 AND 6000"],
    "orders": ["o_orderstatus = 'F'", "o_orderpriority IN ('1-URGENT', '2-HIGH')", "o_totalprice < 250000", "o_orderstatus = 'O' OR o_orderpriority = '5-LOW'"],
    "lineitem": ["l_quantity BETWEEN 10 AND 30", "l_discount >= 0.05", "l_returnflag = 'R'", "l_linenumber <= 3", "l_quantity < 10 OR l_quantity > 40"],
    "part": ["p_size <= 25", "p_size BETWEEN 10 AND 40", "p_retailprice > 950"],
    "supplier": ["s_acctbal > 1000"], "nation": ["n_regionkey <= 2"], "region": [],
    "events": ["event_type = 'purchase'", "event_type IN ('view', 'click')", "value > 20"],
    "documents": ["lang = 'de'", "n_chars < 3000"], "labels": ["quality = 1", "toxic = 0"], "embeddings": ["label <= 5"], "pages": [], "benchmark": [],
    "conversations": ["role = 'system'", "turn >= 2"],
    "orders_skew": ["seg = 'A'", "price_band <= 2", "price_band >= 5"], "events_skew": ["kind_skew = 'view'", "score <= 60", "score >= 80"],
    "lineitem_skew": ["qty_corr <= 12", "qty_corr > 20"], "part_skew": ["price_seg = 'low'", "price_seg = 'high'"],
}
#: Ranges of numeric attributes, from which further predicates are drawn.
RANGES = {
    "customer": {"c_acctbal": (-900, 9900)}, "orders": {"o_totalprice": (1_000, 450_000)}, "lineitem": {"l_quantity": (1, 50), "l_linenumber": (1, 7)},
    "part": {"p_size": (1, 50), "p_retailprice": (900, 1_000)}, "supplier": {"s_acctbal": (-900, 9900)}, "nation": {"n_regionkey": (0, 4)},
    "events": {"value": (0, 100)}, "documents": {"n_chars": (200, 12_000)}, "embeddings": {"label": (0, 9)}, "conversations": {"turn": (0, 7)},
    "orders_skew": {"price_band": (0, 9)}, "events_skew": {"score": (0, 199)}, "lineitem_skew": {"qty_corr": (1, 50)},
}
FILTERS = {t: sorted({*RANGES.get(t, ()), *(a for p in ps for a in attributes(parse(p)))}) for t, ps in POOL.items()}


def predicate(table: str, rng: random.Random) -> str | None:
    """A predicate on a table: one from the pool, a drawn range, or both on different attributes."""
    known, ranges = POOL[table], RANGES.get(table, {})
    first = rng.choice(known) if known and (not ranges or rng.random() < 0.5) else None
    if not ranges or (first and rng.random() < 0.5):
        return first
    attr = rng.choice(sorted(ranges))
    low, high = ranges[attr]
    a, b = sorted(rng.randint(low, high) for _ in range(2))
    drawn = rng.choice([f"{attr} >= {a}", f"{attr} <= {b}", f"{attr} BETWEEN {a} AND {b}"])
    if not first or attr in attributes(parse(first)):
        return drawn
    return f"({first}) AND {drawn}" if " OR " in first else f"{first} AND {drawn}"


def generate(templates: Sequence[str], per_template: int, seed: int = 11, filtered: float = 0.7) -> list[Query]:
    """Queries over templates such as 'c-o-e', each alias filtered with the given probability; the same for a seed."""
    out = []
    for t in templates:
        for i in range(per_template):
            rng = random.Random(f"{seed}|{t}|{i}")
            aliases = [ALIASES[a] for a in t.split("-")]
            where = {a.name: p for a in aliases if rng.random() < filtered and (p := predicate(a.table, rng))}
            if aliases[0].name == "c" and "s" in t.split("-") and "l" in t.split("-"):  # a shared nation would close a cycle
                aliases = [Alias("c", "customer", (("c_custkey", "cust"),)) if a.name == "c" else Alias("s", "supplier", (("s_suppkey", "supp"),)) if a.name == "s" else a for a in aliases]
            elif {"n", "c", "s"} <= {a.name for a in aliases} and "l" in t.split("-"):
                aliases = [Alias("s", "supplier", (("s_suppkey", "supp"),)) if a.name == "s" else a for a in aliases]
            out.append(Query(f"{t}#{i}", aliases, where))
    return out


def read_sql(sql: str) -> Query:
    """SELECT ... FROM table alias, ... WHERE alias.column = alias.column AND ... AND alias.predicate: a Query over TABLES."""
    m = re.fullmatch(r"\s*SELECT\s.+?\sFROM\s(.+?)(?:\sWHERE\s(.+))?\s*;?\s*", sql, re.I | re.S)
    if not m:
        raise ValueError(f"expected SELECT ... FROM ... WHERE ...: {sql!r}")
    tables = {x.split()[-1]: x.split()[0] for x in m[1].split(",")}
    conditions = [x.strip() for x in re.split(r"\sAND\s(?![^(]*\))", re.sub(r"(BETWEEN\s+\S+\s+)AND(\s)", r"\1&\2", m[2] or "", flags=re.I), flags=re.I)] if m[2] else []
    parent: dict[str, str] = {}

    def find(x: str) -> str:
        while parent.setdefault(x, x) != x:
            x = parent[x]
        return x

    where: dict[str, list[str]] = {}
    for c in conditions:
        if pair := re.fullmatch(r"(\w+\.\w+)\s*=\s*(\w+\.\w+)", c):
            parent[find(pair[1])] = find(pair[2])
        else:
            owner = {a for a in re.findall(r"\b(\w+)\.\w+", c) if a in tables}
            if len(owner) != 1:
                raise ValueError(f"a predicate must name one alias: {c!r}")
            (a,) = owner
            where.setdefault(a, []).append(re.sub(rf"\b{a}\.", "", c.replace(" & ", " AND ")))
    keys: dict[str, list[tuple[str, str]]] = {a: [] for a in tables}
    for x in parent:
        keys[x.split(".")[0]].append((x.split(".")[1], find(x).replace(".", "_")))
    return Query("sql", [Alias(a, t, tuple(keys[a])) for a, t in tables.items()], {a: " AND ".join(f"({x})" if " OR " in x.upper() else x for x in xs) for a, xs in where.items()})


WORKLOADS = {"star": (STAR, 4), "chain": (CHAIN, 11), "skew": (SKEW, 10)}


def profile(queries: Sequence[Query]) -> dict[str, int]:
    """Counts of queries, sub-joins, selections with filters and distinct ones."""
    subs = [s for q in queries for s in q.subjoins()]
    sels = [(a.table, q.where[a.name]) for q in queries for s in q.subjoins() for a in q.aliases if a.name in s and a.name in q.where]
    return {"queries": len(queries), "subqueries": len(subs), "selections": len(sels), "distinct_selections": len(set(sels))}


def truth_sql(queries: Sequence[Query], source=lambda table: table) -> str:
    """SQL of ``truths``, written apart: each sub-join as a join of its aliases' counts by key."""
    out = []
    for q in queries:
        for s in q.subjoins():
            classes, names = q.classes(s), [a for a in q.aliases if a.name in s]
            parts = []
            for a in names:
                cols = [(col, c) for col, c in a.keys if c in classes[a.name]]
                where = f" WHERE {q.where[a.name]}" if a.name in q.where else ""
                parts.append((f"(SELECT {', '.join(f'{col} AS {c}_' for col, c in cols)}, count(*)::HUGEINT AS n FROM {source(a.table)}{where} GROUP BY {', '.join(col for col, _ in cols)}) {a.name}_", a))
            done, left = [parts[0][0]], parts[1:]
            have = {c: f"{names[0].name}_" for _, c in names[0].keys if c in classes[names[0].name]}
            while left:  # any alias that shares a class with the ones before
                i = next(i for i, (_, a) in enumerate(left) if any(c in have for c in classes[a.name]))
                sub, a = left.pop(i)
                done.append(f"JOIN {sub} ON " + " AND ".join(f"{have[c]}.{c}_ = {a.name}_.{c}_" for c in classes[a.name] if c in have))
                have |= {c: f"{a.name}_" for c in classes[a.name] if c not in have}
            out.append(f"SELECT '{sub_id(q, s)}' AS sub_id, coalesce(sum({' * '.join(f'{a.name}_.n' for a in names)}), 0)::DOUBLE AS truth FROM {' '.join(done)}")
    return " UNION ALL ".join(out)

