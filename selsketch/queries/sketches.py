"""Queries of hashing, sketches, contraction, estimators and measures, with their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import hashing as H
from ..operators import contract as C
from ..operators import exact as X
from ..operators import leaf as L
from ..operators import metrics as M
from ..operators import sketch as S
from . import oracle as O

W, R = 256, 3
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE: dict[str, str] = {}

#: The custkey hub: customer - orders - events; two join edges on one class.
CUST, ORD, EVT = {"c_custkey": "cust"}, {"o_custkey": "cust"}, {"user_id": "cust"}
SC, SO, SE = {"c_custkey": ["cust#0"]}, {"o_custkey": ["cust#0", "cust#1"]}, {"user_id": ["cust#1"]}
#: The chain customer - orders - lineitem: orders carries two classes.
OCHAIN, LCHAIN = {"o_custkey": "cust", "o_orderkey": "order"}, {"l_orderkey": "order"}
SOCHAIN, SLCHAIN = {"o_custkey": ["cust#0"], "o_orderkey": ["order#0"]}, {"l_orderkey": ["order#0"]}
ORDERS_SKEW = "SELECT o_orderkey, r, {div} AS cust_skew, {band} AS price_band, CASE WHEN r < 300 OR o_orderkey % 10 < 2 THEN 'A' ELSE 'B' END AS seg FROM (SELECT *, (o_orderkey * 7919) % 1000 AS r FROM {orders}) q"
EVENTS_SKEW = "SELECT event_id, r, {div} AS user_skew, {band} * 10 + event_id % 10 AS score, CASE WHEN r < 500 THEN 'view' ELSE event_type END AS kind_skew FROM (SELECT *, (event_id * 6007) % 1000 AS r FROM {events}) q"
LINEITEM_SKEW = "SELECT l_orderkey, l_linenumber, {div} AS part_skew, (l_suppkey % 10) * (l_suppkey % 10) AS supp_skew, (l_suppkey % 10) * 5 + l_linenumber AS qty_corr, l_returnflag, l_discount FROM {lineitem}"
PART_SKEW = "SELECT p_partkey, p_partkey % 1000 AS part_id, CASE WHEN p_retailprice < 925 THEN 'low' WHEN p_retailprice < 975 THEN 'mid' ELSE 'high' END AS price_seg, p_size FROM {part}"
_DIV = {
    "spark": {"o": ("(r * r * r) DIV 1000000", "r DIV 100"), "e": ("(r * r * r) DIV 1000000", "(r DIV 50)"), "l": "(((l_orderkey * 7919) % 1000) * ((l_partkey * 31) % 1000)) DIV 1000"},
    "duck": {"o": ("(r * r * r) // 1000000", "r // 100"), "e": ("(r * r * r) // 1000000", "(r // 50)"), "l": "(((l_orderkey * 7919) % 1000) * ((l_partkey * 31) % 1000)) // 1000"},
}


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def view(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the derived skewed views."""
    base = {"orders_skew": "orders", "events_skew": "events", "lineitem_skew": "lineitem", "part_skew": "part"}[name]
    return spark.sql(view_sql(name, "spark").replace(f"FROM {base}", "FROM {src}"), src=read(spark, sf_dir, base))


def view_sql(name: str, engine: str = "duck") -> str:
    d = _DIV[engine]
    if name == "orders_skew":
        return ORDERS_SKEW.format(div=d["o"][0], band=d["o"][1], orders="orders")
    if name == "events_skew":
        return EVENTS_SKEW.format(div=d["e"][0], band=d["e"][1], events="events")
    return LINEITEM_SKEW.format(div=d["l"], lineitem="lineitem") if name == "lineitem_skew" else PART_SKEW.format(part="part")


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLE[name] = sql
        return f

    return add


def _long(df: DataFrame, *cols: str) -> DataFrame:
    return df.withColumns({c: F.col(c).cast("long") for c in cols or ("val",)})


_cast = lambda body, cols="rep, bin, val::BIGINT AS val": f"SELECT {cols} FROM ({body}) z"

# hashing --------------------------------------------------------------------------------------------------------------


@query("hash_bucket", f"SELECT c_custkey, {', '.join(f'{O.bucket('c_custkey', 'cust', r, W)}::INTEGER AS b{r}' for r in range(R))} FROM customer")
def hash_bucket(spark, d):
    return read(spark, d, "customer").select("c_custkey", *[H.bucket(F.col("c_custkey"), "cust", r, W).alias(f"b{r}") for r in range(R)])


@query("hash_sign", f"SELECT c_custkey, {', '.join(f'{O.sign('c_custkey', 'cust#0', r)}::BIGINT AS s{r}' for r in range(R))} FROM customer")
def hash_sign(spark, d):
    return read(spark, d, "customer").select("c_custkey", *[H.sign(F.col("c_custkey"), "cust#0", r).alias(f"s{r}") for r in range(R)])


@query("hash_composite", f"SELECT o_orderkey, ({O.bins(OCHAIN, 0, W)})::INTEGER AS b FROM orders")
def hash_composite(spark, d):
    return read(spark, d, "orders").select("o_orderkey", S.bin_of(OCHAIN, 0, W).alias("b"))


_SEED = "((('0x' || substr(md5('42|bucket|' || c_mktsegment || '|' || rep || '|' || i), 1, 8))::BIGINT >> 1) % 2147483647)"


@query("hash_seeds", f"SELECT c_custkey, rep::INTEGER AS rep, i::INTEGER AS i, {_SEED} AS coef FROM customer, range({R}) a(rep), range(2) b(i)")
def hash_seeds(spark, d):
    """The seeds of the bucket family that is named after each customer's segment."""
    seeds = F.array(*[F.struct(F.lit(r).alias("rep"), F.lit(i).alias("i"), H.seed("bucket", F.col("c_mktsegment"), r, i).alias("coef")) for r in range(R) for i in range(2)])
    return read(spark, d, "customer").select("c_custkey", F.explode(seeds).alias("s")).select("c_custkey", "s.rep", "s.i", "s.coef")


@query("encode_attributes", "SELECT o_orderkey, dense_rank() OVER (ORDER BY o_orderpriority) - 1 AS prio, ('0x' || substr(md5(o_orderstatus), 1, 8))::BIGINT AS status, date_diff('day', DATE '1995-01-01', o_orderdate::DATE) AS day FROM orders")
def encode_attributes(spark, d):
    from ..functions.encode import fit

    o = read(spark, d, "orders")
    prio = fit(o, "o_orderpriority")
    return o.select("o_orderkey", prio.column().cast("long").alias("prio"), H.portable_hash(F.col("o_orderstatus")).alias("status"), F.datediff("o_orderdate", F.lit("1995-01-01")).cast("long").alias("day"))


# sketches -------------------------------------------------------------------------------------------------------------


@query("sbs_vector", _cast(O.sketch("SELECT o_custkey FROM orders WHERE o_orderstatus = 'F'", ORD, W, R, {"o_custkey": ["cust#0"]})))
def sbs_vector(spark, d):
    return S.signed(read(spark, d, "orders"), ORD, {"o_custkey": ["cust#0"]}, W, R, "o_orderstatus = 'F'")


_SIGN3 = {r: O.sign("c_custkey", "cust#0", r) for r in range(R)}


@query("sbs_frequency", f"""WITH s AS ({O.sketch('SELECT o_custkey FROM orders', ORD, W, R, {'o_custkey': ['cust#0']})}),
v AS ({' UNION ALL '.join(f"SELECT c_custkey, {r} AS rep, {O.bucket('c_custkey', 'cust', r, W)} AS bin, {_SIGN3[r]} AS sg FROM customer" for r in range(R))})
SELECT c_custkey, median((coalesce(val, 0) * sg)::DOUBLE) AS freq FROM v LEFT JOIN s USING (rep, bin) GROUP BY c_custkey""")
def sbs_frequency(spark, d):
    rows = S.signed(read(spark, d, "orders"), ORD, {"o_custkey": ["cust#0"]}, W, R)
    return S.frequency(rows, read(spark, d, "customer"), "c_custkey", "cust", "cust#0", W, R).withColumn("freq", F.col("freq").cast("double"))


def _join2_sql(a: str, b: str) -> str:
    return f"WITH a AS ({a}), b AS ({b}) SELECT rep, sum(a.val::DOUBLE * b.val) AS est FROM a JOIN b USING (rep, bin) GROUP BY rep"


@query("sbs_join2", _join2_sql(O.sketch("SELECT o_custkey FROM orders", ORD, W, R, {"o_custkey": ["cust#1"]}), O.sketch("SELECT user_id FROM events WHERE event_type = 'purchase'", EVT, W, R, SE)))
def sbs_join2(spark, d):
    return C.dot([S.signed(read(spark, d, "orders"), ORD, {"o_custkey": ["cust#1"]}, W, R), S.signed(read(spark, d, "events"), EVT, SE, W, R, "event_type = 'purchase'")])


_HUB = [("customer", CUST, SC), ("orders", ORD, SO), ("events", EVT, SE)]
_HUB_SQL = "WITH " + ", ".join(f"t{i} AS ({O.sketch(f'SELECT {next(iter(k))} FROM {t}', k, W, R, s)})" for i, (t, k, s) in enumerate(_HUB))


def hub(spark, d, kind: str = "signed") -> list[DataFrame]:
    return [S.signed(read(spark, d, t), k, s, W, R) if kind == "signed" else S.countmin(read(spark, d, t), k, W, R) if kind == "cm" else S.degree(read(spark, d, t), k, next(iter(k)), W, R) for t, k, s in _HUB]


@query("sbs_transitive3", _HUB_SQL + " SELECT rep, sum(t0.val::DOUBLE * t1.val * t2.val) AS est FROM t0 JOIN t1 USING (rep, bin) JOIN t2 USING (rep, bin) GROUP BY rep")
def sbs_transitive3(spark, d):
    return C.hadamard(hub(spark, d))


@query("sbs_matrix", _cast(O.tensor("SELECT * FROM orders", OCHAIN, 64, 2, SOCHAIN), "rep, bin1, bin2, val::BIGINT AS val"))
def sbs_matrix(spark, d):
    return S.tensor(read(spark, d, "orders"), OCHAIN, 64, 2, SOCHAIN)


_T3 = f"WITH b AS ({O.tensor('SELECT * FROM orders', OCHAIN, 64, 2, SOCHAIN)}), a AS ({O.sketch('SELECT c_custkey FROM customer', CUST, 64, 2, SC)}), c AS ({O.sketch('SELECT l_orderkey FROM lineitem', LCHAIN, 64, 2, SLCHAIN)}) "


@query("sbs_tensor3", _T3 + "SELECT b.rep, sum(a.val::DOUBLE * b.val * c.val) AS est FROM b JOIN a ON a.rep = b.rep AND a.bin = b.bin1 JOIN c ON c.rep = b.rep AND c.bin = b.bin2 GROUP BY b.rep")
def sbs_tensor3(spark, d):
    a, c = S.signed(read(spark, d, "customer"), CUST, SC, 64, 2), S.signed(read(spark, d, "lineitem"), LCHAIN, SLCHAIN, 64, 2)
    return C.tensor3(a, S.tensor(read(spark, d, "orders"), OCHAIN, 64, 2, SOCHAIN), c)


@query("sbs_convolved", _cast(O.sketch("SELECT * FROM orders", OCHAIN, W, R, SOCHAIN)))
def sbs_convolved(spark, d):
    return S.signed(read(spark, d, "orders"), OCHAIN, SOCHAIN, W, R)


def _chain(spark, d, w=W, reps=R):
    return S.signed(read(spark, d, "customer"), CUST, SC, w, reps), S.signed(read(spark, d, "orders"), OCHAIN, SOCHAIN, w, reps), S.signed(read(spark, d, "lineitem"), LCHAIN, SLCHAIN, w, reps)


_CH = f"WITH a AS ({O.sketch('SELECT c_custkey FROM customer', CUST, W, R, SC)}), b AS ({O.sketch('SELECT * FROM orders', OCHAIN, W, R, SOCHAIN)}), c AS ({O.sketch('SELECT l_orderkey FROM lineitem', LCHAIN, W, R, SLCHAIN)}) "
_XC = _CH + f"SELECT a.rep, ((b.bin - a.bin + {W}) % {W})::INTEGER AS bin, round(sum(a.val::DOUBLE * b.val)) + 0.0 AS val FROM a JOIN b USING (rep) GROUP BY 1, 2"


@query("xcorr_direct", _XC)
def xcorr_direct(spark, d):
    a, b, _ = _chain(spark, d)
    return C.xcorr(a, b, W, "direct").withColumn("val", F.round("val") + 0.0)


@query("xcorr_fft", _XC)
def xcorr_fft(spark, d):
    a, b, _ = _chain(spark, d)
    return C.xcorr(a, b, W).withColumn("val", F.round("val") + 0.0)


@query("sbs_chain3", _CH + f"SELECT a.rep, round(sum(a.val::DOUBLE * c.val * b.val)) AS est FROM a JOIN c USING (rep) JOIN b ON b.rep = a.rep AND b.bin = (a.bin + c.bin) % {W} GROUP BY a.rep")
def sbs_chain3(spark, d):
    a, b, c = _chain(spark, d)
    return C.dot([C.xcorr(a, b, W), c]).withColumn("est", F.round("est"))


@query("sbs_acyclic", ORACLE["sbs_chain3"].replace("a.rep, round", "'c-o-l' AS sub_id, a.rep, round"))
def sbs_acyclic(spark, d):
    rows = [t.select(F.lit("c-o-l").alias("sub_id"), "rep", F.lit("main").alias("role"), F.lit(n).alias("alias"), "bin", "val") for n, t in zip("col", _chain(spark, d), strict=True)]
    plans = {"c-o-l": {"classes": {"c": ["cust"], "o": ["cust", "order"], "l": ["order"]}, "roots": None}}
    return C.acyclic(rows[0].union(rows[1]).union(rows[2]), plans, W).withColumn("est", F.round("est"))


# degree bounds --------------------------------------------------------------------------------------------------------


@query("cm_vector", _cast(O.sketch("SELECT user_id FROM events", EVT, W, R)))
def cm_vector(spark, d):
    return S.countmin(read(spark, d, "events"), EVT, W, R)


@query("degree_vector", _cast(O.degree("SELECT user_id FROM events", EVT, "user_id", W, R)))
def degree_vector(spark, d):
    return S.degree(read(spark, d, "events"), EVT, "user_id", W, R)


@query("degree_vector_directed", _cast(O.degree("SELECT * FROM orders", OCHAIN, "o_custkey", W, R)))
def degree_vector_directed(spark, d):
    return S.degree(read(spark, d, "orders"), OCHAIN, "o_custkey", W, R)


_D2 = f"WITH ca AS ({O.sketch('SELECT o_custkey FROM orders', ORD, W, R)}), da AS ({O.degree('SELECT o_custkey FROM orders', ORD, 'o_custkey', W, R)}), cb AS ({O.sketch('SELECT user_id FROM events', EVT, W, R)}), db AS ({O.degree('SELECT user_id FROM events', EVT, 'user_id', W, R)}) "


@query("dbs_join2", _D2 + "SELECT rep, least(sum(ca.val::DOUBLE * db.val), sum(da.val::DOUBLE * cb.val)) AS est FROM ca JOIN da USING (rep, bin) JOIN cb USING (rep, bin) JOIN db USING (rep, bin) GROUP BY rep")
def dbs_join2(spark, d):
    o, e = read(spark, d, "orders"), read(spark, d, "events")
    one = C.dot([S.countmin(o, ORD, W, R), S.degree(e, EVT, "user_id", W, R)])
    two = C.dot([S.degree(o, ORD, "o_custkey", W, R), S.countmin(e, EVT, W, R)])
    return one.union(two).groupBy("rep").agg(F.min("est").alias("est"))


def _terms_sql() -> str:
    ctes = ", ".join(f"c{i} AS ({O.sketch(f'SELECT {next(iter(k))} FROM {t}', k, W, R)}), d{i} AS ({O.degree(f'SELECT {next(iter(k))} FROM {t}', k, next(iter(k)), W, R)})" for i, (t, k, _) in enumerate(_HUB))
    terms = " UNION ALL ".join(f"SELECT rep, sum({' * '.join(('c' if i == j else 'd') + str(i) + '.val' + ('::DOUBLE' if not i else '') for i in range(3))}) AS est FROM " + " JOIN ".join(("c" if i == j else "d") + str(i) + (" USING (rep, bin)" if i else "") for i in range(3)) + " GROUP BY rep" for j in range(3))
    return f"WITH {ctes} SELECT rep, min(est) AS est FROM ({terms}) t GROUP BY rep"


@query("dbs_transitive3", _terms_sql())
def dbs_transitive3(spark, d):
    cm, deg = hub(spark, d, "cm"), hub(spark, d, "deg")
    terms = [C.hadamard([cm[i] if i == j else deg[i] for i in range(3)]) for j in range(3)]
    return terms[0].union(terms[1]).union(terms[2]).groupBy("rep").agg(F.min("est").alias("est"))


def _dbs_tensor_sql() -> str:
    w, r = 64, 2
    parts = {"ca": O.sketch("SELECT c_custkey FROM customer", CUST, w, r), "da": O.degree("SELECT c_custkey FROM customer", CUST, "c_custkey", w, r), "cb": O.tensor("SELECT * FROM orders", OCHAIN, w, r), "db1": O.tensor("SELECT * FROM orders", OCHAIN, w, r, facing="o_custkey"), "db2": O.tensor("SELECT * FROM orders", OCHAIN, w, r, facing="o_orderkey"), "cc": O.sketch("SELECT l_orderkey FROM lineitem", LCHAIN, w, r), "dc": O.degree("SELECT l_orderkey FROM lineitem", LCHAIN, "l_orderkey", w, r)}
    term = lambda a, b, c: f"SELECT {b}.rep, sum({a}.val::DOUBLE * {b}.val * {c}.val) AS est FROM {b} JOIN {a} ON {a}.rep = {b}.rep AND {a}.bin = {b}.bin1 JOIN {c} ON {c}.rep = {b}.rep AND {c}.bin = {b}.bin2 GROUP BY {b}.rep"
    return "WITH " + ", ".join(f"{k} AS ({v})" for k, v in parts.items()) + f" SELECT rep, min(est) AS est FROM ({term('ca', 'db1', 'dc')} UNION ALL {term('da', 'cb', 'dc')} UNION ALL {term('da', 'db2', 'cc')}) t GROUP BY rep"


@query("dbs_tensor3", _dbs_tensor_sql())
def dbs_tensor3(spark, d):
    c, o, li = (read(spark, d, t) for t in ("customer", "orders", "lineitem"))
    w, r = 64, 2
    ca, da, cc, dc = S.countmin(c, CUST, w, r), S.degree(c, CUST, "c_custkey", w, r), S.countmin(li, LCHAIN, w, r), S.degree(li, LCHAIN, "l_orderkey", w, r)
    terms = [C.tensor3(ca, S.tensor(o, OCHAIN, w, r, facing="o_custkey"), dc), C.tensor3(da, S.tensor(o, OCHAIN, w, r), dc), C.tensor3(da, S.tensor(o, OCHAIN, w, r, facing="o_orderkey"), cc)]
    return terms[0].union(terms[1]).union(terms[2]).groupBy("rep").agg(F.min("est").alias("est"))


def _dbs_chain_sql() -> str:
    parts = {"ca": O.sketch("SELECT c_custkey FROM customer", CUST, W, R), "da": O.degree("SELECT c_custkey FROM customer", CUST, "c_custkey", W, R), "cb": O.sketch("SELECT * FROM orders", OCHAIN, W, R), "db1": O.degree("SELECT * FROM orders", OCHAIN, "o_custkey", W, R), "db2": O.degree("SELECT * FROM orders", OCHAIN, "o_orderkey", W, R), "cc": O.sketch("SELECT l_orderkey FROM lineitem", LCHAIN, W, R), "dc": O.degree("SELECT l_orderkey FROM lineitem", LCHAIN, "l_orderkey", W, R)}
    term = lambda a, b, c: f"SELECT {a}.rep, sum({a}.val::DOUBLE * {b}.val * {c}.val) AS est FROM {a} JOIN {c} ON {c}.rep = {a}.rep JOIN {b} ON {b}.rep = {a}.rep AND {b}.bin = ({a}.bin + {c}.bin) % {W} GROUP BY {a}.rep"
    return "WITH " + ", ".join(f"{k} AS ({v})" for k, v in parts.items()) + f" SELECT 'c-o-l' AS sub_id, rep, min(est) AS est FROM ({term('ca', 'db1', 'dc')} UNION ALL {term('da', 'cb', 'dc')} UNION ALL {term('da', 'db2', 'cc')}) t GROUP BY rep"


@query("dbs_chain3_conv", _dbs_chain_sql())
def dbs_chain3_conv(spark, d):
    return C.acyclic(dbs_chain_rows(spark, d), {"c-o-l": {"classes": {"c": ["cust"], "o": ["cust", "order"], "l": ["order"]}, "roots": ["c", "o", "l"]}}, W)


def dbs_chain_rows(spark, d):
    c, o, li = (read(spark, d, t) for t in ("customer", "orders", "lineitem"))
    parts = [("c", "main", S.countmin(c, CUST, W, R)), ("c", "deg:cust", S.degree(c, CUST, "c_custkey", W, R)), ("o", "main", S.countmin(o, OCHAIN, W, R)), ("o", "deg:cust", S.degree(o, OCHAIN, "o_custkey", W, R)), ("o", "deg:order", S.degree(o, OCHAIN, "o_orderkey", W, R)), ("l", "main", S.countmin(li, LCHAIN, W, R)), ("l", "deg:order", S.degree(li, LCHAIN, "l_orderkey", W, R))]
    out = None
    for a, role, t in parts:
        t = t.select(F.lit("c-o-l").alias("sub_id"), "rep", F.lit(role).alias("role"), F.lit(a).alias("alias"), "bin", "val")
        out = t if out is None else out.union(t)
    return out


@query("cm_join_bound", _join2_sql(O.sketch("SELECT o_custkey FROM orders", ORD, W, R), O.sketch("SELECT user_id FROM events", EVT, W, R)))
def cm_join_bound(spark, d):
    return C.dot([S.countmin(read(spark, d, "orders"), ORD, W, R), S.countmin(read(spark, d, "events"), EVT, W, R)])


@query("cm_point", f"WITH s AS ({O.sketch('SELECT user_id FROM events', EVT, 64, 1)}) SELECT DISTINCT user_id, val::BIGINT AS freq FROM events JOIN s ON s.bin = {O.bucket('user_id', 'cust', 0, 64)}")
def cm_point(spark, d):
    e = read(spark, d, "events")
    return S.point(S.countmin(e, EVT, 64, 1), e, "user_id", "cust", 64, 1)


_HALF = "SELECT o_custkey FROM orders WHERE o_orderkey % 2 = {}"


@query("sketch_merge_linear", f"SELECT rep, bin, sum(val)::BIGINT AS val FROM ({O.sketch('SELECT o_custkey FROM orders', ORD, W, R, {'o_custkey': ['cust#0']})}) t GROUP BY rep, bin")
def sketch_merge_linear(spark, d):
    o, s = read(spark, d, "orders"), {"o_custkey": ["cust#0"]}
    return S.add(S.signed(o, ORD, s, W, R, "o_orderkey % 2 = 0"), S.signed(o, ORD, s, W, R, "o_orderkey % 2 <> 0"))


def _halves(spark, d):
    o = read(spark, d, "orders")
    return [S.degree(o, ORD, "o_custkey", W, R, f"o_orderkey % 2 = {i}") for i in (0, 1)]


_HALVES = " UNION ALL ".join(O.degree(_HALF.format(i), ORD, "o_custkey", W, R) for i in (0, 1))


@query("degree_merge_sum", f"SELECT rep, bin, sum(val)::BIGINT AS val FROM ({_HALVES}) t GROUP BY rep, bin")
def degree_merge_sum(spark, d):
    return S.merge_degree(_halves(spark, d), "sum")


@query("degree_merge_max", f"SELECT rep, bin, max(val)::BIGINT AS val FROM ({_HALVES}) t GROUP BY rep, bin")
def degree_merge_max(spark, d):
    return S.merge_degree(_halves(spark, d), "max")


@query("degree_clamp", f"WITH m AS (SELECT rep, bin, sum(val) AS v FROM ({_HALVES}) t GROUP BY rep, bin), w AS ({O.degree('SELECT o_custkey FROM orders', ORD, 'o_custkey', W, R)}) SELECT rep, bin, least(v, coalesce(w.val, 0))::BIGINT AS val FROM m LEFT JOIN w USING (rep, bin)")
def degree_clamp(spark, d):
    return S.merge_degree(_halves(spark, d), "sum", S.degree(read(spark, d, "orders"), ORD, "o_custkey", W, R))


@query("sketch_density", f"SELECT rep, count(*) AS nnz, round(count(*) / {W}::DOUBLE, 6) AS density FROM ({O.sketch('SELECT user_id FROM events', EVT, W, R)}) t GROUP BY rep")
def sketch_density(spark, d):
    return S.density(S.countmin(read(spark, d, "events"), EVT, W, R), W)


@query("sketch_dense", f"WITH s AS ({O.sketch('SELECT user_id FROM events', EVT, W, R)}) SELECT g.rep::INTEGER AS rep, g.bin::INTEGER AS bin, coalesce(val, 0)::BIGINT AS val FROM (SELECT rep, bin FROM range({R}) a(rep), range({W}) b(bin)) g LEFT JOIN s USING (rep, bin)")
def sketch_dense(spark, d):
    return S.densify(S.countmin(read(spark, d, "events"), EVT, W, R), W, R)


@query("dyadic_countmin", "SELECT level::INTEGER AS level, (l_quantity::BIGINT >> level)::INTEGER AS bin, count(*) AS cnt FROM lineitem, range(7) r(level) GROUP BY ALL")
def dyadic_countmin(spark, d):
    return L.dyadic(read(spark, d, "lineitem").select(F.col("l_quantity").cast("int").alias("q")), "q", 6, 64)


#: A code range of 6 bits of each customer, and the largest dyadic blocks inside each range.
RANGES = "c_nationkey AS lo, c_nationkey + c_custkey % 39 AS hi"
_INSIDE = lambda size, idx: f"({idx}) * ({size}) >= lo AND (({idx}) + 1) * ({size}) - 1 <= hi"
COVERS = f"SELECT lo, hi, level::INTEGER AS level, idx FROM (SELECT DISTINCT {RANGES} FROM customer) r, range(7) a(level), range(64) b(idx) WHERE {_INSIDE('1 << level', 'idx')} AND NOT (level < 6 AND {_INSIDE('2 << level', 'idx // 2')})"


@query("dyadic_cover", f"SELECT c_custkey AS id, level, idx FROM (SELECT c_custkey, {RANGES} FROM customer) c JOIN ({COVERS}) v USING (lo, hi)")
def dyadic_cover_query(spark, d):
    return L.covers(read(spark, d, "customer").selectExpr("c_custkey AS id", *RANGES.split(", ")), 6)


@query("range_dyadic", "SELECT count(*) AS cnt FROM lineitem WHERE l_quantity BETWEEN 10 AND 37")
def range_dyadic(spark, d):
    return L.range_sum(dyadic_countmin(spark, d), 10, 37, 6)


@query("range_enumerated", "SELECT count(*) AS cnt FROM lineitem WHERE l_quantity BETWEEN 10 AND 37")
def range_enumerated(spark, d):
    return L.range_sum(dyadic_countmin(spark, d), 10, 37, 6, "enumerate")


# exact sizes ----------------------------------------------------------------------------------------------------------


@query("exact_card_star", "SELECT count(*) AS card FROM customer JOIN orders ON c_custkey = o_custkey JOIN events ON user_id = c_custkey WHERE event_type = 'purchase' AND o_orderstatus = 'F'")
def exact_card_star(spark, d):
    return X.cardinality({"c": (read(spark, d, "customer"), CUST, None), "o": (read(spark, d, "orders"), ORD, "o_orderstatus = 'F'"), "e": (read(spark, d, "events"), EVT, "event_type = 'purchase'")})


@query("exact_card_chain", "SELECT count(*) AS card FROM customer JOIN orders ON c_custkey = o_custkey JOIN lineitem ON l_orderkey = o_orderkey JOIN part ON p_partkey = l_partkey JOIN supplier ON s_suppkey = l_suppkey WHERE p_size <= 10 AND l_discount >= 0.05")
def exact_card_chain(spark, d):
    t = lambda n: read(spark, d, n)
    return X.cardinality({"c": (t("customer"), CUST, None), "o": (t("orders"), OCHAIN, None), "l": (t("lineitem"), {"l_orderkey": "order", "l_partkey": "part", "l_suppkey": "supp"}, "l_discount >= 0.05"), "p": (t("part"), {"p_partkey": "part"}, "p_size <= 10"), "s": (t("supplier"), {"s_suppkey": "supp"}, None)})


@query("exact_card_skew", f"SELECT count(*) AS card FROM ({view_sql('orders_skew')}) o JOIN ({view_sql('events_skew')}) e ON cust_skew = user_skew WHERE seg = 'A' AND kind_skew = 'view'")
def exact_card_skew(spark, d):
    return X.cardinality({"o": (view(spark, d, "orders_skew"), {"cust_skew": "cust"}, "seg = 'A'"), "e": (view(spark, d, "events_skew"), {"user_skew": "cust"}, "kind_skew = 'view'")})


@query("exact_card_self", "SELECT count(*) AS card FROM lineitem a JOIN lineitem b USING (l_partkey) WHERE a.l_returnflag = 'R' AND b.l_linestatus = 'O'")
def exact_card_self(spark, d):
    li = read(spark, d, "lineitem")
    return X.cardinality({"a": (li, {"l_partkey": "part"}, "l_returnflag = 'R'"), "b": (li, {"l_partkey": "part"}, "l_linestatus = 'O'")})


@query("foj_identity", "WITH j AS (SELECT d.doc_id IS NOT NULL AND l.doc_id IS NOT NULL AND lang = 'de' AND quality = 1 AS hit FROM documents d FULL JOIN labels l USING (doc_id)) SELECT count(*) AS foj_size, round(count(*) FILTER (WHERE hit) / count(*), 9) AS probability, count(*) FILTER (WHERE hit) AS card FROM j")
def foj_identity(spark, d):
    return X.foj_probability(read(spark, d, "documents").select("doc_id", "lang"), read(spark, d, "labels"), "doc_id", "lang = 'de' AND quality = 1").withColumn("probability", F.round("probability", 9))


@query("independent_frequency", "WITH f AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1), p AS (SELECT avg(CASE WHEN o_orderstatus = 'F' THEN 1.0::DOUBLE ELSE 0 END) * avg(CASE WHEN o_totalprice > 100000 THEN 1.0::DOUBLE ELSE 0 END) AS p FROM orders) SELECT o_custkey, round(n * p, 6) AS freq FROM f, p")
def independent_frequency(spark, d):
    o = read(spark, d, "orders")
    share = [F.avg(F.when(F.expr(c), 1.0).otherwise(0.0)) for c in ("o_orderstatus = 'F'", "o_totalprice > 100000")]
    p = o.agg((share[0] * share[1]).alias("p"))
    return o.groupBy("o_custkey").agg(F.count("*").alias("n")).join(F.broadcast(p)).select("o_custkey", F.round(F.col("n") * F.col("p"), 6).alias("freq"))


# estimators and measures ----------------------------------------------------------------------------------------------

_EST = ORACLE["sbs_join2"]
for _name, _how, _agg in (("est_median", "median", "median(est)"), ("est_max", "max", "max(est)"), ("est_q75", "q75", "quantile_cont(est, 0.75)")):
    query(_name, f"SELECT {_agg} AS est FROM ({_EST}) t")(lambda spark, d, how=_how: C.reduce_reps(sbs_join2(spark, d), how))
query("est_dbs_min", f"SELECT min(est) AS est FROM ({ORACLE['dbs_join2']}) t")(lambda spark, d: C.reduce_reps(dbs_join2(spark, d), "min"))
query("est_clamp", f"SELECT rep, greatest(est, 1.0::DOUBLE) AS est FROM ({_EST}) t")(lambda spark, d: C.clamp(sbs_join2(spark, d)))

_PAIRS = f"(SELECT rep, est, (SELECT count(*)::DOUBLE FROM orders JOIN events ON o_custkey = user_id WHERE event_type = 'purchase') AS truth FROM ({_EST}) t)"


def _pairs(spark, d):
    truth = X.cardinality({"o": (read(spark, d, "orders"), ORD, None), "e": (read(spark, d, "events"), EVT, "event_type = 'purchase'")})
    return sbs_join2(spark, d).join(F.broadcast(truth)).select("rep", "est", F.col("card").cast("double").alias("truth"))


query("metric_qerror", f"SELECT rep, round(greatest(greatest(est, 1) / truth, truth / greatest(est, 1)), 9) AS qerror FROM {_PAIRS} p WHERE truth > 0")(lambda spark, d: M.qerror(_pairs(spark, d)).select("rep", F.round("qerror", 9).alias("qerror")))
query("metric_relerr", f"SELECT rep, round((est - truth) / truth, 9) AS relerr FROM {_PAIRS} p WHERE truth > 0")(lambda spark, d: M.relative_error(_pairs(spark, d)).select("rep", F.round("relerr", 9).alias("relerr")))
query("metric_bias_share", f"SELECT round(avg(CASE WHEN est > truth THEN 1.0::DOUBLE ELSE 0 END), 9) AS over, round(avg(CASE WHEN est < truth THEN 1.0::DOUBLE ELSE 0 END), 9) AS under FROM {_PAIRS} p")(lambda spark, d: M.bias_share(_pairs(spark, d)))
query("metric_bound_share", f"SELECT round(avg(CASE WHEN est >= truth THEN 1.0::DOUBLE ELSE 0 END), 9) AS bound_share FROM {_PAIRS} p")(lambda spark, d: M.bound_share(_pairs(spark, d)))

_F_ROWS, _P = O.sketch("SELECT o_custkey FROM orders WHERE o_orderstatus = 'F'", ORD, W, R), "(SELECT avg(CASE WHEN o_orderstatus = 'F' THEN 1.0::DOUBLE ELSE 0 END) FROM orders)"
_IND = f"SELECT rep, bin, val * {_P} AS val FROM ({O.sketch('SELECT o_custkey FROM orders', ORD, W, R)}) i"
ORACLE["metric_l1"] = f"WITH a AS ({_F_ROWS}), b AS ({_IND}) SELECT rep, round(sum(abs(coalesce(a.val, 0) - coalesce(b.val, 0))), 6) AS l1 FROM a FULL JOIN b USING (rep, bin) GROUP BY rep"


@query("metric_l1", ORACLE["metric_l1"])
def metric_l1(spark, d):
    """L1 distance between the exact sketch of a selection and its independence estimate, the worst case."""
    o = read(spark, d, "orders")
    p = o.agg(F.avg(F.when(F.col("o_orderstatus") == "F", 1.0).otherwise(0.0))).first()[0]
    return M.l1(S.countmin(o, ORD, W, R, "o_orderstatus = 'F'"), S.scale(S.countmin(o, ORD, W, R), p))


@query("copula_rank", "SELECT o_orderkey, round(cume_dist() OVER (ORDER BY o_totalprice), 9) AS u FROM orders")
def copula_rank(spark, d):
    from pyspark.sql import Window

    return read(spark, d, "orders").select("o_orderkey", F.round(F.cume_dist().over(Window.orderBy("o_totalprice")), 9).alias("u"))


# synopsis baselines ---------------------------------------------------------------------------------------------------

_HB = 20


@query("hist_join2", f"""WITH o AS (SELECT o_custkey // {_HB} AS b, count(*)::DOUBLE AS n, count(DISTINCT o_custkey) AS v FROM orders GROUP BY 1),
e AS (SELECT user_id // {_HB} AS b, count(*)::DOUBLE AS n, count(DISTINCT user_id) AS v FROM events GROUP BY 1)
SELECT round(sum(o.n * e.n / greatest(o.v, e.v)), 6) AS est FROM o JOIN e USING (b)""")
def hist_join2(spark, d):
    from ..baselines.synopses import histogram_join

    return histogram_join(read(spark, d, "orders"), "o_custkey", read(spark, d, "events"), "user_id", _HB)


@query("sample_join2", f"""WITH o AS (SELECT o_custkey AS k, count(*)::DOUBLE AS n FROM orders WHERE {O.bucket('o_custkey', 'sample', 0, 100)} < 25 GROUP BY 1),
e AS (SELECT user_id AS k, count(*)::DOUBLE AS n FROM events WHERE {O.bucket('user_id', 'sample', 0, 100)} < 25 GROUP BY 1)
SELECT round(sum(o.n * e.n) * 4, 6) AS est FROM o JOIN e USING (k)""")
def sample_join2(spark, d):
    from ..baselines.synopses import sample_join

    return sample_join(read(spark, d, "orders"), "o_custkey", read(spark, d, "events"), "user_id", 25)


@query("md_hist_selectivity", "SELECT o_orderstatus, o_orderpriority, count(*)::DOUBLE / (SELECT count(*) FROM orders) AS p FROM orders GROUP BY 1, 2")
def md_hist_selectivity(spark, d):
    from ..baselines.synopses import md_histogram

    return md_histogram(read(spark, d, "orders"), ["o_orderstatus", "o_orderpriority"])
