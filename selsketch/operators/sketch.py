"""Sketch construction.  Rows are counted per key first, so each distinct key is hashed once per repetition, and the counts
combine on the map side; a sketch is a sparse table of (rep, bin, val)."""

from __future__ import annotations

from collections.abc import Mapping, Sequence
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import PRIME, bucket, coefficients, composite, sign

#: keys: column -> attribute class; signs: column -> edges whose sign hashes the column takes part in.
Keys = Mapping[str, str]
Signs = Mapping[str, Sequence[str]]


def key_counts(df: DataFrame, keys: Keys, by: Sequence[str] = ()) -> DataFrame:
    kept = df.where(reduce(lambda a, b: a & b, [F.col(c).isNotNull() for c in keys]))
    return kept.groupBy(*by, *keys).agg(F.count("*").alias("n"))


def _per_rep(counts: DataFrame, reps: int, make) -> DataFrame:
    return counts.withColumn("_r", F.explode(F.array(*[F.struct(F.lit(r).alias("rep"), *make(r)) for r in range(reps)])))


def signs_of(signs: Signs, rep: int) -> Column:
    parts = [sign(F.col(c), e, rep) for c, edges in signs.items() for e in edges]
    return reduce(lambda a, b: a * b, parts, F.lit(1).cast("long"))


def bin_of(keys: Keys, rep: int, width: int) -> Column:
    return composite([bucket(F.col(c), cls, rep, width) for c, cls in keys.items()], width)


def from_counts(counts: DataFrame, keys: Keys, width: int, reps: int, signs: Signs | None = None, by: Sequence[str] = ()) -> DataFrame:
    rows = _per_rep(counts, reps, lambda r: [bin_of(keys, r, width).alias("bin"), signs_of(signs or {}, r).alias("s")])
    out = rows.groupBy(*by, F.col("_r.rep").alias("rep"), F.col("_r.bin").alias("bin")).agg(F.sum(F.col("n") * F.col("_r.s")).alias("val"))
    return out.where("val <> 0")


#: Rows that are hashed together in Python.
CHUNK = 1 << 18


def of_variants(counts: DataFrame, variants: Sequence, keys: Keys, width: int, reps: int, one: str) -> DataFrame:
    """(one, variant, rep, bins, vals), packed, of all variants from counts (one, *keys, n), a row for each key.  Variants of
    the same columns share a pass, which adds rows up in dense vectors; directed degrees meet at their facing value first."""
    sets: dict[tuple[str, ...], list] = {}
    for v in variants:
        sets.setdefault(v.columns, []).append(v)
    have, parts, cores = set(counts.columns) - {one, "n"}, [], counts.sparkSession.sparkContext.defaultParallelism
    for columns, own in sets.items():
        rows = counts.dropna(subset=list(columns))
        if have != set(columns):
            rows = rows.groupBy(one, *columns).agg(F.sum("n").alias("n"))
        flat = [v for v in own if not v.facing or len(columns) == 1]  # one column: the bin follows from the value
        if flat:  # as many partial vectors as there are parts, so their number doesn't follow the data
            parts.append(rows.select(one, *[F.col(c).cast("long").alias(c) for c in columns], "n").coalesce(2 * cores).mapInArrow(_folded(columns, flat, keys, width, reps, one), packed_schema(one)))
        for v in own:
            if v not in flat:  # the rows of a facing value lie together
                near = rows.select(one, *[F.col(c).cast("long").alias(c) for c in columns], "n").repartition(v.facing).sortWithinPartitions(v.facing)
                parts.append(near.mapInArrow(_folded(columns, [v], keys, width, reps, one, v.facing), packed_schema(one)))
    return _summed(reduce(DataFrame.unionByName, parts), {v.name for v in variants if v.facing}, width, one, cores)


def packed_schema(one: str) -> str:
    return f"{one} int, variant string, rep int, bins binary, vals binary"


def _batch(rows: list[tuple], one: str) -> pa.RecordBatch:
    types = {one: pa.int32(), "variant": pa.string(), "rep": pa.int32(), "bins": pa.binary(), "vals": pa.binary()}
    return pa.record_batch([pa.array([r[i] for r in rows], t) for i, t in enumerate(types.values())], names=list(types))


def _sparse(group: int, variant: str, rep: int, dense: np.ndarray) -> tuple:
    bins = np.flatnonzero(dense).astype(np.int32)
    return int(group), variant, rep, bins.tobytes(), dense[bins].tobytes()


def _folded(columns: Sequence[str], variants: Sequence, keys: Keys, width: int, reps: int, one: str, facing: str = ""):
    """One part's sketches: rows are hashed a chunk at a time and added to a dense vector of each group, variant and repetition.
    With ``facing`` rows come sorted by it; those of one value and bin count together, and chunks end between values."""
    edges = sorted({(c, e) for v in variants for c, es in v.signs for e in es})
    buckets = {(c, r): coefficients("bucket", keys[c], r, 2) for c in columns for r in range(reps)}
    signs = {(c, e, r): coefficients("sign", e, r, 4) for c, e in edges for r in range(reps)}

    def polynomial(x: np.ndarray, coeffs: Sequence[int]) -> np.ndarray:
        return reduce(lambda acc, c: (acc * x + c) % PRIME, coeffs[1:], np.full(len(x), coeffs[0], np.int64))

    def fold(batches):
        dense: dict[tuple[int, int, int], np.ndarray] = {}

        def add(held: list) -> None:
            table = pa.Table.from_batches(held)
            group, n = table.column(one).to_numpy(), table.column("n").to_numpy().astype(np.float64)
            xs = {c: table.column(c).to_numpy() % PRIME for c in columns}
            where_of = {g: np.flatnonzero(group == g) for g in np.unique(group)}
            where = list(where_of.items())
            if facing:
                value = table.column(facing).to_numpy()
                rank = np.cumsum(np.diff(value, prepend=value[:1]) != 0)
            for r in range(reps):
                at = sum(polynomial(xs[c], buckets[c, r]) % width for c in columns) % width
                sign = {(c, e): 1 - 2 * (polynomial(xs[c], signs[c, e, r]) % 2) for c, e in edges}
                for i, v in enumerate(variants):
                    val = reduce(lambda a, b: a * b, [sign[c, e] for c, es in v.signs for e in es], n)
                    for g, rows in where:
                        if facing:
                            pair = rank[rows] * width + at[rows]
                            order = np.argsort(pair, kind="stable")
                            first = np.flatnonzero(np.diff(pair[order], prepend=-1))
                            rows, val = rows[order[first]], np.zeros(len(n))
                            val[rows] = np.add.reduceat(n[where_of[g]][order], first)
                        if (g, i, r) not in dense:
                            dense[g, i, r] = np.zeros(width)
                        (np.maximum if v.facing else np.add).at(dense[g, i, r], at[rows], val[rows])

        held, size = [], 0
        for batch in batches:
            held.append(batch)
            size += batch.num_rows
            if size >= CHUNK:
                table, cut = pa.Table.from_batches(held), size
                if facing:
                    value = table.column(facing).to_numpy()
                    cut = int(np.searchsorted(value, value[-1]))
                if cut:
                    add(table.slice(0, cut).to_batches())
                    held, size = table.slice(cut).to_batches(), size - cut
        if size:
            add(held)
        for (g, i, r), vector in dense.items():
            yield _batch([_sparse(g, variants[i].name, r, vector)], one)

    return fold


def _summed(parts: DataFrame, degrees: set[str], width: int, one: str, cores: int) -> DataFrame:
    def total(key, table):
        g, variant, rep = (k.as_py() for k in key)
        out = np.zeros(width)
        for bins, vals in zip(table.column("bins").to_pylist(), table.column("vals").to_pylist(), strict=True):
            (np.maximum if variant in degrees else np.add).at(out, np.frombuffer(bins, np.int32), np.frombuffer(vals, np.float64))
        return pa.Table.from_batches([_batch([_sparse(g, variant, rep, out)], one)])

    keys = [one, "variant", "rep"]
    return parts.repartition(4 * cores, *keys).groupBy(*keys).applyInArrow(total, packed_schema(one))


def packed(rows: DataFrame, one: str) -> DataFrame:
    """rows(one, variant, rep, bin, val) with each sketch as one row of packed counters."""

    def pack(key, table):
        group = table.column(one).to_numpy()
        order = np.argsort(group, kind="stable")
        found, cuts = np.unique(group[order], return_index=True)
        bins = np.split(table.column("bin").to_numpy().astype(np.int32)[order], cuts[1:])
        vals = np.split(table.column("val").to_numpy().astype(np.float64)[order], cuts[1:])
        variant, rep = (k.as_py() for k in key)
        return pa.Table.from_batches([_batch([(int(g), variant, rep, b.tobytes(), v.tobytes()) for g, b, v in zip(found, bins, vals, strict=True)], one)])

    return rows.select(one, "variant", "rep", "bin", F.col("val").cast("double").alias("val")).groupBy("variant", "rep").applyInArrow(pack, packed_schema(one))


def rows_of_packed(df: DataFrame, one: str) -> DataFrame:
    """(one, variant, rep, bin, val) of packed sketches."""

    def unpack(batches):
        for batch in batches:
            for g, variant, rep, bins, vals in zip(*(batch.column(c).to_pylist() for c in (one, "variant", "rep", "bins", "vals")), strict=True):
                at, n = np.frombuffer(bins, np.int32), len(bins) // 4
                yield pa.record_batch([pa.array(np.full(n, g, np.int32)), pa.array([variant] * n, pa.string()), pa.array(np.full(n, rep, np.int32)), pa.array(at), pa.array(np.frombuffer(vals, np.float64))], names=[one, "variant", "rep", "bin", "val"])

    return df.select(one, "variant", "rep", "bins", "vals").mapInArrow(unpack, f"{one} int, variant string, rep int, bin int, val double")


def unpacked(bins: bytes, vals: bytes, width: int) -> np.ndarray:
    out = np.zeros(width)
    out[np.frombuffer(bins, np.int32)] = np.frombuffer(vals, np.float64)
    return out


def signed(df: DataFrame, keys: Keys, signs: Signs, width: int, reps: int, where: str | None = None, by: Sequence[str] = ()) -> DataFrame:
    """Signed-bucket sketch; with several keys the convolved sketch over their composite bin."""
    return from_counts(key_counts(df.where(where) if where else df, keys, by), keys, width, reps, signs, by)


def countmin(df: DataFrame, keys: Keys, width: int, reps: int, where: str | None = None, by: Sequence[str] = ()) -> DataFrame:
    return from_counts(key_counts(df.where(where) if where else df, keys, by), keys, width, reps, None, by)


def degree(df: DataFrame, keys: Keys, facing: str, width: int, reps: int, where: str | None = None, by: Sequence[str] = ()) -> DataFrame:
    """Largest number of rows that share the facing column's value and the bin; with one key the plain degree vector."""
    counts = key_counts(df.where(where) if where else df, keys, by)
    rows = _per_rep(counts, reps, lambda r: [bin_of(keys, r, width).alias("bin")])
    each = rows.groupBy(*by, F.col("_r.rep").alias("rep"), F.col("_r.bin").alias("bin"), facing).agg(F.sum("n").alias("d"))
    return each.groupBy(*by, "rep", "bin").agg(F.max("d").alias("val"))


def tensor(df: DataFrame, keys: Keys, width: int, reps: int, signs: Signs | None = None, facing: str | None = None) -> DataFrame:
    """One axis (bin1, bin2, ...) per key: signed, or plain counts without signs, or directed degrees with ``facing``."""
    counts = key_counts(df, keys)
    axes = [f"bin{i + 1}" for i in range(len(keys))]
    rows = _per_rep(counts, reps, lambda r: [*[bucket(F.col(c), cls, r, width).alias(a) for a, (c, cls) in zip(axes, keys.items(), strict=True)], signs_of(signs or {}, r).alias("s")])
    flat = [F.col("_r.rep").alias("rep"), *[F.col(f"_r.{a}").alias(a) for a in axes]]
    if facing:
        return rows.groupBy(*flat, facing).agg(F.sum("n").alias("d")).groupBy("rep", *axes).agg(F.max("d").alias("val"))
    return rows.groupBy(*flat).agg(F.sum(F.col("n") * F.col("_r.s")).alias("val")).where("val <> 0")


def frequency(rows: DataFrame, values: DataFrame, key: str, cls: str, edge: str, width: int, reps: int) -> DataFrame:
    """Median over repetitions of a value's frequency read back from a signed sketch."""
    at = _per_rep(values.select(key).distinct(), reps, lambda r: [bucket(F.col(key), cls, r, width).alias("bin"), sign(F.col(key), edge, r).alias("s")])
    at = at.select(key, "_r.*")
    read = at.join(rows, ["rep", "bin"], "left").select(key, (F.coalesce("val", F.lit(0)) * F.col("s")).alias("f"))
    return read.groupBy(key).agg(F.median("f").alias("freq"))


def point(rows: DataFrame, values: DataFrame, key: str, cls: str, width: int, reps: int) -> DataFrame:
    """Smallest count-min counter of a value over the repetitions."""
    at = _per_rep(values.select(key).distinct(), reps, lambda r: [bucket(F.col(key), cls, r, width).alias("bin")]).select(key, "_r.*")
    return at.join(rows, ["rep", "bin"], "left").groupBy(key).agg(F.min(F.coalesce("val", F.lit(0))).alias("freq"))


def add(*tables: DataFrame) -> DataFrame:
    return reduce(DataFrame.unionByName, tables).groupBy("rep", "bin").agg(F.sum("val").alias("val")).where("val <> 0")


def scale(rows: DataFrame, factor: float) -> DataFrame:
    return rows.withColumn("val", F.col("val") * factor)


def subtract(a: DataFrame, b: DataFrame) -> DataFrame:
    return add(a, scale(b, -1))


def merge_degree(tables: Sequence[DataFrame], how: str = "sum", clamp: DataFrame | None = None) -> DataFrame:
    """Degree vectors of parts: their sum (or the rejected maximum), held below the whole relation's vector."""
    out = reduce(DataFrame.unionByName, tables).groupBy("rep", "bin").agg((F.sum if how == "sum" else F.max)("val").alias("val"))
    if clamp is None:
        return out
    return out.join(clamp.withColumnRenamed("val", "most"), ["rep", "bin"], "left").select("rep", "bin", F.least("val", F.coalesce("most", F.lit(0))).alias("val"))


def density(rows: DataFrame, width: int) -> DataFrame:
    """Counters in use per repetition, and their share."""
    return rows.groupBy("rep").agg(F.count("*").alias("nnz")).withColumn("density", F.round(F.col("nnz") / width, 6))


def densify(rows: DataFrame, width: int, reps: int) -> DataFrame:
    spark = rows.sparkSession
    grid = spark.range(reps * width).select((F.col("id") / width).cast("int").alias("rep"), (F.col("id") % width).cast("int").alias("bin"))
    return grid.join(rows, ["rep", "bin"], "left").select("rep", "bin", F.coalesce("val", F.lit(0)).alias("val"))
