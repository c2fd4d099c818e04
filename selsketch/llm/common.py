"""Shared plumbing: scratch tables in the cluster's shared folder, joins that survive hot keys, Arrow map helpers."""

from __future__ import annotations

import sys
import tempfile
import types
import uuid
from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A key is hot if it holds at least this share of the rows; so at most 1/share keys are hot, which bounds the broadcast.
HOT_SHARE = 1 / 1024
_HOT_LEAST = 500
#: Size of a Sieve.
SIEVE_BITS = 26


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share (``spark.checkpoint.dir``); a temporary one only on a single machine."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not found:
        found = spark.sparkContext.getCheckpointDir()
    if not found:
        if not spark.sparkContext.master.startswith("local"):  # local or local-cluster: one machine
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="shared-"))
        found = spark.sparkContext.getCheckpointDir()
    return found.rstrip("/")


def small_batches(spark: SparkSession) -> None:
    """Bound what a Python worker holds: long texts come in batches of few rows and bytes (session settings, not static)."""
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "1000")
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", "4m")


class Scratch:
    """Tables written to the shared folder: they cut lineage, and a lost executor costs no recomputation."""

    def __init__(self, spark: SparkSession):
        small_batches(spark)
        self.spark, self.root = spark, f"{shared_dir(spark)}/scratch-{uuid.uuid4().hex}"
        self._n = 0

    def path(self, name: str) -> str:
        self._n += 1
        return f"{self.root}/{self._n:03d}-{name}"

    def save(self, df: DataFrame, name: str) -> DataFrame:
        df.write.option("compression", "zstd").parquet(at := self.path(name))
        return self.spark.read.schema(df.schema).parquet(at)

    def drop(self, *tables: DataFrame) -> None:
        """Delete tables that no later step reads."""
        jvm = self.spark._jvm
        for df in tables:
            for at in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
                if at.split(":", 1)[-1].lstrip("/").startswith(self.root.split(":", 1)[-1].lstrip("/")):
                    path = jvm.org.apache.hadoop.fs.Path(at)
                    path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def hot_join(big: DataFrame, small: DataFrame, keys: list[str], weight: str, how: str = "inner", weights: DataFrame | None = None) -> DataFrame:
    """big JOIN small on ``keys`` (unique in small) where few keys may hold most rows of big.

    ``weight`` is the number of big's rows of the key: a column of small, or of ``weights`` (keys, weight), which spares a
    small of large rows one shuffle.  Keys above HOT_SHARE of the rows, at most 1/HOT_SHARE of them, are broadcast; their
    rows then spread evenly over the shuffle of the others.  Column names that start with ``_join_`` are reserved.  ``how``: inner or left.  The join is a merge at every size.
    """
    counted = small if weights is None else weights
    values = [c for c in small.columns if c not in keys and c != weight]
    total = counted.agg(F.coalesce(F.sum(weight), F.lit(0))).first()[0]
    least = max(int(total * HOT_SHARE), _HOT_LEAST)
    names = counted.where(F.col(weight) >= least).select(*keys)
    if not names.take(1):
        return big.join(small.select(*keys, *values).hint("merge"), keys, how).select(*big.columns, *values)
    many, few = (small.where(F.col(weight) >= least), small.where(F.col(weight) < least)) if weights is None else (small.join(F.broadcast(names), keys, "left_semi"), small.join(F.broadcast(names), keys, "left_anti"))
    rest = few.select(*keys, *values, F.lit(0).cast("long").alias("_join_salt"), F.lit(True).alias("_join_cold"))
    hot = many.select(*keys, *[F.col(c).alias(f"_join_hot_{c}") for c in values], F.lit(True).alias("_join_hot"))
    marked = big.join(F.broadcast(hot), keys, "left").withColumn(
        "_join_salt", F.when(F.col("_join_hot"), 1 + F.pmod(F.xxhash64(*big.columns), F.lit(1 << 20))).otherwise(F.lit(0).cast("long"))
    )
    out = marked.join(rest.hint("merge"), [*keys, "_join_salt"], "left")
    if how == "inner":
        out = out.where(F.col("_join_hot") | F.col("_join_cold"))
    return out.select(*big.columns, *[F.when(F.col("_join_hot"), F.col(f"_join_hot_{c}")).otherwise(F.col(c)).alias(c) for c in values])


class Sieve:
    """A set of 64-bit values as 2^SIEVE_BITS bits, whose size does not depend on the data: it lets every member through and
    few others, so it only spares work and an exact join still follows.  The driver holds the bits, 8 MB, once."""

    def __init__(self, values: DataFrame, column: str):
        place = F.pmod(F.col(column), F.lit(1 << SIEVE_BITS)) + 1
        rows = values.select(F.bitmap_bucket_number(place).alias("bucket"), F.bitmap_bit_position(place).alias("bit"))
        bits = np.zeros((1 << SIEVE_BITS) // 8, np.uint8)
        for r in rows.groupBy("bucket").agg(F.bitmap_construct_agg("bit").alias("map")).toLocalIterator():  # at most 2^SIEVE_BITS bits
            at = (r["bucket"] - 1) * len(r["map"])
            bits[at : at + len(r["map"])] = np.frombuffer(r["map"], np.uint8)[: len(bits) - at]
        self.bits = values.sparkSession.sparkContext.broadcast(bits)

    def maybe(self, column: str | Column) -> Column:
        """Whether a long column's value may be a member; null for null."""
        held = self.bits

        @F.pandas_udf("boolean")
        def test(x: pd.Series) -> pd.Series:
            return pd.Series(in_sieve(held.value, x.fillna(0).to_numpy(np.int64)))

        column = F.col(column) if isinstance(column, str) else column
        return F.when(column.isNotNull(), test(column))


def in_sieve(bits: np.ndarray, x: np.ndarray) -> np.ndarray:
    at = x & ((1 << SIEVE_BITS) - 1)
    return (bits[at >> 3] >> (at & 7).astype(np.uint8)) & 1 == 1


def without(rows: DataFrame, gone: DataFrame, key: str = "doc_id") -> DataFrame:
    """rows whose key is not in gone(key), null keys included; rows that a Sieve of gone rejects are not shuffled."""
    gone = gone.select(F.col(key).alias("_gone_key")).where("_gone_key IS NOT NULL").distinct()
    maybe = F.coalesce(Sieve(gone.select(F.xxhash64("_gone_key").alias("h")), "h").maybe(F.xxhash64(key)), F.lit(False))
    rest = rows.where(maybe).join(gone.hint("merge"), F.col(key) == F.col("_gone_key"), "left_anti")
    return rows.where(~maybe).unionByName(rest)


def let(value: Column, use: Callable[[Column], Column]) -> Column:
    """use(value) with value computed once: a lambda's variable is held, a column expression would be copied."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def running(values: Column, start: Column, step: Callable[[Column, Column], Column]) -> Column:
    """Running results of ``step`` (associative, ``start`` neutral) over an array of longs, in blocks of about the square
    root of its size: an array grows only inside its block."""
    none = F.array().cast("array<bigint>")
    last = lambda a: F.coalesce(F.try_element_at(a, F.lit(-1)), start)
    grow = lambda acc, x: F.concat(acc, F.array(step(last(acc), x)))

    def blocks(x: Column) -> Column:
        return let(F.greatest(F.ceil(F.sqrt(F.size(x).cast("double"))).cast("int"), F.lit(1)), lambda n: F.transform(F.sequence(F.lit(0), n - 1), lambda j: F.aggregate(F.slice(x, j * n + 1, n), none, grow)))

    def joined(inner: Column) -> Column:
        before = F.aggregate(F.transform(inner, last), F.array(start), grow)
        return let(before, lambda base: F.flatten(F.transform(inner, lambda own, j: F.transform(own, lambda x: step(F.get(base, j), x)))))

    return let(let(values, blocks), joined)


def arrow_schema(**kinds: str) -> pa.Schema:
    names = {"long": pa.int64(), "int": pa.int32(), "double": pa.float64(), "string": pa.string(), "binary": pa.binary(), "boolean": pa.bool_(), "longs": pa.list_(pa.int64()), "ints": pa.list_(pa.int32())}
    return pa.schema([(k, names[v]) for k, v in kinds.items()])


def spark_schema(**kinds: str) -> str:
    return ", ".join(f"`{k}` {({'longs': 'array<long>', 'ints': 'array<int>'}).get(v, v)}" for k, v in kinds.items())


def map_batches(df: DataFrame, step: Callable[[pa.RecordBatch], Iterator[dict]], **kinds: str) -> DataFrame:
    """mapInArrow of a generator that turns one batch into dicts of columns, sent on piece by piece."""

    def run(batches):
        made = arrow_schema(**kinds)
        for batch in batches:
            for columns in step(batch):
                yield pa.RecordBatch.from_arrays([x if isinstance(x := columns[f.name], pa.Array) else pa.array(x, f.type) for f in made], schema=made)

    return df.mapInArrow(run, spark_schema(**kinds))


def squeezed(texts: DataFrame, keys: list[str], text: str = "text", level: int = 3) -> DataFrame:
    """Keys and the zstandard-compressed text as ``packed``: half of what a shuffle of plain text moves."""

    def run(batches):
        press = zstandard.ZstdCompressor(level=level)
        for b in batches:
            packed = [None if x is None else press.compress(x.encode()) for x in b.column(text).to_pylist()]
            yield pa.RecordBatch.from_arrays([*[b.column(k) for k in keys], pa.array(packed, pa.binary())], names=[*keys, "packed"])

    kinds = dict(texts.dtypes)
    return texts.select(*keys, text).mapInArrow(run, ", ".join([*[f"`{k}` {kinds[k]}" for k in keys], "packed binary"]))


def unsqueezed(packed: pa.Array) -> pa.Array:
    press = zstandard.ZstdDecompressor()
    return pa.array([None if x is None else press.decompress(x).decode() for x in packed.to_pylist()], pa.large_string())


def kept_in_worker(key: tuple, make: Callable[[], object]) -> object:
    """make() once per Python process: functions travel by value, so their module's globals don't outlive a task."""
    home = sys.modules.setdefault("_selsketch_worker", types.ModuleType("_selsketch_worker"))
    store = home.__dict__.setdefault("store", {})
    if key not in store:
        store[key] = make()
    return store[key]


def union_all(tables: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, tables)


def docs_of(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def text_column(name: str = "text") -> Column:
    return F.coalesce(F.col(name), F.lit(""))
