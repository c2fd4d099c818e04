"""MinHash near-duplicates with min-max hashing: each permutation gives its minimum and its maximum, so half the hash
evaluations fill a signature of the same length.

Plan
 1. One scan: per document the size and a 128-bit hash of its shingle set, and its band keys (2 x PERMUTATIONS signature
    values in bands of ROWS).  Documents with equal sets form a class; its smallest doc_id stands for it.
 2. Band keys that several classes share make groups around their smallest class.  Every pair of classes that shares a band
    key is inside the group of that key's smallest class.
 3. Exact verification on full sets: every member against the group's centre; links give components.
 4. In groups that still hold several components, all members outside the largest one are compared with every member whose
    set is of like size, in blocks (a grid of BLOCK members by BLOCK probes), so nothing is capped and no pair becomes a row
    unless it is a link.
 5. Components again over all links.

The one source of loss is banding: a pair at exactly the threshold 0.75 shares no band with probability
(1 - 0.75^4)^40 = 3e-7, less for more similar pairs.  (Shingles of a prefix as further keys of small sets would find those for
certain, but a line that many short documents share then makes one group of unlike members, whose pairs outgrow the disk.)
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Scratch, Sieve, docs_of, hot_join, map_batches, squeezed, unsqueezed
from .components import components
from .text import mix, signed, words_of

WORDS, THRESHOLD = 5, 75
PERMUTATIONS, ROWS = 80, 4
BLOCK = 128
_U = np.uint64


def _permutations(n: int) -> tuple[np.ndarray, np.ndarray]:
    seed = mix(np.arange(1, 2 * n + 1, dtype=_U) * _U(0x9E3779B97F4A7C15))
    return seed[:n] | _U(1), seed[n:]


def shingle_sets(texts: pa.Array, k: int = WORDS):
    """(first row, rows with words, start of each one's shingles, distinct sorted shingle hashes), slice by slice."""
    for lo, _, words in words_of(texts, lower=True):
        at = words.windows(k)
        few = np.flatnonzero((words.counts() > 0) & (words.counts() < k))
        shingle = np.concatenate([words.run_hash(at, at + k), words.run_hash(words.ptr[few], words.ptr[few + 1])])
        row = np.concatenate([words.row_of(at), few])
        order = np.lexsort((signed(shingle), row))
        shingle, row = shingle[order], row[order]
        fresh = np.ones(len(row), bool)
        fresh[1:] = (shingle[1:] != shingle[:-1]) | (row[1:] != row[:-1])
        rows, start = np.unique(row[fresh], return_index=True)
        yield lo, rows, start, shingle[fresh], words.rows


def min_max(shingle: np.ndarray, start: np.ndarray, n: int = PERMUTATIONS) -> np.ndarray:
    """Signature of 2n values for each set: minima, then maxima, of n permutations."""
    out = np.empty((len(start), 2 * n), _U)
    for i, (a, b) in enumerate(zip(*_permutations(n), strict=True)):
        x = shingle * a + b
        x ^= x >> _U(32)
        out[:, i], out[:, n + i] = np.minimum.reduceat(x, start), np.maximum.reduceat(x, start)
    return out


def band_keys(signature: np.ndarray, rows: int = ROWS) -> np.ndarray:
    """Keys of the bands.  The values of a band come from different permutations, as the minimum and the maximum of one
    permutation are not independent: minima of some permutations, maxima of the next band's."""
    n = signature.shape[1] // 2
    bands = signature.shape[1] // rows
    order = np.arange(bands * rows).reshape(rows, bands)
    order = np.where(order < n, order, n + np.roll(order, -1, axis=1) % n)
    key = np.broadcast_to(mix(np.arange(1, bands + 1, dtype=_U)), (len(signature), bands)).copy()
    for j in range(rows):
        key = mix(key * _U(31) + signature[:, order[j]])
    return key


def signatures(docs: DataFrame, k: int = WORDS, permutations: int = PERMUTATIONS, rows: int = ROWS) -> DataFrame:
    """(doc_id, n_shingles, s1, s2, bands): one row per document; bands is empty where there are no words."""

    def step(batch: pa.RecordBatch):
        ids = batch.column("doc_id")
        for lo, full, start, shingle, n in shingle_sets(batch.column("text"), k):
            size, s1, s2 = np.zeros(n, np.int64), np.zeros(n, np.int64), np.zeros(n, np.int64)
            at, keys = np.zeros(n + 1, np.int64), np.zeros(0, np.int64)
            if len(full):
                size[full] = np.diff(np.append(start, len(shingle)))
                s1[full], s2[full] = _set_hash(shingle, start)
                bands = band_keys(min_max(shingle, start, permutations), rows)
                keys = signed(bands).ravel()
                at[1:][full] = bands.shape[1]
            bands = pa.ListArray.from_arrays(pa.array(np.cumsum(at).astype(np.int32)), pa.array(keys))
            yield {"doc_id": ids.slice(lo, n), "n_shingles": size, "s1": s1, "s2": s2, "bands": bands}

    return map_batches(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")), step, doc_id="long", n_shingles="long", s1="long", s2="long", bands="longs")


def _set_hash(shingle: np.ndarray, start: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    return signed(np.add.reduceat(mix(shingle), start)), signed(np.add.reduceat(mix(shingle ^ _U(0x5851F42D4C957F2D)), start))


def _sets(docs: DataFrame, wanted: DataFrame, k: int) -> DataFrame:
    """(c, t, shingles): full shingle sets of the documents in wanted(c); t tells the texts of one id apart.  Only texts that
    a Sieve of the wanted ids lets through are compressed and shuffled."""
    ids = wanted.select("c").distinct()
    sieve = Sieve(ids.select(F.xxhash64("c").alias("h")), "h")
    near = docs.select(F.col("doc_id").cast("long").alias("c"), F.col("text").cast("string"))
    packed = squeezed(near.where(sieve.maybe(F.when(F.col("c").isNotNull(), F.xxhash64("c")))), ["c"])

    def step(batch: pa.RecordBatch):
        ids = batch.column("c")
        for lo, full, start, shingle, _ in shingle_sets(unsqueezed(batch.column("packed")), k):
            if len(full):
                ptr = np.append(start, len(shingle)).astype(np.int32)
                yield {"c": ids.take(pa.array(lo + full)), "t": _set_hash(shingle, start)[0], "shingles": pa.ListArray.from_arrays(pa.array(ptr), pa.array(signed(shingle)))}

    return map_batches(packed.join(ids.hint("merge"), "c").dropDuplicates(["c", "packed"]), step, c="long", t="long", shingles="longs")


def _grid_links(threshold: int):
    def linked(key, table):
        """Links between the probes and the members of one grid cell, by exact intersection sizes."""
        probe = np.asarray(table.column("probe").to_numpy(zero_copy_only=False), bool)
        c = table.column("c").to_numpy()
        sets = table.column("shingles").combine_chunks()
        flat, ptr = sets.flatten().to_numpy(), np.append(0, np.cumsum(sets.value_lengths().to_numpy())).astype(np.int64)
        members = np.flatnonzero(~probe)
        size = np.diff(ptr)
        who = np.repeat(np.arange(len(members)), size[members])
        value = np.concatenate([flat[ptr[i] : ptr[i + 1]] for i in members]) if len(members) else flat[:0]
        order = np.argsort(value, kind="stable")
        value, who = value[order], who[order]
        a, b = [], []
        for i in np.flatnonzero(probe):
            own = flat[ptr[i] : ptr[i + 1]]
            lo, hi = np.searchsorted(value, own, "left"), np.searchsorted(value, own, "right")
            n = hi - lo
            hits = who[np.repeat(lo - np.append(0, np.cumsum(n)[:-1]), n) + np.arange(n.sum())]
            common = np.bincount(hits, minlength=len(members))
            union = size[i] + size[members] - common
            good = members[(100 * common >= threshold * union) & (c[members] != c[i])]
            a += [c[i]] * len(good)
            b += c[good].tolist()
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    return linked


def _verify(cells: DataFrame, sets: DataFrame, threshold: int) -> DataFrame:
    """cells(g, z, m, p, c, t, probe) with the sets of c, t -> links(a, b) between probes and members of each cell g, z, m, p."""
    weights = cells.groupBy("c", "t").agg(F.count("*").alias("w"))
    return hot_join(cells, sets, ["c", "t"], "w", weights=weights).groupBy("g", "z", "m", "p").applyInArrow(_grid_links(threshold), "a long, b long")


def _same_id(full: DataFrame, classes: DataFrame, scratch: Scratch) -> DataFrame:
    """links(a, b) that hold the texts of a repeated doc_id together: between the id and the classes of its texts."""
    texts = full.select("doc_id", "s1", "s2", "n_shingles").distinct()
    several = scratch.save(texts.groupBy("doc_id").agg(F.count("*").alias("w")).where("w > 1"), "several")
    return hot_join(texts, several, ["doc_id"], "w").join(classes.hint("merge"), ["s1", "s2", "n_shingles"]).select(F.col("doc_id").alias("a"), F.col("c").alias("b"))


def near_duplicates(docs: DataFrame, k: int = WORDS, threshold: int = THRESHOLD, permutations: int = PERMUTATIONS, rows: int = ROWS) -> DataFrame:
    """docs(doc_id, text, ...) -> (doc_id, n_shingles, component_id, kept).

    A document's set: distinct k-word shingles of the lower-cased words; fewer words make one shingle; null or empty texts
    have an empty set and are linked with nothing (component_id is their own doc_id, kept).  Rows that repeat a doc_id
    each give a row; they are one document, so all of them with words are in one component, with what any of them is linked
    with.  Null doc_ids stay alone: component_id null, kept true.  Other columns are ignored.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark)
    sig = scratch.save(signatures(docs, k, permutations, rows), "signatures")
    full = sig.where("n_shingles > 0 AND doc_id IS NOT NULL")
    classes = scratch.save(full.groupBy("s1", "s2", "n_shingles").agg(F.min("doc_id").alias("c"), F.count("*").alias("w")), "classes")
    same = ["doc_id", "s1", "s2", "n_shingles"]
    once = full.groupBy(*same).agg(F.first("bands").alias("bands"))
    stand = once.join(classes.select(F.col("c").alias("doc_id"), *same[1:]).hint("merge"), same)
    # sets of unlike size can't be linked: sizes whose ratio is within the threshold are in the same or in adjacent classes z
    size = F.floor(F.log(F.col("n_shingles").cast("double")) / F.lit(float(np.log(100 / threshold * 1.0001)))).cast("int")
    keyed = stand.select(F.col("doc_id").alias("c"), F.col("s1").alias("t"), size.alias("z"), F.explode("bands").alias("key"))
    shared = scratch.save(keyed.groupBy("key").agg(F.min("c").alias("g"), F.count("*").alias("w")).where("w > 1"), "shared")
    member = scratch.save(hot_join(keyed, shared, ["key"], "w").select("g", "c", "t", "z").distinct(), "members")
    sets = scratch.save(_sets(docs, member, k), "sets")

    sized = member.groupBy("g").agg(F.count("*").alias("n"))
    grid = hot_join(member, scratch.save(sized.withColumn("w", F.col("n")), "sized"), ["g"], "w")
    zero = F.lit(0).cast("int")
    blocks = lambda n: F.ceil(F.col(n) / BLOCK).cast("int")
    turn = lambda n, seed: F.pmod(F.xxhash64("c", "t", F.lit(seed)), blocks(n)).cast("int")
    every = lambda n: F.explode(F.sequence(zero, blocks(n) - 1))
    others = grid.where("c <> g").select("g", zero.alias("z"), turn("n", 0).alias("m"), zero.alias("p"), "c", "t", F.lit(False).alias("probe"))
    centres = grid.where("c = g").select("g", zero.alias("z"), every("n").alias("m"), zero.alias("p"), "c", "t", F.lit(True).alias("probe"))
    first = _verify(scratch.save(others.union(centres), "cells"), sets, threshold)
    first = scratch.save(first.union(_same_id(full, classes, scratch)), "links")

    label = components(first, scratch)
    placed = scratch.save(grid.join(label.withColumnRenamed("node", "c"), "c", "left").withColumn("component", F.coalesce("component", "c")), "placed")
    parts = placed.groupBy("g", "component").agg(F.count("*").alias("n_part"))
    mixed = parts.groupBy("g").agg(F.count("*").alias("parts"), F.max(F.struct("n_part", "component")).alias("most"), F.sum("n_part").alias("w")).where("parts > 1")
    mixed = scratch.save(mixed.select("g", F.col("most.component").alias("main"), "w"), "mixed")
    left = scratch.save(hot_join(placed, mixed, ["g"], "w").select("g", "z", "c", "t", (F.col("component") != F.col("main")).alias("apart")), "left")
    probes = left.where("apart").select("g", F.explode(F.sequence(F.col("z") - 1, F.col("z") + 1)).alias("z"), "c", "t")
    load = left.groupBy("g", "z").agg(F.count("*").alias("n")).join(probes.groupBy("g", "z").agg(F.count("*").alias("q")), ["g", "z"])
    load = scratch.save(load.withColumn("w", F.col("n") + F.col("q")), "load")
    members = hot_join(left.drop("apart"), load, ["g", "z"], "w").select("g", "z", turn("n", 0).alias("m"), every("q").alias("p"), "c", "t", F.lit(False).alias("probe"))
    probing = hot_join(probes, load, ["g", "z"], "w").select("g", "z", every("n").alias("m"), turn("q", 1).alias("p"), "c", "t", F.lit(True).alias("probe"))
    second = scratch.save(_verify(scratch.save(members.union(probing), "cells"), sets, threshold), "links")

    final = components(first.union(second), scratch) if second.take(1) else label
    of_class = scratch.save(classes.join(final.withColumnRenamed("node", "c"), "c", "left").select("s1", "s2", "n_shingles", F.coalesce("component", "c").alias("component_id"), "w"), "of_class")
    named = full.select("doc_id", "s1", "s2", "n_shingles")
    out = hot_join(named, of_class, ["s1", "s2", "n_shingles"], "w").select("doc_id", "n_shingles", "component_id")
    alone = sig.where("n_shingles = 0 OR doc_id IS NULL").select("doc_id", "n_shingles", F.col("doc_id").alias("component_id"))
    return out.union(alone).withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def op9_near_dup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for every document."""
    return near_duplicates(docs_of(spark, sf_dir))
