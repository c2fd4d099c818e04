"""Benchmark decontamination by greedy string tiling.

Documents and benchmark items that share a seed of MIN_MATCH tokens are tiled: the longest common runs of tokens not yet
marked are found by running Karp-Rabin hashes, marked on both sides and taken out, until no run of MIN_MATCH is left.  The
share of the item's tokens under tiles is its coverage, which passages in another order reach as well.

Seeds meet in a join: the scan of the documents emits only seeds that a Sieve of the benchmark's seeds lets through, however
large the benchmark is.  Pairs whose shared seeds could cover enough are candidates; only their texts move, and an item's tokens
go to the documents that need them.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Scratch, Sieve, docs_of, hot_join, in_sieve, map_batches, squeezed, unsqueezed
from .text import NON_ALNUM, Words, signed, words_of

MIN_MATCH, COVERAGE = 5, 0.5
_U = np.uint64
_BASE = _U(0xC2B2AE3D27D4EB4F)


def _rolling(tokens: np.ndarray, size: int) -> np.ndarray:
    """Karp-Rabin hashes of all windows of ``size`` tokens."""
    out = np.zeros(len(tokens) - size + 1, _U)
    for j in range(size):
        out = out * _BASE + tokens[j : j + len(out)]
    return out


def tiles(item: np.ndarray, text: np.ndarray, least: int = MIN_MATCH) -> list[tuple[int, int, int]]:
    """Greedy tiling of two token arrays: (item start, text start, length), longest first, none overlapping."""
    free_i, free_t = np.ones(len(item), bool), np.ones(len(text), bool)
    found: list[tuple[int, int, int]] = []
    size = max(least, min(len(item), len(text), 4 * least))
    while size >= least:
        if min(len(item), len(text)) < size:
            size = min(len(item), len(text))
            if size < least:
                break
        hashes_t, hashes_i = _rolling(text, size), _rolling(item, size)
        open_t = np.convolve(free_t, np.ones(size, int), "valid") == size
        open_i = np.convolve(free_i, np.ones(size, int), "valid") == size
        where: dict[int, list[int]] = {}
        wanted = np.isin(hashes_t, hashes_i[open_i]) & open_t
        for t in np.flatnonzero(wanted):
            where.setdefault(int(hashes_t[t]), []).append(int(t))
        runs = []
        for i in np.flatnonzero(open_i):
            for t in where.get(int(hashes_i[i]), ()):
                if i and t and free_i[i - 1] and free_t[t - 1] and item[i - 1] == text[t - 1]:
                    continue  # part of the run that starts one earlier
                n = 0
                while i + n < len(item) and t + n < len(text) and free_i[i + n] and free_t[t + n] and item[i + n] == text[t + n]:
                    n += 1
                if n >= size:
                    runs.append((n, int(i), t))
        longest = max((r[0] for r in runs), default=0)
        if longest > 2 * size:
            size = longest
            continue
        again = False
        for n, i, t in sorted(runs, key=lambda r: (-r[0], r[1], r[2])):
            if free_i[i : i + n].all() and free_t[t : t + n].all():
                free_i[i : i + n] = free_t[t : t + n] = False
                found.append((i, t, n))
            else:
                again = True  # what a longer tile left of this run may still be long enough
        if again:
            continue
        size = size // 2 if size > 2 * least else least if size > least else 0
    return found


def _row_hash(words: Words) -> np.ndarray:
    return signed(words.run_hash(words.ptr[:-1], words.ptr[1:], 1))


def _seeds(words: Words, least: int) -> tuple[np.ndarray, np.ndarray]:
    at = words.windows(least)
    return at, signed(words.run_hash(at, at + least))


def _item_seeds(items: DataFrame, least: int) -> DataFrame:
    """(item, n, h, place): the seeds of each token sequence of the benchmark, ``item`` its hash and n its length."""

    def step(batch: pa.RecordBatch):
        for _, _, words in words_of(batch.column("text"), NON_ALNUM, lower=True):
            at, h = _seeds(words, least)
            row = words.row_of(at)
            yield {"item": _row_hash(words)[row], "n": words.counts()[row].astype(np.int64), "h": h, "place": (at - words.ptr[row]).astype(np.int32)}

    return map_batches(items.select("text"), step, item="long", n="long", h="long", place="int").distinct()


def _item_tokens(items: DataFrame) -> DataFrame:
    """(item_id, item, tokens), one row per row."""

    def step(batch: pa.RecordBatch):
        ids = batch.column("item_id")
        for lo, hi, words in words_of(batch.column("text"), NON_ALNUM, lower=True):
            tokens = pa.ListArray.from_arrays(pa.array(words.ptr.astype(np.int32)), pa.array(signed(words.hash)))
            yield {"item_id": ids.slice(lo, hi - lo), "item": _row_hash(words), "tokens": tokens}

    return map_batches(items, step, item_id="long", item="long", tokens="longs")


def _hits(docs: DataFrame, sieve: Sieve, least: int) -> DataFrame:
    """(doc_id, t, h): the distinct seeds of each document that may be the benchmark's; t tells texts of one id apart."""

    def step(batch: pa.RecordBatch):
        ids = batch.column("doc_id")
        for lo, _, words in words_of(batch.column("text"), NON_ALNUM, lower=True):
            at, h = _seeds(words, least)
            near = in_sieve(sieve.bits.value, h)
            row, h = words.row_of(at[near]), h[near]
            if len(h):
                row, h = np.unique(np.stack([row, h]), axis=1)
                yield {"doc_id": ids.take(pa.array(lo + row)), "t": _row_hash(words)[row], "h": h}

    return map_batches(docs, step, doc_id="long", t="long", h="long")


def contaminated(docs: DataFrame, benchmark: DataFrame, least: int = MIN_MATCH, coverage: float = COVERAGE) -> DataFrame:
    """docs(doc_id, text), benchmark(item_id, text) -> (doc_id, item_id, coverage, n_tiles, longest), one row per leak.

    Tokens are lower-cased runs of letters and digits.  Null or empty texts leak nothing; an item of fewer than ``least``
    tokens can't be told from chance and matches nothing.  Repeated documents give repeated rows, repeated items one row
    each; a null id stays null.  Other columns are ignored.
    """
    scratch = Scratch(docs.sparkSession)
    items = benchmark.where(F.length("text") > 0).select(F.col("item_id").cast("long"), F.col("text").cast("string"))
    slim = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    seeds = scratch.save(_item_seeds(items, least), "seeds")
    hits = scratch.save(_hits(slim, Sieve(seeds, "h"), least), "hits")
    of_seed = seeds.groupBy("h").agg(F.collect_list(F.struct("item", "n", "place")).alias("places"))
    weights = hits.groupBy("h").agg(F.count("*").alias("w"))
    shared = hot_join(hits, of_seed, ["h"], "w", weights=weights).select("doc_id", "t", F.explode("places").alias("p"))
    pairs = shared.groupBy("doc_id", "t", "p.item", "p.n").agg(F.collect_set("p.place").alias("places"))
    reach = F.array_distinct(F.flatten(F.transform("places", lambda p: F.sequence(p, p + (least - 1)))))
    pairs = scratch.save(pairs.where(F.size(reach) >= coverage * F.col("n")).select("doc_id", "t", "item"), "pairs")

    tokens = scratch.save(_item_tokens(items), "tokens")
    known = tokens.dropDuplicates(["item"]).select("item", "tokens")
    given = hot_join(pairs, known, ["item"], "w", weights=pairs.groupBy("item").agg(F.count("*").alias("w")))
    given = given.groupBy(F.col("doc_id").alias("d"), "t").agg(F.collect_list(F.struct("item", "tokens")).alias("items"))
    ids = Sieve(pairs.select(F.xxhash64("doc_id").alias("k")), "k")

    def marked(batch: pa.RecordBatch):
        for lo, hi, words in words_of(unsqueezed(batch.column("packed")), NON_ALNUM, lower=True):
            yield {"doc_id": batch.column("doc_id").slice(lo, hi - lo), "packed": batch.column("packed").slice(lo, hi - lo), "t": _row_hash(words)}

    near = map_batches(squeezed(slim.where(ids.maybe(F.xxhash64("doc_id"))), ["doc_id"]), marked, doc_id="long", packed="binary", t="long").withColumnRenamed("t", "u")
    meet = near.join(given.hint("merge"), F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("u") == F.col("t"))).select("doc_id", "packed", "items")

    def step(batch: pa.RecordBatch):
        ids, rows = batch.column("doc_id").to_pylist(), []
        for lo, _, words in words_of(unsqueezed(batch.column("packed")), NON_ALNUM, lower=True):
            for r in range(words.rows):
                own = words.hash[words.ptr[r] : words.ptr[r + 1]]
                for x in batch.column("items")[lo + r].as_py():
                    item = np.array(x["tokens"], np.int64).view(_U)
                    found = tiles(item, own, least)
                    share = sum(t[2] for t in found) / len(item)
                    if share >= coverage:
                        rows.append((ids[lo + r], x["item"], share, len(found), max(t[2] for t in found)))
        if rows:
            yield dict(zip(("doc_id", "item", "coverage", "n_tiles", "longest"), map(list, zip(*rows, strict=True)), strict=True))

    leaks = scratch.save(map_batches(meet, step, doc_id="long", item="long", coverage="double", n_tiles="long", longest="long"), "leaks")
    named = tokens.groupBy("item").agg(F.collect_list(F.struct("item_id")).alias("named"))  # a list of structs keeps null ids
    out = hot_join(leaks, named, ["item"], "w", weights=leaks.groupBy("item").agg(F.count("*").alias("w")))
    return out.select("doc_id", F.explode("named").alias("x"), "coverage", "n_tiles", "longest").select("doc_id", "x.item_id", "coverage", "n_tiles", "longest")


def op2_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, item_id, coverage, n_tiles, longest of every leak of a benchmark item in a document."""
    return contaminated(docs_of(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
