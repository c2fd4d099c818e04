"""Repeated-passage removal on a compacted de Bruijn graph of tokens.

Nodes are the words' KMER-grams that are the smallest, by hash, of some WINDOW consecutive words (one in about twenty), and an
edge is a step of some document from one node to the next.  A window of WINDOW words always holds a node, and equal windows
hold the same one, so a window that stands in two documents can only lie around a node that both have.

 1. One scan writes each document as node occurrences: the node before and the node after (its edges), hashes of the words
    to the left and to the right that its windows reach, and where its windows start.
 2. An aggregation gives each node's degrees: how many different predecessors and successors, left and right contexts.
    A node of a single document carries nothing repeated and is dropped.
 3. Nodes with one context on either side don't branch.  A join of the edges' ends finds those that follow each other
    without a branch, and such paths are compacted into one row each, with the coordinates of their first source.
 4. At branching nodes, the distinct contexts (not their occurrences) are opened at the coordinates of their first source and
    their windows compared by BLAKE2 digests of the words.
 5. Compacted paths are digested at their source too; a span goes only if the digest of its own words is that of its source.

Hot passages stay one row per node; joins on a node spread the keys that hold many rows.  Texts move only where a Sieve of
the documents concerned lets them through.
"""

from __future__ import annotations

import hashlib
from itertools import compress

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import Scratch, Sieve, docs_of, hot_join, map_batches
from .text import Words, signed, words_of

WINDOW, KMER = 50, 10
_U = np.uint64


def minimizers(words: Words, window: int, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Window starts, the word index of each one's leftmost minimizer, and that k-mer's hash."""
    width, n = window - k + 1, len(words.start)
    value = np.full(n + width, np.iinfo(_U).max, _U)
    at = words.windows(k)
    value[at] = words.run_hash(at, at + k)
    low, where, span = value, np.arange(len(value)), 1
    while span < width:
        s = min(span, width - span)
        later = low[s:] < low[:-s]
        low = np.concatenate([np.where(later, low[s:], low[:-s]), low[-s:]])
        where = np.concatenate([np.where(later, where[s:], where[:-s]), where[-s:]])
        span += s
    starts = words.windows(window)
    return starts, where[starts], value[where[starts]]


def _row_hash(words: Words) -> np.ndarray:
    return signed(words.run_hash(words.ptr[:-1], words.ptr[1:], 1))


def occurrences(docs: DataFrame, window: int = WINDOW, k: int = KMER) -> DataFrame:
    """(doc_id, t, h, before, after, l, r, at, n): n windows from word ``at`` on lie around node h, between the nodes before
    and after (null at an end); l and r hash what these windows hold up to and from the node; t tells texts of one id apart."""

    def step(batch: pa.RecordBatch):
        ids = batch.column("doc_id").to_numpy(zero_copy_only=False)
        for lo, _, words in words_of(batch.column("text")):
            start, anchor, h = minimizers(words, window, k)
            if not len(start):
                continue
            cut = np.ones(len(start), bool)
            cut[1:] = (anchor[1:] != anchor[:-1]) | (start[1:] != start[:-1] + 1)
            first = np.flatnonzero(cut)
            last = np.append(first[1:], len(start)) - 1
            row, node = words.row_of(start[first]), signed(h[first])
            joined = row[1:] == row[:-1]  # windows of a row are consecutive, so its nodes follow each other
            left = words.run_hash(start[first], anchor[first] + k)
            right = words.run_hash(anchor[first], start[last] + window)
            yield {
                "doc_id": ids[lo + row], "t": _row_hash(words)[row], "h": node, "before": pa.array(np.append(0, node[:-1]), mask=np.append(True, ~joined)),
                "after": pa.array(np.append(node[1:], 0), mask=np.append(~joined, True)), "l": signed(left), "r": signed(right),
                "at": (start[first] - words.ptr[row]).astype(np.int32), "n": (last - first + 1).astype(np.int32),
            }

    docs = docs.where(F.col("doc_id").isNotNull()).select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    return map_batches(docs, step, doc_id="long", t="long", h="long", before="long", after="long", l="long", r="long", at="int", n="int")


def _packed(docs: DataFrame) -> DataFrame:
    def step(batch: pa.RecordBatch):
        press, texts, ids = zstandard.ZstdCompressor(level=3), batch.column("text"), batch.column("doc_id")
        for lo, hi, words in words_of(texts):
            packed = [press.compress((x or "").encode()) for x in texts.slice(lo, hi - lo).to_pylist()]
            yield {"doc_id": ids.slice(lo, hi - lo), "t": _row_hash(words), "packed": packed}

    return map_batches(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")), step, doc_id="long", t="long", packed="binary")


class _Joined:
    """Words of a text joined by one space, and the bytes of any run of them."""

    def __init__(self, text: bytes):
        self.words = text.split()  # bytes.split() parts at exactly \x20 and \x09-\x0D
        self.bytes = memoryview(b" ".join(self.words))
        self.at = np.cumsum([0, *[len(w) + 1 for w in self.words]]).tolist()

    def digest(self, start: int, end: int) -> bytes:
        return hashlib.blake2b(self.bytes[self.at[start] : self.at[end] - 1], digest_size=16).digest()


def _opened(docs: DataFrame, wanted: DataFrame, window: int) -> DataFrame:
    """(h, l, r, i, w, doc_id): digests of the paths in wanted(doc_id, t, h, l, r, at, n, whole), read at these coordinates:
    of all words of a path as i = -1, and, unless ``whole``, of each of its windows."""
    listed = wanted.groupBy("doc_id", "t").agg(F.collect_list(F.struct("h", "l", "r", "at", "n", "whole")).alias("paths"))
    sieve = Sieve(listed.select(F.xxhash64("doc_id").alias("d")), "d")

    def step(batch: pa.RecordBatch):
        press, names = zstandard.ZstdDecompressor(), ("h", "l", "r", "i", "w", "doc_id")
        rows: list[tuple] = []
        for doc, packed, paths in zip(batch.column("doc_id").to_pylist(), batch.column("packed"), batch.column("paths"), strict=True):
            text = _Joined(press.decompress(packed.as_py()))
            for p in paths.as_py():
                spans = [(-1, p["at"], p["at"] + p["n"] - 1 + window)]
                if not p["whole"]:
                    spans += [(i, p["at"] + i, p["at"] + i + window) for i in range(p["n"])]
                rows += [(p["h"], p["l"], p["r"], i, text.digest(a, b), doc) for i, a, b in spans]
                if len(rows) > 20_000:
                    yield dict(zip(names, map(list, zip(*rows, strict=True)), strict=True))
                    rows = []
        if rows:
            yield dict(zip(names, map(list, zip(*rows, strict=True)), strict=True))

    near = docs.where(sieve.maybe(F.when(F.col("doc_id").isNotNull(), F.xxhash64(F.col("doc_id").cast("long")))))
    joined = _packed(near).join(listed.hint("merge"), ["doc_id", "t"]).dropDuplicates(["doc_id", "t"])  # repeated rows open once
    return map_batches(joined, step, h="long", l="long", r="long", i="int", w="binary", doc_id="long")


def repeated_spans(docs: DataFrame, window: int = WINDOW, k: int = KMER) -> DataFrame:
    """docs(doc_id, text) -> (doc_id, t, start, end, proof): word ranges covered by windows that a document of smaller id has
    too, with the digest of the words at the source."""
    scratch = Scratch(docs.sparkSession)
    seen = scratch.save(occurrences(docs, window, k), "occurrences")
    ends = [f(c).alias(f"{c}{i}") for c in ("before", "after", "l", "r") for i, f in enumerate((F.min, F.max))]
    nodes = seen.groupBy("h").agg(F.count("*").alias("w"), *ends, F.count("before").alias("nb"), F.count("after").alias("na"), F.min("doc_id").alias("d0"), F.max("doc_id").alias("d1"))
    one = lambda c: F.col(f"{c}0") == F.col(f"{c}1")
    nodes = nodes.where("d0 < d1").select(
        "h", "w", "d0", (one("l") & one("r")).alias("straight"),
        F.when(one("before") & (F.col("nb") == F.col("w")), F.col("before0")).alias("before"), F.when(one("after") & (F.col("na") == F.col("w")), F.col("after0")).alias("after"),
    )
    nodes = scratch.save(nodes, "nodes")
    met = scratch.save(hot_join(seen.drop("before", "after"), nodes.select("h", "w", "d0", "straight"), ["h"], "w"), "met")

    # nonbranching paths: u is followed by v in all occurrences of u, and v preceded by u in all of v
    plain = nodes.where("straight")
    head_of = plain.select(F.col("h").alias("u"), F.col("after").alias("v"))
    follows = plain.join(head_of.hint("merge"), (F.col("before") == F.col("u")) & (F.col("h") == F.col("v")), "left").select("h", "w", F.col("u").isNotNull().alias("follows"))
    source = met.where("straight AND doc_id = d0").groupBy("h").agg(F.min(F.struct("doc_id", "t", "at", "n")).alias("src"))
    steps = follows.join(source.hint("merge"), "h").select("h", "w", "follows", "src.*")
    along = Window.partitionBy("doc_id", "t").orderBy("at")
    head = F.last(F.when(~F.col("follows"), F.col("at")), True).over(along).alias("head")
    paths = steps.select("h", "w", "doc_id", "t", "at", "n", head).groupBy("doc_id", "t", "head")
    paths = paths.agg(F.sum("n").cast("int").alias("n"), F.max(F.when(F.col("at") == F.col("head"), F.col("h"))).alias("h"), F.max("w").alias("w"))
    paths = scratch.save(paths.select("doc_id", "t", "h", F.lit(0).cast("long").alias("l"), F.lit(0).cast("long").alias("r"), F.col("head").alias("at"), "n", F.lit(True).alias("whole"), "w"), "paths")

    branching = met.where("NOT straight")
    turns = branching.groupBy("h", "l", "r").agg(F.min(F.struct("doc_id", "t", "at", "n")).alias("src"), F.count("*").alias("w"))
    turns = scratch.save(turns.select("src.doc_id", "src.t", "h", "l", "r", "src.at", "src.n", F.lit(False).alias("whole"), "w"), "turns")
    opened = scratch.save(_opened(docs, paths.drop("w").unionByName(turns.drop("w")), window), "opened")
    proofs = opened.where("i < 0").select("h", "l", "r", F.col("w").alias("proof"))

    # a path follows its head node, whose context is that of all its occurrences
    whole = (F.col("at") + F.col("n") - 1 + window).alias("end")
    known = scratch.save(paths.join(proofs.hint("merge"), ["h", "l", "r"]).select("h", "n", "proof", "w"), "known")
    straight = hot_join(met.where("straight AND doc_id > d0").select("doc_id", "t", "h", "at"), known, ["h"], "w")
    straight = straight.select("doc_id", "t", F.col("at").alias("start"), whole, "proof")

    windows = opened.where("i >= 0")
    shared = windows.groupBy("w").agg(F.count("*").alias("weight"), F.min("doc_id").alias("first"), F.max("doc_id").alias("last"))
    shared = scratch.save(shared.where("first < last").select("w", "weight", "first"), "shared")
    early = hot_join(windows, shared, ["w"], "weight").where("first < doc_id")
    early = early.groupBy("h", "l", "r").agg(F.collect_list(F.struct("i", "first", "w")).alias("early"))
    known = turns.select("h", "l", "r", "w", F.col("doc_id").alias("own")).join(early.hint("merge"), ["h", "l", "r"], "left")
    known = scratch.save(known.join(proofs.hint("merge"), ["h", "l", "r"]), "known")
    scratch.drop(opened, shared)
    at_turn = hot_join(branching.select("doc_id", "t", "h", "l", "r", "at", "n"), known, ["h", "l", "r"], "w")
    full = at_turn.where("own < doc_id").select("doc_id", "t", F.col("at").alias("start"), whole, "proof")
    some = at_turn.where("own >= doc_id").select("doc_id", "t", "at", F.explode(F.filter("early", lambda e: e["first"] < F.col("doc_id"))).alias("e"))
    some = some.select("doc_id", "t", (F.col("at") + F.col("e.i")).alias("start"), (F.col("at") + F.col("e.i") + window).alias("end"), F.col("e.w").alias("proof"))
    return scratch.save(straight.union(full).union(some), "spans")


def without_repeats(docs: DataFrame, window: int = WINDOW, k: int = KMER, text: bool = True) -> DataFrame:
    """docs(doc_id, text) -> (doc_id, n_words, n_removed, kept_sha256[, kept_text]), one row per row of docs.

    Words are runs outside \\x20 and \\x09-\\x0D; null and empty texts have none.  Documents of fewer than ``window`` words
    are kept whole.  Null doc_ids have no order: they neither lose words nor make others lose theirs.  Rows that repeat a
    doc_id count as documents of equal id, so none is the other's repeat.  Other columns are ignored.
    """
    found = repeated_spans(docs, window, k)
    sieve = Sieve(found.select(F.xxhash64("doc_id").alias("d")), "d")
    spans = found.groupBy("doc_id", "t").agg(F.collect_set(F.struct("start", "end", "proof")).alias("spans"))
    kinds = {"doc_id": "long", "n_words": "long", "n_removed": "long", "kept_sha256": "string"} | ({"kept_text": "string"} if text else {})
    slim = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))

    def row(doc, words: list[bytes], kept: list[bytes]) -> tuple:
        left = b" ".join(kept)
        return (doc, len(words), len(words) - len(kept), hashlib.sha256(left).hexdigest(), *([left.decode()] if text else []))

    def columns(rows: list[tuple]) -> dict:
        return dict(zip(kinds, map(list, zip(*rows, strict=True)), strict=True))

    def untouched(batch: pa.RecordBatch):
        rows = [row(i, words := (x.as_py() or "").encode().split(), words) for i, x in zip(batch.column("doc_id").to_pylist(), batch.column("text"), strict=True)]
        if rows:
            yield columns(rows)

    def cut(batch: pa.RecordBatch):
        press, rows = zstandard.ZstdDecompressor(), []
        for doc, packed, found in zip(batch.column("doc_id").to_pylist(), batch.column("packed"), batch.column("spans"), strict=True):
            whole = _Joined(press.decompress(packed.as_py()))
            cover = np.zeros(len(whole.words) + 1, np.int64)
            for s in found.as_py() or ():
                if whole.digest(s["start"], s["end"]) == s["proof"]:
                    cover[s["start"]] += 1
                    cover[s["end"]] -= 1
            rows.append(row(doc, whole.words, list(compress(whole.words, np.cumsum(cover[:-1]) == 0))))
        if rows:
            yield columns(rows)

    maybe = F.coalesce(sieve.maybe(F.when(F.col("doc_id").isNotNull(), F.xxhash64("doc_id"))), F.lit(False))
    met = _packed(slim.where(maybe)).join(spans.hint("merge"), ["doc_id", "t"], "left")
    return map_batches(slim.where(~maybe), untouched, **kinds).union(map_batches(met, cut, **kinds))


def op3_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 for every document."""
    return without_repeats(docs_of(spark, sf_dir), text=False)


OP3_SQL = r"""
WITH d AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM documents),
w AS (SELECT doc_id, unnest(ws) AS word, unnest(range(1, len(ws) + 1)) AS i FROM d),
g AS (SELECT doc_id, p, md5(array_to_string(ws[p:p + 49], ' ')) AS h
      FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 48)) AS p FROM d)),
m AS (SELECT h, min(doc_id) AS first FROM g GROUP BY h),
r AS (SELECT g.doc_id, g.p FROM g JOIN m USING (h) WHERE m.first < g.doc_id),
c AS (SELECT w.doc_id, w.word, w.i, coalesce(max(r.p) OVER (PARTITION BY w.doc_id ORDER BY w.i) >= w.i - 49, false) AS gone
      FROM w LEFT JOIN r ON r.doc_id = w.doc_id AND r.p = w.i),
k AS (SELECT doc_id, count(*) AS n_words, count(*) FILTER (WHERE gone) AS n_removed,
             string_agg(word, ' ' ORDER BY i) FILTER (WHERE NOT gone) AS kept FROM c GROUP BY doc_id)
SELECT documents.doc_id, coalesce(n_words, 0) AS n_words, coalesce(n_removed, 0) AS n_removed,
       sha256(coalesce(kept, '')) AS kept_sha256
FROM documents LEFT JOIN k USING (doc_id)
"""
