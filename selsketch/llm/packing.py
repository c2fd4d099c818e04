"""Sequence packing: shortest-pack-first over the length histogram.

Documents are tokenized once and cut at multiples of the sequence length; what remains is a piece of 1..LENGTH tokens.  The
driver sees only the histogram of piece lengths (at most LENGTH numbers, whatever the input) and plans patterns of lengths
with counts.  Each piece then finds its place by its rank among the pieces of its length; ranks come from counts per
(length, chunk), so a length that holds most pieces is still spread over many tasks.
"""

from __future__ import annotations

import base64
import zlib
from collections import defaultdict
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import Scratch, docs_of, kept_in_worker, map_batches

LENGTH = 1024
SEPARATOR = 0
CHUNK_ROWS, SPAN = 20_000, 1_000


def vocabulary_path(name: str = "byte_bpe_50k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def _encoder(path: str) -> Callable[[str], list[int]]:
    """Ids of the tokenizer file, special tokens in a text included, as ``Tokenizer.encode`` with its defaults gives them.

    A plain byte-level BPE (ids in the order of the merges, usual split, special tokens without options of their own) runs on
    the faster of the two libraries; any other file, and a text that the faster one refuses, goes to the other.
    """
    import json

    import public_tokenizers
    import tiktoken
    from tokenizers import Tokenizer

    slow = Tokenizer.from_file(path)
    exact = lambda text: slow.encode(text, add_special_tokens=False).ids
    rest = json.loads(open(path, encoding="utf-8").read())
    pre, model, added = rest.get("pre_tokenizer") or {}, rest["model"], rest.get("added_tokens", [])
    split = pre.get("type") == "ByteLevel" and not pre.get("add_prefix_space") and pre.get("use_regex", True) and not rest.get("normalizer")
    options = ("dropout", "unk_token", "continuing_subword_prefix", "end_of_word_suffix", "byte_fallback", "ignore_merges")
    made = [model["vocab"].get("".join(m.split(" ") if isinstance(m, str) else m), -1) for m in model.get("merges", [])]
    plain = model.get("type") == "BPE" and not any(model.get(k) for k in options) and made == sorted(made)
    special = {x["content"]: x["id"] for x in added}
    simple = not any(x.get(k) for x in added for k in ("lstrip", "rstrip", "single_word")) and not any(a != b and a in b for a in special for b in special)
    if not (split and plain and simple and rest.get("truncation") is None and rest.get("padding") is None):
        return exact
    codes = [*range(33, 127), *range(161, 173), *range(174, 256)]
    back = {chr(c): c for c in codes} | {chr(256 + i): b for i, b in enumerate(b for b in range(256) if b not in set(codes))}
    ranks = {bytes(back[c] for c in piece): i for piece, i in model["vocab"].items() if piece not in special and all(c in back for c in piece)}
    fast = tiktoken.Encoding("file", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens=special)
    names = set(special)

    def encode(text: str) -> list[int]:
        try:
            return fast.encode(text, allowed_special=names, disallowed_special=())
        except BaseException as e:  # the library's panics aren't Exceptions
            if isinstance(e, (KeyboardInterrupt, SystemExit, MemoryError)):
                raise
            return exact(text)

    return encode


def pieces(docs: DataFrame, length: int = LENGTH, tokenizer: str | None = None, ids: bool = False) -> DataFrame:
    """(doc_id, start, length, ids_crc32, doc_tokens[, ids]): each document's ids and the separator, cut every ``length``."""
    path = tokenizer or vocabulary_path()

    def step(batch: pa.RecordBatch):
        encode, ids_of = kept_in_worker(("encoder", path), lambda: _encoder(path)), batch.column("doc_id")
        names = ["row", "start", "length", "ids_crc32", "doc_tokens"] + ["ids"] * ids
        out: dict[str, list] = {k: [] for k in names}

        def done():
            return {"doc_id": ids_of.take(pa.array(out.pop("row"), pa.int64()))} | out

        for i, text in enumerate(batch.column("text")):
            whole = np.asarray([*encode(text.as_py() or ""), SEPARATOR], "<u4")
            for at in range(0, len(whole), length):
                part = whole[at : at + length]
                for k, v in zip(names, (i, at, len(part), zlib.crc32(part.tobytes()), len(whole), part.astype(np.int64)), strict=False):
                    out[k].append(v)
        if out["row"]:
            yield done()

    kinds = {"doc_id": "long", "start": "long", "length": "long", "ids_crc32": "long", "doc_tokens": "long"} | ({"ids": "longs"} if ids else {})
    return map_batches(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")), step, **kinds)


def plan_patterns(histogram: dict[int, int], length: int = LENGTH) -> list[tuple[int, tuple[int, ...]]]:
    """Shortest pack first: lengths longest first; each goes to the emptiest open pack that has room, else to a new one.

    Packs of equal content are one counted pattern.  Returns (count, lengths of the pattern, longest first).
    """
    room: dict[int, list[tuple[int, tuple[int, ...]]]] = defaultdict(list)
    for size in sorted((k for k, v in histogram.items() if v > 0), reverse=True):
        left = histogram[size]
        while left:
            free = max((r for r, packs in room.items() if packs), default=0)
            if free < size:
                fits = length // size
                whole, rest = divmod(left, fits)
                if whole:
                    room[length - fits * size].append((whole, (size,) * fits))
                if rest:
                    room[length - rest * size].append((1, (size,) * rest))
                break
            count, content = room[free].pop()
            used = min(count, left)
            if count > used:
                room[free].append((count - used, content))
            room[free - size].append((used, (*content, size)))
            left -= used
    return [pack for packs in room.values() for pack in packs]


def _places(patterns: list[tuple[int, tuple[int, ...]]]) -> dict[str, np.ndarray]:
    """Rank ranges: the pieces of length ``size`` with ranks from ``first`` on fill ``copies`` slots of packs ``pack``..."""
    taken: dict[int, int] = defaultdict(int)
    rows, pack = [], 0
    for count, content in patterns:
        at = 0
        for size in sorted(set(content), reverse=True):
            copies = content.count(size)
            rows.append((size, taken[size], copies, pack, at))
            taken[size] += copies * count
            at += copies * size
        pack += count
    rows.sort()
    return dict(zip(("size", "first", "copies", "pack", "at"), np.array(rows, np.int64).reshape(-1, 5).T, strict=True))


def pack(docs: DataFrame, length: int = LENGTH, tokenizer: str | None = None, ids: bool = False) -> DataFrame:
    """docs(doc_id, text) -> one row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset[, ids].

    Null and empty texts are one separator.  Repeated doc_ids are separate documents; a null doc_id stays null.  Other
    columns are ignored.  Sequences are gapless from offset 0.
    """
    scratch = Scratch(docs.sparkSession)
    cut = scratch.save(pieces(docs, length, tokenizer, ids), "pieces")
    histogram = {r["length"]: r["n"] for r in cut.groupBy("length").agg(F.count("*").alias("n")).collect()}  # <= LENGTH rows
    place = _places(plan_patterns(histogram, length))
    chunks = max(64, sum(histogram.values()) // CHUNK_ROWS)
    chunked = cut.withColumn("chunk", F.pmod(F.xxhash64("doc_id", "start", "ids_crc32"), F.lit(chunks)))
    counts = scratch.save(chunked.groupBy("length", "chunk").agg(F.count("*").alias("n")), "counts")
    counts = counts.withColumn("span", F.floor(F.col("chunk") / SPAN))  # prefix sums in two levels, so no task holds all chunks
    spans = counts.groupBy("length", "span").agg(F.sum("n").alias("n"))
    before = lambda *keys: Window.partitionBy("length", *keys[:-1]).orderBy(keys[-1]).rowsBetween(Window.unboundedPreceding, -1)
    far = spans.select("length", "span", F.coalesce(F.sum("n").over(before("span")), F.lit(0)).alias("far"))
    base = counts.join(far.hint("merge"), ["length", "span"]).select("length", "chunk", (F.col("far") + F.coalesce(F.sum("n").over(before("span", "chunk")), F.lit(0))).alias("base"))
    own = Window.partitionBy("length", "chunk").orderBy("doc_id", "start", "ids_crc32")
    ranked = chunked.withColumn("rank", F.row_number().over(own) - 1).join(base.hint("merge"), ["length", "chunk"])
    ranked = ranked.withColumn("rank", F.col("rank") + F.col("base")).drop("base", "chunk")

    def step(batch: pa.RecordBatch):
        size, rank = batch.column("length").to_numpy(), batch.column("rank").to_numpy()
        lo, hi = np.searchsorted(place["size"], size, "left"), np.searchsorted(place["size"], size, "right")
        key = np.stack([size, rank], 1)
        order = np.lexsort((key[:, 1], key[:, 0]))
        at = np.empty(len(size), np.int64)
        for i in np.split(order, np.flatnonzero(np.diff(size[order])) + 1):
            if len(i):
                a, b = lo[i[0]], hi[i[0]]
                at[i] = a + np.searchsorted(place["first"][a:b], rank[i], "right") - 1
        local = rank - place["first"][at]
        nth, slot = np.divmod(local, place["copies"][at])
        out = {n: batch.column(n) for n in batch.schema.names if n != "rank"}
        yield out | {"sequence_id": place["pack"][at] + nth, "offset": place["at"][at] + slot * size}

    kinds = {"doc_id": "long", "start": "long", "length": "long", "ids_crc32": "long", "doc_tokens": "long"} | ({"ids": "longs"} if ids else {})
    return map_batches(ranked.select(*kinds, "rank"), step, **kinds, sequence_id="long", offset="long")


def op4_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset for every piece of every document."""
    return pack(docs_of(spark, sf_dir))
