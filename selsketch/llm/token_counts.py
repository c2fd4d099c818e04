"""Word-piece counts by a linear longest-match automaton.

The vocabulary's trie gets failure links with precomputed numbers of popped tokens, so a word's greedy longest-match pieces
are counted in one pass over its bytes, without backing up and without building a piece.  The pass runs over all distinct
words of a slice at once, column by column; words longer than LONG bytes are passed one by one.
"""

from __future__ import annotations

import json
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import docs_of, kept_in_worker, map_batches, small_batches
from .packing import vocabulary_path
from .text import words_of

_LOST = -1
LONG = 64


@dataclass
class Automaton:
    """Transitions as sorted keys state*256+byte; ``fail`` is the state after the pops, _LOST if a byte can't be matched."""

    keys: np.ndarray
    goal: np.ndarray
    fail: np.ndarray
    pops: np.ndarray
    entry: int

    def step(self, state: np.ndarray, byte: np.ndarray) -> np.ndarray:
        key = state * 256 + byte
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        return np.where(self.keys[at] == key, self.goal[at], _LOST)

    def counts(self, data: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """Pieces of the words data[start:end]; a word with an unmatchable byte is one unknown piece."""
        out, short = np.zeros(len(start), np.int64), end - start <= LONG
        out[short] = self._columns(data, start[short], end[short])
        for i in np.flatnonzero(~short):
            out[i] = self.one(data[start[i] : end[i]].tobytes())
        return out

    @cached_property
    def _moves(self) -> tuple[dict[int, int], list[int], list[int]]:
        return dict(zip(self.keys.tolist(), self.goal.tolist(), strict=True)), self.fail.tolist(), self.pops.tolist()

    def one(self, word: bytes) -> int:
        goal, fail, pops = self._moves
        state, pieces = self.entry, 0
        for byte in word:
            while (to := goal.get(state * 256 + byte)) is None:
                pieces += pops[state]
                state = fail[state]
                if state == _LOST:
                    return 1
            state = to
        while state:
            pieces += pops[state]
            state = fail[state]
            if state == _LOST:
                return 1
        return pieces

    def _columns(self, data: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        order = np.argsort(start - end, kind="stable")
        start, end = start[order], end[order]
        size = end - start
        state, pieces, lost = np.full(len(start), self.entry), np.zeros(len(start), np.int64), np.zeros(len(start), bool)
        alive = len(start)
        for i in range(int(size.max(initial=0))):
            alive = int(np.searchsorted(-size[:alive], -i, "left"))  # sizes fall, so the longer words come first
            todo = np.flatnonzero(~lost[:alive])
            byte = data[start[todo] + i].astype(np.int64)
            while len(todo):
                to = self.step(state[todo], byte)
                stuck = to == _LOST
                state[todo[~stuck]] = to[~stuck]
                todo, byte = todo[stuck], byte[stuck]
                self._pop(todo, state, pieces, lost)
                go = ~lost[todo]
                todo, byte = todo[go], byte[go]
        todo = np.flatnonzero(~lost & (state != 0) & (size > 0))
        while len(todo):
            self._pop(todo, state, pieces, lost)
            todo = todo[~lost[todo] & (state[todo] != 0)]
        pieces[lost] = 1
        out = np.empty_like(pieces)
        out[order] = pieces
        return out

    def _pop(self, todo: np.ndarray, state: np.ndarray, pieces: np.ndarray, lost: np.ndarray) -> None:
        pieces[todo] += self.pops[state[todo]]
        state[todo] = self.fail[state[todo]]
        gone = todo[state[todo] == _LOST]
        lost[gone] = True
        state[gone] = 0


def build(pieces: set[bytes], mark: bytes = b"") -> Automaton:
    """Automaton of the pieces.  ``mark`` is put before each word: the pieces with it are the word-initial ones."""
    children: list[dict[int, int]] = [{}]
    token, depth = [False], [0]
    for piece in sorted(pieces):
        at = 0
        for c in piece:
            if c not in children[at]:
                children[at][c] = len(children)
                children.append({})
                token.append(False)
                depth.append(depth[at] + 1)
            at = children[at][c]
        token[at] = bool(piece)
    fail, pops = np.full(len(children), _LOST, np.int64), np.zeros(len(children), np.int64)
    queue = [0]
    for at in queue:  # breadth first: a state's link needs only shallower states
        for c, to in children[at].items():
            queue.append(to)
            if token[to]:
                fail[to], pops[to] = 0, 1
                continue
            link, n = fail[at], pops[at]
            while link != _LOST and c not in children[link]:
                n += pops[link]
                link = fail[link]
            if link != _LOST:
                fail[to], pops[to] = children[link][c], n
    edges = sorted((s * 256 + c, to) for s, next_ in enumerate(children) for c, to in next_.items())
    keys, goal = np.array(edges, np.int64).reshape(-1, 2).T.copy()
    entry = 0
    for c in mark:
        if c not in children[entry]:
            raise ValueError("the vocabulary lacks the mark")
        entry = children[entry][c]
    return Automaton(keys, goal, fail, pops, entry)


def byte_pieces(path: str) -> set[bytes]:
    """The pieces of a byte-level vocabulary file, as bytes; a leading space marks word-initial ones."""
    codes = [*range(33, 127), *range(161, 173), *range(174, 256)]
    back = {chr(c): c for c in codes} | {chr(256 + i): b for i, b in enumerate(b for b in range(256) if b not in set(codes))}
    vocab = json.loads(open(path, encoding="utf-8").read())["model"]["vocab"]
    return {bytes(back[c] for c in piece) for piece in vocab if all(c in back for c in piece)}


def token_counts(docs: DataFrame, vocabulary: str | None = None) -> DataFrame:
    """docs(doc_id, text) -> (doc_id, n_words, n_tokens), one row per row.

    Each word, a run outside \\x20 and \\x09-\\x0D, is matched with a space before it, greedily by the longest piece.  Null
    and empty texts count 0.  Repeated ids give repeated rows; other columns are ignored.
    """
    path = vocabulary or vocabulary_path()
    small_batches(docs.sparkSession)

    def step(batch: pa.RecordBatch):
        automaton = kept_in_worker(("automaton", path), lambda: build(byte_pieces(path), b" "))
        ids = batch.column("doc_id")
        for lo, hi, words in words_of(batch.column("text")):
            _, first, which = np.unique(words.hash, return_index=True, return_inverse=True)
            total = np.append(0, np.cumsum(automaton.counts(words.data, words.start[first], words.end[first])[which])) if len(words.hash) else np.zeros(1, np.int64)
            yield {"doc_id": ids.slice(lo, hi - lo), "n_words": words.counts().astype(np.int64), "n_tokens": total[words.ptr[1:]] - total[words.ptr[:-1]]}

    return map_batches(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")), step, doc_id="long", n_words="long", n_tokens="long")


def op5_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_words, n_tokens for every document."""
    return token_counts(docs_of(spark, sf_dir))
