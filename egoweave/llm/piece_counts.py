"""Operator 6: greedy word-piece lengths by a linear longest-match automaton.

The vocabulary is a trie with one root for pieces that begin a word and one for those that go on. Each node has
a failure link (the node to go on from once the longest pieces of its text are given out) and the number of pieces so given
out, both found in one pass over the trie in breadth-first order. A word then takes one step or link per character, and only
counts are summed; no piece is built.

Pieces come from the public sentencepiece vocabulary: those that begin with its word mark start a word, the others go
on. The bare mark is a piece too: a word whose first characters have no marked piece counts it and goes on after it. The
vocabulary has a piece for each byte: a character without a piece counts one per byte of its UTF-8. Only a vocabulary
that lacks either leaves words that it cannot cover; each counts as one unknown piece. Words are cut at ASCII white
space. Null texts have no words; repeated rows and null ids stay.
Counts of distinct words are kept in the worker, up to STORE words.
"""

from __future__ import annotations

from collections import deque
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common, textkit as tk, tokens

MARK = "▁"
STORE = 2_000_000
_counters: dict[str, Counter] = {}


class Automaton:
    """length(word): number of greedy longest-match pieces. "" in begin is the bare mark; with by_bytes a character without a piece counts its bytes."""

    def __init__(self, begin: set[str], go_on: set[str], by_bytes: bool = False):
        self.by_bytes = by_bytes
        self.step: dict[tuple[int, str], int] = {}
        ends, parent = [False, False], [(-1, "")] * 2
        for root, pieces in ((0, begin), (1, go_on)):
            for piece in pieces:
                v = root
                for c in piece:
                    if (v, c) not in self.step:
                        self.step[v, c] = len(ends)
                        ends.append(False)
                        parent.append((v, c))
                    v = self.step[v, c]
                ends[v] = ends[v] or v > 1
        self.fail, self.popped = [-1] * len(ends), [0] * len(ends)
        if "" in begin:
            self.fail[0], self.popped[0] = 1, 1
        below: dict[int, list[int]] = {}
        for v in range(2, len(ends)):
            below.setdefault(parent[v][0], []).append(v)
        todo = deque([0, 1])
        while todo:
            for v in below.get(u := todo.popleft(), ()):
                todo.append(v)
                c = parent[v][1]
                if ends[v] or by_bytes and u == 1:
                    self.fail[v], self.popped[v] = 1, 1 if ends[v] else len(c.encode())
                    continue
                z, n = self.fail[u], self.popped[u]
                while z >= 0 and (z, c) not in self.step and not (by_bytes and z == 1):
                    n += self.popped[z]
                    z = self.fail[z]
                if (z, c) in self.step:
                    self.fail[v], self.popped[v] = self.step[z, c], n
                elif z >= 0:
                    self.fail[v], self.popped[v] = 1, n + len(c.encode())

    def length(self, word: str) -> int:
        step, fail, popped = self.step, self.fail, self.popped
        v = n = 0
        for c in word:
            while (t := step.get((v, c))) is None:
                if v == 1 and self.by_bytes:
                    n, t = n + len(c.encode()), 1
                    break
                n += popped[v]
                v = fail[v]
                if v < 0:
                    return 1
            v = t
        while v != 1:
            n += popped[v]
            v = fail[v]
            if v < 0:
                return 1
        return n


def pieces(path: str) -> tuple[set[str], set[str], bool]:
    """Pieces that begin a word (without the mark, "" for the bare one), pieces that go on, and whether every byte has a piece, of a sentencepiece model."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    begin, go_on, n_bytes = set(), set(), 0
    for i in range(model.get_piece_size()):
        n_bytes += model.is_byte(i)
        if model.is_control(i) or model.is_unknown(i) or model.is_byte(i) or model.is_unused(i):
            continue
        text = model.id_to_piece(i)
        if text.startswith(MARK) and MARK not in text[1:]:
            begin.add(text[1:])
        elif MARK not in text:
            go_on.add(text)
    return begin, go_on, n_bytes == 256


class Counter:
    """Lengths of many words; each distinct word passes the automaton once while it is in the store."""

    def __init__(self, path: str):
        self.automaton = Automaton(*pieces(path))
        self.keys, self.n = np.zeros(0, np.uint64), np.zeros(0, np.int64)

    def lengths(self, w: tk.Words) -> np.ndarray:
        distinct, one, back = np.unique(w.hash, return_index=True, return_inverse=True)
        if len(self.keys) > STORE:
            self.keys, self.n = self.keys[:0], self.n[:0]
        at = np.searchsorted(self.keys, distinct)
        known = at < len(self.keys)
        known[known] = self.keys[at[known]] == distinct[known]
        out = np.zeros(len(distinct), np.int64)
        out[known] = self.n[at[known]]
        raw, fresh = w.data.tobytes(), np.flatnonzero(~known)
        out[fresh] = [self.automaton.length(raw[a:b].decode("utf-8", "replace")) for a, b in zip(w.start[one[fresh]].tolist(), w.end[one[fresh]].tolist(), strict=True)]
        self.keys, self.n = np.insert(self.keys, at[fresh], distinct[fresh]), np.insert(self.n, at[fresh], out[fresh])
        return out[back]


def counter(path: str) -> Counter:
    if path not in _counters:
        _counters[path] = Counter(path)
    return _counters[path]


def count(docs: DataFrame, model: str) -> DataFrame:
    """(doc_id, n_words, n_tokens) of documents (doc_id, text)."""
    common.ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = counter(model)
        for batch in batches:
            for lo, hi, data, off in tk.pieces(batch.column(1)):
                w = tk.split(data, off)
                sums = np.concatenate([[0], np.cumsum(own.lengths(w))])
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo), pa.array(w.counts), pa.array(sums[w.first[1:]] - sums[w.first[:-1]])], ["doc_id", "n_words", "n_tokens"])

    return docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id bigint, n_words bigint, n_tokens bigint")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return count(spark.read.parquet(f"{sf_dir}/documents.parquet"), tokens.exists(tokens.vocabulary("piece_bpe_32k.model")))
