"""Token ids of whole texts through the tokenizers library, encoding each distinct stretch once.

A text is cut before every run of ASCII white space, which neither vocabulary's pre-tokenizer
joins with what precedes it, so the ids of the stretches in order are the ids of the text. A
text with other Unicode white space is encoded whole. Stretches are keyed by 64-bit hash and
length; the store is emptied when it holds ``STORE`` stretches, which bounds a worker's memory.
"""

from __future__ import annotations

import os
import re
from pathlib import Path

import numpy as np

from . import textkit as tk

STORE = 1_500_000
JOIN = 64
#: UTF-8 of Unicode white space outside ASCII.
_WIDE_SPACE = re.compile(rb"\xc2[\x85\xa0]|\xe1\x9a\x80|\xe2\x80[\x80-\x8a\xa8\xa9\xaf]|\xe2\x81\x9f|\xe3\x80\x80")
_encoders: dict[tuple[str, bool], Encoder] = {}


def vocabulary(name: str) -> str:
    """Path of a public vocabulary file."""
    import public_tokenizers

    return str(public_tokenizers.path(name))


class Encoder:
    """ids(data, docs): flat ids and their number per document."""

    def __init__(self, path: str, with_space: bool):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.model = Tokenizer.from_file(path)
        self.with_space = with_space
        self._empty()

    def _empty(self) -> None:
        self.keys, self.at, self.size = np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64)
        self.pool: list[np.ndarray] = [np.zeros(0, np.uint32)]
        self.flat, self.used = np.zeros(0, np.uint32), 0

    def _learn(self, keys: np.ndarray, texts: list[str]) -> None:
        if len(self.keys) + len(keys) > STORE:
            self._empty()
        size, ids = np.zeros(len(texts), np.int64), []
        # stretches that begin with white space are put together, which spares most of a call's cost
        lead = "" if self.with_space else " "
        apart = [i for i, x in enumerate(texts) if not lead and not x[:1].isspace()]
        single = set(apart)
        joined = [i for i in range(len(texts)) if i not in single]
        runs = [joined[lo : lo + JOIN] for lo in range(0, len(joined), JOIN)]
        order = [*joined, *apart]
        for lo in range(0, len(runs), 256):
            part = runs[lo : lo + 256]
            for run, e in zip(part, self.model.encode_batch([lead.join(texts[i] for i in run) for run in part], add_special_tokens=False), strict=True):
                stops = np.cumsum([len(texts[i]) + len(lead) for i in run])
                ends = np.array([y for _, y in e.offsets], np.int64)
                size[run] = np.bincount(np.searchsorted(stops, ends), minlength=len(run))
                ids += e.ids
        for lo in range(0, len(apart), 4096):
            for i, e in zip(apart[lo : lo + 4096], self.model.encode_batch_fast([texts[i] for i in apart[lo : lo + 4096]], add_special_tokens=False), strict=True):
                size[i] = len(e.ids)
                ids += e.ids
        got = size[order]
        if self.used + len(ids) > len(self.flat):
            grown = np.zeros(2 * (self.used + len(ids)), np.uint32)
            grown[: self.used] = self.flat[: self.used]
            self.flat = grown
        self.flat[self.used : self.used + len(ids)] = ids
        at = np.empty_like(got)
        at[order] = self.used + np.cumsum(got) - got
        self.used += len(ids)
        where = np.searchsorted(self.keys, keys)
        self.keys, self.at, self.size = np.insert(self.keys, where, keys), np.insert(self.at, where, at), np.insert(self.size, where, size)

    def ids(self, data: np.ndarray, docs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        odd = [d for d in range(len(docs) - 1) if _WIDE_SPACE.search(data[docs[d] : docs[d + 1]])] if (data >= 0xE1).any() or (data == 0xC2).any() else []
        w = tk.split(data, docs)
        start, end = w.start, w.end
        if self.with_space:
            start = np.concatenate([[0], end[:-1]]) if len(end) else start
            has = w.counts > 0
            start[w.first[:-1][has]] = docs[:-1][has]
        first = w.first
        if self.with_space:  # white space at the end of a document is a stretch of its own
            last = np.where(has, end[np.maximum(w.first[1:], 1) - 1] if len(end) else 0, docs[:-1])
            tail = np.flatnonzero(last < docs[1:])
            start, end = np.insert(start, w.first[1:][tail], last[tail]), np.insert(end, w.first[1:][tail], docs[1:][tail])
            more = np.zeros(len(docs) - 1, np.int64)
            more[tail] = 1
            first = w.first + np.concatenate([[0], np.cumsum(more)])
        sums = tk.prefix(tk.BYTES[data], tk._P)
        key = tk.mix(tk.between(sums, tk._P, start, end)) ^ (end - start).astype(np.uint64)
        distinct, one, back = np.unique(key, return_index=True, return_inverse=True)
        place = np.searchsorted(self.keys, distinct)
        known = place < len(self.keys)
        known[known] = self.keys[place[known]] == distinct[known]
        fresh = np.flatnonzero(~known)
        if len(fresh):
            raw = data.tobytes()
            new = lambda which: self._learn(distinct[which], [raw[start[i] : end[i]].decode("utf-8", "replace") for i in one[which]])
            if len(self.keys) + len(fresh) > STORE:
                self._empty()
                new(np.arange(len(distinct)))
            else:
                new(fresh)
            place = np.searchsorted(self.keys, distinct)
        at, size = self.at[place], self.size[place]
        sizes = size[back]
        flat = self.flat[tk.spread(at[back], sizes)]
        ends = np.concatenate([[0], np.cumsum(sizes)])
        counts = ends[first[1:]] - ends[first[:-1]]
        if odd:
            parts = np.split(flat, np.cumsum(counts)[:-1])
            for d in odd:
                parts[d] = np.array(self.model.encode(data[docs[d] : docs[d + 1]].tobytes().decode("utf-8", "replace"), add_special_tokens=False).ids, np.uint32)
            counts = np.array([len(p) for p in parts], np.int64)
            flat = np.concatenate(parts)
        return flat, counts

    def ended(self, data: np.ndarray, docs: np.ndarray, end_id: int) -> tuple[np.ndarray, np.ndarray]:
        """As ids, with end_id after each document."""
        flat, counts = self.ids(data, docs)
        return np.insert(flat, np.cumsum(counts), end_id), counts + 1


def encoder(path: str, with_space: bool) -> Encoder:
    """This worker's encoder, which outlives a task."""
    key = (path, with_space)
    if key not in _encoders:
        _encoders[key] = Encoder(path, with_space)
    return _encoders[key]


def exists(path: str) -> str:
    if not Path(path).exists():
        raise FileNotFoundError(path)
    return path
