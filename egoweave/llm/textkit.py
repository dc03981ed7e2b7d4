"""Vectorised word splitting and hashing over Arrow string columns.

Words are maximal runs of bytes that are not separators. All hashes are 64-bit
polynomials over table values of the bytes (or of the words, for windows of words),
taken as differences of prefix sums, so that any window costs a constant number of
NumPy passes. Nulls count as empty texts. Pieces of at most ``CHUNK`` bytes (or one
document, where that is longer) are processed at a time, which bounds memory.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

CHUNK = 2 << 20
#: For passes that treat every document on its own, so that smaller pieces cost nothing.
STEP = 512 << 10
U64 = np.uint64
_P, _Q, _R = U64(0x9E3779B97F4A7C17), U64(0xD6E8FEB86659FD97), U64(0xA0761D6478BD642F)
BYTES = np.random.default_rng(20240229).integers(0, 2**64, 256, dtype=U64)

SPACE = np.zeros(256, bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True
NOT_ALNUM = np.zeros(256, bool)
NOT_ALNUM[[b for b in range(128) if not chr(b).isalnum()]] = True
FOLD = np.arange(256, dtype=np.uint8)
FOLD[65:91] += 32

_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def powers(base: np.uint64, n: int) -> tuple[np.ndarray, np.ndarray]:
    """base**i and base**-i modulo 2**64 for i below n at least."""
    have = _powers.get(int(base))
    if have is None or len(have[0]) < n:
        n = max(n, 1 << 16)
        inverse = U64(pow(int(base), -1, 2**64))
        have = tuple(np.concatenate([np.ones(1, U64), np.multiply.accumulate(np.full(n - 1, b, U64))]) for b in (base, inverse))
        _powers[int(base)] = have
    return have


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit values that spreads their bits."""
    x = x ^ (x >> U64(30))
    x = x * U64(0xBF58476D1CE4E5B9)
    x ^= x >> U64(27)
    x *= U64(0x94D049BB133111EB)
    x ^= x >> U64(31)
    return x


def prefix(values: np.ndarray, base: np.uint64) -> np.ndarray:
    """Prefix sums (one longer than values) of values[i] * base**i."""
    out = np.zeros(len(values) + 1, U64)
    np.cumsum(values * powers(base, len(values) + 1)[0][: len(values)], out=out[1:])
    return out


def between(sums: np.ndarray, base: np.uint64, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Polynomials of the values in [start, end), whatever their place."""
    return (sums[end] - sums[start]) * powers(base, len(sums))[1][start]


@dataclass
class Words:
    """Words of some documents: byte ranges, hashes, and each document's first word."""

    data: np.ndarray
    docs: np.ndarray  # byte offsets of documents, one more than documents
    start: np.ndarray
    end: np.ndarray
    first: np.ndarray  # index of each document's first word, one more than documents
    hash: np.ndarray

    @property
    def counts(self) -> np.ndarray:
        return np.diff(self.first)

    def doc(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.first) - 1), self.counts)

    def windows(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        """First words of all windows of n words within one document, and per document the number of windows."""
        counts = np.maximum(self.counts - n + 1, 0)
        ends = np.cumsum(counts)
        at = np.arange(ends[-1] if len(ends) else 0)
        return at + np.repeat(self.first[:-1] - (ends - counts), counts), counts

    def grams(self, n: int, salt: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """First words, hashes and numbers per document of the windows of n words."""
        base = _R if salt else _Q
        at, counts = self.windows(n)
        sums = prefix(self.hash, base)
        return at, mix(between(sums, base, at, at + n)), counts


def column(values: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets of a string or binary column; nulls are empty."""
    if isinstance(values, pa.ChunkedArray):
        values = values.combine_chunks()
    if values.null_count:
        values = values.fill_null("" if pa.types.is_string(values.type) or pa.types.is_large_string(values.type) else b"")
    wide = pa.types.is_large_string(values.type) or pa.types.is_large_binary(values.type)
    _, offsets, data = values.buffers()
    if len(values) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    off = np.frombuffer(offsets, np.int64 if wide else np.int32)[values.offset : values.offset + len(values) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8)[off[0] : off[-1]] if data is not None else np.zeros(0, np.uint8)
    return raw, off - off[0]


def split(data: np.ndarray, docs: np.ndarray, separator: np.ndarray = SPACE, fold: bool = False) -> Words:
    if fold:
        data = FOLD[data]
    sep = separator[data]
    n = len(data)
    before, after = np.ones(n, bool), np.ones(n, bool)
    before[1:], after[:-1] = sep[:-1], sep[1:]
    inner = docs[(docs > 0) & (docs < n)]
    before[inner], after[inner - 1] = True, True
    start, end = np.flatnonzero(~sep & before), np.flatnonzero(~sep & after) + 1
    sums = prefix(BYTES[data], _P)
    return Words(data, docs, start, end, np.searchsorted(start, docs), mix(between(sums, _P, start, end)))


def pieces(values: pa.Array, limit: int = CHUNK) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Row ranges of about limit bytes with their bytes and offsets."""
    data, off = column(values)
    lo, n = 0, len(off) - 1
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(off, off[lo] + limit, "right")) - 1)
        yield lo, hi, data[off[lo] : off[hi]], off[lo : hi + 1] - off[lo]
        lo = hi


def signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)


def lists(values: np.ndarray, counts: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(counts)]).astype(np.int32)), pa.array(values))


def spread(starts: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Concatenation of ranges [starts[i], starts[i] + counts[i])."""
    ends = np.cumsum(counts)
    return np.arange(ends[-1] if len(ends) else 0) + np.repeat(starts - (ends - counts), counts)


def arrays(batch: pa.RecordBatch) -> tuple[np.ndarray, ...]:
    """Columns as arrays; binary values of one length as rows of 64-bit words."""
    return tuple(column(c)[0].reshape(len(c), -1).view(U64) if pa.types.is_binary(c.type) else c.to_numpy(zero_copy_only=False) for c in batch.columns)


def runs(batches: Iterator[pa.RecordBatch], limit: int) -> Iterator[tuple[bool, tuple[np.ndarray, ...]]]:
    """Columns of whole lists (equal first column), some at a time; a list of over limit rows comes in parts, marked True."""
    held: list[tuple[np.ndarray, ...]] = []
    part = False
    joined = lambda parts: tuple(np.concatenate(x) for x in zip(*parts, strict=True))
    for batch in batches:
        if not batch.num_rows:
            continue
        cols = arrays(batch)
        cut = np.searchsorted(cols[0], cols[0][-1])
        if cut or (held and held[0][0][0] != cols[0][-1]):
            yield part, joined([*held, tuple(c[:cut] for c in cols)])
            held, part = [], False
        held.append(tuple(c[cut:] for c in cols))
        if sum(len(x[0]) for x in held) > limit:
            yield True, joined(held)
            held, part = [], True
    if held:
        yield part, joined(held)
