"""Which subgraphs of a bin a vertex belongs to: three bitmap classes and the column form."""

from __future__ import annotations

import sys
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Slots per BIGINT in column form: 32 keeps away from the sign bit.
WORD = 32


class WordBitmap:
    """One row of 64-bit words a vertex, all of the same width; the default."""

    def __init__(self, n: int, bits: int):
        self.words = np.zeros((n, max(1, -(-bits // 64))), np.uint64)

    def set(self, v: int, bit: int) -> None:
        self.words[v, bit >> 6] |= np.uint64(1) << np.uint64(bit & 63)

    def get(self, v: int, bit: int) -> bool:
        return bool(self.words[v, bit >> 6] >> np.uint64(bit & 63) & np.uint64(1))

    def nbytes(self) -> int:
        return self.words.nbytes


class GrowableBitmap:
    """One growing integer a vertex, as long as its highest set bit."""

    def __init__(self, n: int, bits: int = 0):
        self.rows = [0] * n

    def set(self, v: int, bit: int) -> None:
        self.rows[v] |= 1 << bit

    def get(self, v: int, bit: int) -> bool:
        return bool(self.rows[v] >> bit & 1)

    def nbytes(self) -> int:
        return sum(map(sys.getsizeof, self.rows))


class SparseBitmap:
    """A hash set of set bits a vertex; its model is 134 + 4 n bytes."""

    def __init__(self, n: int, bits: int = 0):
        self.rows: list[set[int]] = [set() for _ in range(n)]

    def set(self, v: int, bit: int) -> None:
        self.rows[v].add(bit)

    def get(self, v: int, bit: int) -> bool:
        return bit in self.rows[v]

    def nbytes(self) -> int:
        return sum(map(sys.getsizeof, self.rows))

    @staticmethod
    def model_bytes(set_bits: int) -> int:
        return 134 + 4 * set_bits


CLASSES = {"words": WordBitmap, "growable": GrowableBitmap, "sparse": SparseBitmap}


def choose_bitmap(mean_set: float, width: int) -> str:
    """The hash form where its model is smaller than dense words."""
    return "sparse" if 134 + 4 * mean_set < width / 8 else "words"


def bitmap_bytes(width: int, set_bits: int) -> dict[str, int]:
    """Measured bytes of one vertex in each class."""
    out = {}
    for name, cls in CLASSES.items():
        b = cls(1, width)
        for k in range(set_bits):
            b.set(0, k * width // max(1, set_bits))
        out[name] = b.nbytes()
    return out


def measured_bytes(members: DataFrame, assignment: DataFrame) -> DataFrame:
    """(width, set_bits, n_vertices, words, growable, sparse, sparse_model): bitmap_bytes of every width and number of set bits, and how many vertices of bins have it."""
    width = assignment.groupBy("bin_id").agg(F.count("*").alias("width"))
    per = members.select("sg_id", "v").join(assignment.select("sg_id", "bin_id"), "sg_id").groupBy("bin_id", "v").agg(F.count("*").alias("set_bits"))
    kinds = per.join(width, "bin_id").groupBy("width", "set_bits").agg(F.count("*").alias("n_vertices"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [r | bitmap_bytes(r["width"], r["set_bits"]) | {"sparse_model": SparseBitmap.model_bytes(r["set_bits"])} for r in batch.to_pylist()]
            if rows:
                yield pa.RecordBatch.from_pylist(rows)

    return kinds.mapInArrow(run, "width bigint, set_bits bigint, n_vertices bigint, words bigint, growable bigint, sparse bigint, sparse_model bigint")


def slot_bitmap(members: DataFrame, assignment: DataFrame) -> DataFrame:
    """(bin_id, v, word, bits): words of WORD slots each."""
    rows = members.select("sg_id", "v").join(assignment.select("sg_id", "bin_id", "slot"), "sg_id")
    bit = F.expr(f"shiftleft(1L, slot % {WORD})")
    return rows.groupBy("bin_id", "v", F.floor(F.col("slot") / WORD).cast("bigint").alias("word")).agg(F.bit_or(bit).alias("bits"))
