"""Operator 5: best-fit-decreasing packing of token sequences.

Documents longer than a sequence are cut into full pieces, the first piece taking the
remainder. Which bin an item joins depends on lengths alone, so best fit decreasing runs
on the histogram of piece lengths (at most ``capacity`` rows, whatever the corpus) with bins
of equal remaining capacity handled together: a segment tree over remaining capacities
finds the tightest class of open bins that still takes an item in logarithmic time.
The plan lists runs "items rank..rank+n of this length go to bins b..b+n at this offset";
pieces get their rank within their length from counts per (bucket, length), and a
join with the plan places them. A full piece is a sequence by itself and needs neither rank nor shuffle; its
sequence_id is negative.
"""

from __future__ import annotations

import zlib
from collections import defaultdict, deque
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common, textkit, tokens

CAPACITY = 1024
PIECES = "doc_id bigint, piece int, start bigint, length bigint, ids_crc32 bigint"
#: Buckets within which pieces of one length are ranked, and pieces in a bucket from which on there are more of them; copies of one document spread over them.
BUCKETS, BUCKET_ROWS = 1024, 100_000


class Remaining:
    """Segment tree over remaining capacities 0..size: how many classes are open below each node."""

    def __init__(self, size: int):
        self.base = 1 << size.bit_length()
        self.open = [0] * (2 * self.base)

    def set(self, value: int, is_open: bool) -> None:
        i = value + self.base
        change = int(is_open) - self.open[i]
        while change and i:
            self.open[i] += change
            i >>= 1

    def tightest(self, least: int) -> int | None:
        """The smallest open value that is least or more."""
        i = least + self.base
        if self.open[i]:
            return least
        while i > 1:
            if not i & 1 and self.open[i + 1]:
                i += 1
                while i < self.base:
                    i = 2 * i if self.open[2 * i] else 2 * i + 1
                return i - self.base
            i >>= 1
        return None


def plan(histogram: dict[int, int], capacity: int = CAPACITY) -> tuple[list[tuple[int, int, int, int, int]], int]:
    """Runs (length, first rank, number, first bin, offset) of best fit decreasing, and the number of bins.

    Lengths must lie in 1..capacity. Among bins of equal remaining capacity the one that
    came to it first takes the next item.
    """
    runs, bins = [], 0
    tree, open_bins = Remaining(capacity), defaultdict(deque)
    for length in sorted(histogram, reverse=True):
        if not 1 <= length <= capacity:
            raise ValueError(f"length {length} is outside 1..{capacity}")
        rank, left = 0, histogram[length]
        while left:
            room = tree.tightest(length)
            if room is None:
                room, first, have = capacity, bins, left
            else:
                first, have = open_bins[room].popleft()
            # the bin just used stays the tightest while it takes another item of this length
            per = room // length
            n = min(have, left // per)
            if not n:
                n, per = 1, left
            if first == bins:
                bins += n
            else:
                if have > n:
                    open_bins[room].appendleft((first + n, have - n))
                if not open_bins[room]:
                    tree.set(room, False)
            for k in range(per):
                runs.append((length, rank, n, first, capacity - room + k * length))
                rank, left = rank + n, left - n
            rest = room - per * length
            if rest:
                open_bins[rest].append((first, n))
                tree.set(rest, True)
    return runs, bins


def cut(docs: DataFrame, vocabulary: str, with_space: bool = True, end_id: int = 2, capacity: int = CAPACITY) -> DataFrame:
    """PIECES of documents (doc_id, text): null texts are empty and give one piece, the end id."""
    common.ship(docs.sparkSession)

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        code = tokens.encoder(vocabulary, with_space)
        for batch in batches:
            for lo, hi, data, off in textkit.pieces(batch.column(1)):
                flat, counts = code.ended(data, off, end_id)
                flat = flat.astype("<u4")
                base = np.cumsum(counts) - counts
                n = -(-counts // capacity)
                doc = np.repeat(np.arange(hi - lo), n)
                piece = textkit.spread(np.zeros_like(n), n)
                first = counts - (n - 1) * capacity
                start = np.where(piece == 0, 0, first[doc] + (piece - 1) * capacity)
                length = np.where(piece == 0, first[doc], capacity)
                at = base[doc] + start
                crc = [zlib.crc32(flat[a:b]) for a, b in zip(at, at + length, strict=True)]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo).take(pa.array(doc)), pa.array(piece.astype(np.int32)), pa.array(start), pa.array(length), pa.array(crc, pa.int64())], ["doc_id", "piece", "start", "length", "ids_crc32"])

    return docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(encode, PIECES)


def pack(pieces: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """pieces with sequence_id and offset. Give a saved frame: it is read several times.

    Ties in length go by bucket, doc_id (nulls first), piece, start and checksum; rows that
    agree in all of these are interchangeable. An empty frame gives an empty result.
    """
    spark = pieces.sparkSession
    histogram = {r.length: r.n for r in pieces.groupBy("length").count().withColumnRenamed("count", "n").collect()}  # at most capacity rows
    histogram.pop(capacity, None)
    runs, _ = plan(histogram, capacity)
    buckets = max(BUCKETS, sum(histogram.values()) // BUCKET_ROWS)
    rows = pieces.where(F.col("length") < capacity).withColumn("bucket", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(buckets)))
    counts = rows.groupBy("length", "bucket").agg(F.count("*").alias("n"))
    full = pieces.where(F.col("length") == capacity).select("doc_id", "piece", "start", "length", "ids_crc32", (-1 - F.monotonically_increasing_id()).alias("sequence_id"), F.lit(0).cast("bigint").alias("offset"))
    before = counts.withColumn("before", F.sum("n").over(Window.partitionBy("length").orderBy("bucket")) - F.col("n")).drop("n")
    within = F.row_number().over(Window.partitionBy("bucket", "length").orderBy("doc_id", "piece", "start", "ids_crc32")) - 1
    ranked = rows.withColumn("within", within).join(before, ["length", "bucket"]).withColumn("rank", F.col("before") + F.col("within"))
    table = spark.createDataFrame([(int(a), int(b), int(b + n), int(c - b), int(d)) for a, b, n, c, d in runs], "length bigint, lo bigint, hi bigint, shift bigint, offset bigint")
    # as many rows as the plan has runs: a few for each length
    found = ranked.join(F.broadcast(table), (ranked.length == table.length) & (F.col("rank") >= F.col("lo")) & (F.col("rank") < F.col("hi"))).drop(table.length)
    return found.select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("rank") + F.col("shift")).alias("sequence_id"), "offset").unionAll(full)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return pack(common.saved(cut(docs, tokens.exists(tokens.vocabulary("byte_bpe_50k.json"))), "pieces"))
