"""Operator 1: token ids in patched frame-of-reference blocks.

File format, version 1 (all numbers little-endian): a shard holds whole documents in
ascending doc_id order (nulls first, equal ids by text). Its payload is

    "PFB1" | ids u64 | blocks u32 | block starts u64 x (blocks + 1) | blocks

A block holds BLOCK ids (the last one is filled up with its last id):

    minimum u32 | width u8 | exceptions u8 | packed low bits (BLOCK * width / 8 bytes)
    | exception places u8 x n | exception high parts u32 x n

The width is that of the PERCENTILE-th widest id minus minimum; ids that need more
bits keep their low bits in place and the rest in the exception list. Shards are rows of a
Parquet table (doc_ids, lengths, payload), so that any store Spark reaches can hold them.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common, textkit, tokens

BLOCK, PERCENTILE, MAGIC = 128, 90, b"PFB1"
SHARD_IDS = 1 << 20
SHARDS = "part bigint, shard bigint, n_ids bigint, doc_ids array<bigint>, lengths array<bigint>, payload binary"


def _pack(values: np.ndarray, width: int) -> np.ndarray:
    """Columns of BLOCK values below 2**width as little-endian 64-bit words, one row a block."""
    words = np.zeros((BLOCK * width // 64, values.shape[1]), np.uint64)
    for i in range(BLOCK):
        word, shift = divmod(i * width, 64)
        words[word] |= values[i] << np.uint64(shift)
        if shift + width > 64:
            words[word + 1] |= values[i] >> np.uint64(64 - shift)
    return np.ascontiguousarray(words.T)


def _unpack(words: np.ndarray, width: int) -> np.ndarray:
    words = np.ascontiguousarray(words.T)
    out = np.empty((BLOCK, words.shape[1]), np.uint64)
    keep = np.uint64((1 << width) - 1)
    for i in range(BLOCK):
        word, shift = divmod(i * width, 64)
        x = words[word] >> np.uint64(shift)
        if shift + width > 64:
            x = x | (words[word + 1] << np.uint64(64 - shift))
        out[i] = x & keep
    return out


def pack(ids: np.ndarray) -> bytes:
    """The payload of some ids."""
    n = len(ids)
    blocks = -(-n // BLOCK)
    if not n:
        return MAGIC + struct.pack("<QIQ", 0, 0, 24)
    grid = np.full(blocks * BLOCK, ids[-1], np.uint64)
    grid[:n] = ids
    grid = np.ascontiguousarray(grid.reshape(blocks, BLOCK).T)
    low = grid.min(0)
    grid -= low
    bits = np.frexp(grid.astype(np.float64))[1].astype(np.uint8)
    rank = BLOCK * PERCENTILE // 100 - 1
    width = np.partition(bits, rank, axis=0)[rank]
    high = grid >> width.astype(np.uint64)
    place, block = np.nonzero(high)
    order = np.lexsort((place, block))
    place, block = place[order], block[order]
    over = np.bincount(block, minlength=blocks)
    size = 6 + BLOCK // 8 * width.astype(np.int64) + 5 * over
    base = 4 + 12 + 8 * (blocks + 1)
    starts = base + np.concatenate([[0], np.cumsum(size)])
    out = np.zeros(starts[-1], np.uint8)
    out[:base] = np.frombuffer(MAGIC + struct.pack("<QI", n, blocks) + starts.astype("<u8").tobytes(), np.uint8)
    at = starts[:-1]
    out[at[:, None] + np.arange(4)] = low.astype("<u4").view(np.uint8).reshape(-1, 4)
    out[at + 4], out[at + 5] = width, over
    for w in np.unique(width):
        if w:
            which = np.flatnonzero(width == w)
            raw = _pack(grid[:, which] & np.uint64((1 << int(w)) - 1), int(w)).view(np.uint8)
            out[at[which][:, None] + 6 + np.arange(raw.shape[1])] = raw
    if len(block):
        nth = np.arange(len(block)) - (np.cumsum(over) - over)[block]
        after = at[block] + 6 + BLOCK // 8 * width[block].astype(np.int64)
        out[after + nth] = place
        out[(after + over[block] + 4 * nth)[:, None] + np.arange(4)] = high[place, block].astype("<u4").view(np.uint8).reshape(-1, 4)
    return out.tobytes()


def unpack(payload: bytes, first: int = 0, count: int | None = None) -> np.ndarray:
    """Ids [first, first + count) of a payload; only their blocks are decoded."""
    if payload[:4] != MAGIC:
        raise ValueError("not a block payload of this version")
    n, blocks = struct.unpack_from("<QI", payload, 4)
    count = n - first if count is None else min(count, n - first)
    if count <= 0:
        return np.zeros(0, np.uint32)
    b0, b1 = first // BLOCK, -(-(first + count) // BLOCK)
    raw = np.frombuffer(payload, np.uint8)
    at = np.frombuffer(payload, "<u8", b1 - b0, 16 + 8 * b0).astype(np.int64)
    low = np.ascontiguousarray(raw[at[:, None] + np.arange(4)]).view("<u4")[:, 0].astype(np.uint64)
    width, over = raw[at + 4], raw[at + 5].astype(np.int64)
    grid = np.zeros((BLOCK, b1 - b0), np.uint64)
    for w in np.unique(width):
        if w:
            which = np.flatnonzero(width == w)
            grid[:, which] = _unpack(np.ascontiguousarray(raw[at[which][:, None] + 6 + np.arange(BLOCK // 8 * int(w))]).view("<u8"), int(w))
    block = np.repeat(np.arange(b1 - b0), over)
    if len(block):
        nth = np.arange(len(block)) - (np.cumsum(over) - over)[block]
        after = at[block] + 6 + BLOCK // 8 * width[block].astype(np.int64)
        high = np.ascontiguousarray(raw[(after + over[block] + 4 * nth)[:, None] + np.arange(4)]).view("<u4")[:, 0].astype(np.uint64)
        grid[raw[after + nth], block] |= high << width[block].astype(np.uint64)
    grid += low
    return np.ascontiguousarray(grid.T).reshape(-1)[first - b0 * BLOCK :][:count].astype(np.uint32)


def write(docs: DataFrame, path: str, vocabulary: str, with_space: bool = False, end_id: int = 2) -> None:
    """Encode documents (doc_id, text) and write their shards to path.

    A null text is empty and gives the end id alone; null ids come first; repeated rows are kept,
    each on its own; other columns are not read. An empty table gives a table without shards.
    """
    spark = docs.sparkSession
    common.ship(spark)

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        code, part, shard = tokens.encoder(vocabulary, with_space), TaskContext.get().partitionId(), 0
        ids, names, sizes, held = [], [], [], 0

        def flush() -> pa.RecordBatch:
            flat = np.concatenate(ids)
            lengths = np.concatenate(sizes)
            row = [pa.array([part], pa.int64()), pa.array([shard], pa.int64()), pa.array([len(flat)], pa.int64()), pa.array([[x for a in names for x in a.to_pylist()]], pa.list_(pa.int64())), pa.array([lengths], pa.list_(pa.int64())), pa.array([pack(flat)], pa.binary())]
            return pa.RecordBatch.from_arrays(row, ["part", "shard", "n_ids", "doc_ids", "lengths", "payload"])

        for batch in batches:
            for lo, hi, data, off in textkit.pieces(batch.column(1)):
                flat, counts = code.ended(data, off, end_id)
                ids.append(flat)
                sizes.append(counts)
                names.append(batch.column(0).slice(lo, hi - lo))
                held += len(flat)
                if held >= SHARD_IDS:
                    yield flush()
                    ids, names, sizes, held, shard = [], [], [], 0, shard + 1
        if names:
            yield flush()

    rows = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text"))
    dealt = rows.repartitionByRange(common.partitions(spark), "doc_id").sortWithinPartitions("doc_id", "text")
    dealt.mapInArrow(encode, SHARDS).write.option("compression", "uncompressed").parquet(path)


def read(spark: SparkSession, path: str) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) of every document in the shards at path, decoded from them."""
    common.ship(spark)
    shards = spark.read.schema(SHARDS).parquet(path)
    # one row a part, at most as many as shuffle partitions
    sizes = {r.part: r.n for r in shards.groupBy("part").agg(F.sum("n_ids").alias("n")).collect()}
    before, total = {}, 0
    for part in sorted(sizes):
        before[part] = total
        total += sizes[part]

    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in range(batch.num_rows):
                part, shard, names, sizes, payload = (batch.column(i)[row] for i in range(5))
                counts = sizes.values.to_numpy(zero_copy_only=False) if sizes.values is not None else np.zeros(0, np.int64)
                ends = np.cumsum(counts)
                flat = unpack(payload.as_py()).astype("<u4")
                crc = [zlib.crc32(flat[a:b]) for a, b in zip(ends - counts, ends, strict=True)]
                n = len(counts)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(n, part.as_py())), pa.array(np.full(n, shard.as_py())), names.values, pa.array(ends - counts), pa.array(counts), pa.array(crc, pa.int64())], ["part", "shard", "doc_id", "local", "n_tokens", "ids_crc32"])

    docs = shards.select("part", "shard", "doc_ids", "lengths", "payload").mapInArrow(decode, "part bigint, shard bigint, doc_id bigint, local bigint, n_tokens bigint, ids_crc32 bigint")
    order = shards.select("part", "shard", "n_ids")
    from pyspark.sql import Window

    place = order.withColumn("skip", F.sum("n_ids").over(Window.partitionBy("part").orderBy("shard")) - F.col("n_ids")).drop("n_ids")
    base = spark.createDataFrame(sorted(before.items()), "part bigint, base bigint")
    place = place.join(F.broadcast(base), "part").withColumn("skip", F.col("skip") + F.col("base")).drop("base")
    return docs.join(place, ["part", "shard"]).select("doc_id", (F.col("skip") + F.col("local")).alias("start"), "n_tokens", "ids_crc32")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = common.new_path(spark, "token-blocks")
    write(spark.read.parquet(f"{sf_dir}/documents.parquet"), path, tokens.exists(tokens.vocabulary("word_bpe_49k.json")))
    return read(spark, path)
