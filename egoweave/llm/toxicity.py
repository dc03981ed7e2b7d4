"""Operator 4: toxicity by FTRL-proximal logistic regression over hashed words and skip-grams.

Features are the distinct words, adjacent word pairs and pairs one word apart of a text,
lower-cased (A-Z) and cut at ASCII characters that are neither letters nor digits, each hashed to one
of 2**BITS weights. FTRL-proximal gives each weight its own learning rate and, by its L1
term, leaves most at zero: what scores the corpus is a short list of (place, weight), at most
2**BITS entries, which is broadcast.

The fit uses a bounded sample of labelled rows: the ``SAMPLE`` rows of smallest
xxhash64(doc_id, seed) among those allowed for learning (ties by doc_id), of which those are learned from whose distinct
places together stay within ``SAMPLE_PLACES``, so one task holds 4 bytes for each. Of the labels of one id the largest counts, of
its texts the first in text order, so repeated rows do not count twice. Scoring covers every row, repeated rows and null ids
too; a null id is not held out. Null, empty and wordless texts get the bias alone. An empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common, textkit as tk

BITS = 20
SAMPLE, SAMPLE_PLACES, EPOCHS = 10_000, 50_000_000, 3
#: The L1 term is per learning row, and rows labelled 1 count UPWEIGHT times, as they are few.
ALPHA, BETA, L1_PER_ROW, L2, UPWEIGHT = 0.3, 1.0, 0.0025, 1.0, 3.0
THRESHOLD = 0.3
BIAS = 0


def features(words: tk.Words) -> tuple[np.ndarray, np.ndarray]:
    """Distinct places per document (flat, document by document) and their numbers."""
    h = words.hash
    pair, n2 = words.windows(2)
    skip, n3 = words.windows(3)
    two = tk.mix(h[pair] * np.uint64(3) + h[pair + 1])
    gap = tk.mix(h[skip] * np.uint64(5) + h[skip + 2])
    docs = np.arange(len(words.first) - 1)
    place = np.concatenate([h, two, gap]) >> np.uint64(64 - BITS)
    doc = np.concatenate([words.doc(), np.repeat(docs, n2), np.repeat(docs, n3)])
    both = np.unique((doc.astype(np.uint64) << np.uint64(BITS)) | place)
    doc = (both >> np.uint64(BITS)).astype(np.int64)
    return (both & np.uint64((1 << BITS) - 1)).astype(np.int64), np.bincount(doc, minlength=len(docs))


class Ftrl:
    """Per-coordinate online logistic regression with L1 and L2 terms; coordinate -1 is a bias without L1."""

    def __init__(self, rows: int):
        self.z, self.n = np.zeros((1 << BITS) + 1), np.zeros((1 << BITS) + 1)
        self.l1 = np.full((1 << BITS) + 1, L1_PER_ROW * rows)
        self.l1[-1] = 0

    def weights(self, at: np.ndarray | slice) -> np.ndarray:
        z, l1 = self.z[at], self.l1[at]
        return np.where(np.abs(z) <= l1, 0.0, -(z - np.sign(z) * l1) / ((BETA + np.sqrt(self.n[at])) / ALPHA + L2))

    def learn(self, places: np.ndarray, label: int) -> None:
        at = np.append(places, 1 << BITS)
        w = self.weights(at)
        g = (1 / (1 + np.exp(-np.clip(w.sum(), -35, 35))) - label) * (UPWEIGHT if label else 1.0)
        old = self.n[at]
        self.n[at] = old + g * g
        self.z[at] += g - (np.sqrt(self.n[at]) - np.sqrt(old)) / ALPHA * w


def fit(docs: DataFrame, labelled: DataFrame, sample: int = SAMPLE) -> tuple[np.ndarray, np.ndarray, float]:
    """Places, weights and bias from documents (doc_id, text) and labelled (doc_id, label in 0/1).

    Rows with a null id or label are left out. Without any labelled row the model is the
    prior 0.5. The sample is taken from the ids, and only its texts move, to one task that learns from them in
    an order fixed by the same hash.
    """
    spark = docs.sparkSession
    common.ship(spark)
    order = F.xxhash64("doc_id", F.lit(4))
    chosen = labelled.where("doc_id is not null and label is not null").groupBy("doc_id").agg(F.max("label").alias("label")).withColumn("turn", order).orderBy("turn", "doc_id").limit(sample)
    # at most `sample` rows of 20 bytes
    texts = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").groupBy("turn", "label").agg(F.min(F.col("text").cast("string")).alias("text"))

    def hashed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo, hi, data, off in tk.pieces(batch.column(2), tk.STEP):
                places, counts = features(tk.split(data, off, tk.NOT_ALNUM, True))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo), batch.column(1).slice(lo, hi - lo), tk.lists(places.astype(np.int32), counts)], ["turn", "label", "places"])

    def learn(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows, held = [], 0
        for b in batches:
            for label, places in zip(b.column(1).to_pylist(), b.column(2), strict=True):
                if held + len(places) <= SAMPLE_PLACES:
                    held += len(places)
                    rows.append((label, places.values.to_numpy(zero_copy_only=False).copy()))
        model = Ftrl(len(rows))
        for _ in range(EPOCHS if rows else 0):
            for label, places in rows:
                model.learn(places, label)
        w = model.weights(slice(None))
        at = np.flatnonzero(w)
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(w[at])], ["place", "weight"])

    rows = texts.select("turn", F.col("label").cast("int").alias("label"), "text").mapInArrow(hashed, "turn bigint, label int, places array<int>")
    model = rows.repartition(1).sortWithinPartitions("turn").mapInArrow(learn, "place int, weight double")
    got = model.toArrow().to_pydict()  # at most 2**BITS + 1 rows; L1 leaves a few hundred
    place, weight = np.array(got["place"], np.int64), np.array(got["weight"])
    bias = float(weight[place == 1 << BITS].sum())
    keep = place < 1 << BITS
    return place[keep], weight[keep], bias


def score(docs: DataFrame, model: tuple[np.ndarray, np.ndarray, float], name: str = "score") -> DataFrame:
    """docs with a column (name) in 0..1; a null or empty text gets the bias alone. Other columns keep their values; one of that name is replaced."""
    spark = docs.sparkSession
    common.ship(spark)
    sent = spark.sparkContext.broadcast((model[0].astype(np.int32), model[1].astype(np.float64)))
    bias = model[2]

    def rate(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        dense = np.zeros(1 << BITS)
        dense[sent.value[0]] = sent.value[1]
        for batch in batches:
            text = batch.column(batch.schema.get_field_index("text"))
            out = []
            for _, _, data, off in tk.pieces(text, tk.STEP):
                places, counts = features(tk.split(data, off, tk.NOT_ALNUM, True))
                ends = np.concatenate([[0], np.cumsum(counts)])
                sums = np.concatenate([[0.0], np.cumsum(dense[places])])
                out.append(1 / (1 + np.exp(-np.clip(sums[ends[1:]] - sums[ends[:-1]] + bias, -35, 35))))
            keep = [i for i, n in enumerate(batch.schema.names) if n != name]
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in keep), pa.array(np.concatenate(out) if out else np.zeros(0))], [*(batch.schema.names[i] for i in keep), name])

    base = docs.drop(name).withColumn("text", F.col("text").cast("string"))
    from pyspark.sql.types import DoubleType, StructType

    return base.mapInArrow(rate, StructType(list(base.schema.fields)).add(name, DoubleType()))


def remainder(n: int) -> Column:
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % n


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", F.col("toxic").alias("label")).where(remainder(4) != 2)
    rated = score(docs, fit(docs, labels))
    return rated.select("doc_id", F.coalesce(remainder(4) == 2, F.lit(False)).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))


def clean(docs: DataFrame, labelled: DataFrame) -> DataFrame:
    """Documents that score below the threshold, with their own columns."""
    name = common.free(docs.columns, "score")[0]
    return score(docs, fit(docs, labelled), name).where(F.col(name) < THRESHOLD).drop(name)
