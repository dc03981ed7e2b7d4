"""Operator 10: quality by weighted votes of the nearest labelled documents in a latent-semantic space.

A document's terms are its byte trigrams, hashed to ``TERMS`` - 1 places, and in a place of its own "a word that repeats
the word before", which counts as REPEAT trigrams; log-scaled counts a thousand terms, weighted by rarity within the fitted sample, are
projected on the leading singular vectors of that sample and scaled to length one. The sample
of labelled vectors (``SAMPLE`` rows of ``DIMENSIONS`` floats, about a megabyte at most) is broadcast;
every document's cosines with all of them are exact blocked matrix products, and the ``NEIGHBOURS``
closest vote with weight cosine**POWER; among equally close neighbours at the edge any may vote, as the place in the sample decides.

A score depends on its text alone, not on the texts beside it. Null and empty texts, and texts without a term, get the mean
label. Every row is scored, repeated rows and null ids too; a null id is not held out. Rows of one id with different
texts: the first in text order is learned from, so that repeats do not count in the fit. An empty table gives an empty result.
Clashing columns are not read.
"""

from __future__ import annotations

import io
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common, textkit as tk
from .toxicity import remainder

TERMS, DIMENSIONS, SAMPLE = 2048, 48, 3000
REPEAT = 3.0
NEIGHBOURS, POWER, THRESHOLD = 15, 8, 0.5
ROWS = 256


def counts(data: np.ndarray, docs: np.ndarray) -> np.ndarray:
    """Log-scaled term counts, a row a document."""
    n = len(docs) - 1
    out = np.zeros((n, TERMS), np.float32)
    if len(data) > 2:
        code = (data[:-2].astype(np.uint32) * np.uint32(0x9E3779B1)) ^ (data[1:-1].astype(np.uint32) * np.uint32(0x85EBCA6B)) ^ (data[2:].astype(np.uint32) * np.uint32(0xC2B2AE35))
        place = ((code ^ (code >> np.uint32(15))) * np.uint32(0x2C1B3C6D)) % np.uint32(TERMS - 1)
        for d in range(n):  # whole trigrams of each document
            if docs[d + 1] - docs[d] > 2:
                out[d, : TERMS - 1] = np.bincount(place[docs[d] : docs[d + 1] - 2], minlength=TERMS - 1)
    w = tk.split(data, docs)
    same = np.zeros(len(w.hash) + 2, np.int64)  # at i + 1: word i repeats the word before it
    same[2:-1] = w.hash[1:] == w.hash[:-1]
    same[w.first[:-1] + 1] = 0
    sums = np.cumsum(same)
    total = np.maximum(out.sum(1), 1)
    out *= (1000 / total)[:, None]
    out[:, TERMS - 1] = 1000 * REPEAT * (sums[w.first[1:]] - sums[w.first[:-1]]) / np.maximum(w.counts, 1)
    return np.log1p(out)


def unit(x: np.ndarray) -> np.ndarray:
    return x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)


def train(x: np.ndarray, labels: np.ndarray, shares: np.ndarray) -> dict[str, np.ndarray]:
    """Projection, labelled vectors and labels from term counts (documents x TERMS)."""
    seen = (x > 0).sum(0)
    rarity = np.log1p(len(x) / (1.0 + seen)).astype(np.float32)
    centre = unit(x * rarity).mean(0) if len(x) else np.zeros(TERMS, np.float32)
    y = unit(x * rarity) - centre
    # leading right singular vectors through the TERMS x TERMS Gram matrix
    _, vectors = np.linalg.eigh((y.T @ y).astype(np.float64))
    project = vectors[:, ::-1][:, :DIMENSIONS].astype(np.float32)
    return {"rarity": rarity, "centre": centre, "project": project, "vectors": unit(y @ project).astype(np.float32), "labels": labels.astype(np.float32), "shares": shares}


def vote(model: dict[str, np.ndarray], x: np.ndarray) -> np.ndarray:
    prior = float((model["labels"] * model["shares"]).sum() / model["shares"].sum()) if len(model["labels"]) else 0.5
    empty = ~(x > 0).any(1)
    if not len(model["labels"]):
        return np.full(len(x), prior)
    v = unit((unit(x * model["rarity"]) - model["centre"]) @ model["project"])
    cos = v @ model["vectors"].T
    k = min(NEIGHBOURS, cos.shape[1])
    near = np.argpartition(-cos, k - 1, axis=1)[:, :k]
    weight = np.maximum(np.take_along_axis(cos, near, 1), 0).astype(np.float64) ** POWER + 1e-12
    weight *= model["shares"][near]
    out = (weight * model["labels"][near]).sum(1) / weight.sum(1)
    return np.where(empty, prior, np.clip(out, 0, 1))


def fit(docs: DataFrame, labelled: DataFrame, sample: int = SAMPLE) -> dict[str, np.ndarray]:
    """A model from documents (doc_id, text) and labelled (doc_id, label in 0/1): ``sample`` rows of smallest xxhash64, half of each label where there are as many.

    Rows with a null id or label are left out; without any the score is 0.5 everywhere.
    """
    spark = docs.sparkSession
    common.ship(spark)
    known = labelled.where("doc_id is not null and label is not null").groupBy("doc_id").agg(F.max("label").alias("label")).withColumn("turn", F.xxhash64("doc_id", F.lit(10)))
    number = {r.label: r.n for r in known.groupBy("label").agg(F.count("*").alias("n")).collect()}  # two rows
    # the sample is even; a vote counts for all the labelled rows that it stands for
    share = {k: max(n / (sample // 2), 1.0) for k, n in number.items()}
    chosen = known.where("label = 0").orderBy("turn", "doc_id").limit(sample // 2).unionByName(known.where("label = 1").orderBy("turn", "doc_id").limit(sample // 2))
    # a text an id, so the fit sees `sample` rows at most
    texts = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").groupBy("turn", "label").agg(F.min(F.col("text").cast("string")).alias("text")).select("turn", F.col("label").cast("int").alias("label"), "text")

    def hashed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo, hi, data, off in tk.pieces(batch.column(2)):
                rows = counts(data, off)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo), batch.column(1).slice(lo, hi - lo), pa.array([r.tobytes() for r in rows], pa.binary())], ["turn", "label", "counts"])

    def learn(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        x, labels = [], []
        for b in batches:
            x += [np.frombuffer(r, np.float32) for r in b.column(2).to_pylist()]
            labels += b.column(1).to_pylist()
        out = io.BytesIO()
        np.savez(out, **train(np.array(x, np.float32).reshape(-1, TERMS), np.array(labels, np.float32), np.array([share[k] for k in labels], np.float64)))
        yield pa.RecordBatch.from_arrays([pa.array([out.getvalue()], pa.binary())], ["model"])

    rows = texts.mapInArrow(hashed, "turn bigint, label int, counts binary").repartition(1).sortWithinPartitions("turn")
    row = rows.mapInArrow(learn, "model binary").head()
    if row is None:  # no labelled row has a text
        return train(np.zeros((0, TERMS), np.float32), np.zeros(0, np.float32), np.zeros(0))
    with np.load(io.BytesIO(bytes(row.model))) as got:
        return {k: got[k] for k in got.files}


def score(docs: DataFrame, model: dict[str, np.ndarray]) -> DataFrame:
    """(doc_id, score) of documents (doc_id, text). Null and empty texts get the mean label of the sample."""
    spark = docs.sparkSession
    common.ship(spark)
    sent = spark.sparkContext.broadcast(model)

    def rate(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for lo, hi, data, off in tk.pieces(batch.column(1)):
                for a in range(0, hi - lo, ROWS):
                    b = min(a + ROWS, hi - lo)
                    out.append(vote(sent.value, counts(data[off[a] : off[b]], off[a : b + 1] - off[a])))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.concatenate(out) if out else np.zeros(0), pa.float64())], ["doc_id", "score"])

    return docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(rate, "doc_id bigint, score double")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", F.col("quality").alias("label")).where(remainder(3) != 1)
    return score(docs, fit(docs, labels)).select("doc_id", F.coalesce(remainder(3) == 1, F.lit(False)).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
