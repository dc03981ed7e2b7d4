"""Operator 8: benchmark decontamination by a BM25 index of the test items and block-max WAND.

The inverted index holds the items (the side that is small by nature; its counted size is checked against
INDEX_BYTES, beyond which items go in several indexes, one pass each). Postings of a term are kept by item and grouped into
blocks of BLOCK items; beside each run of postings in one block stands its largest score, so the index grows with the
postings alone. Items are numbered by threshold, so that a block's least threshold says something of all its items.
Every passage of a document is a query: passages of PASSAGE words that begin every STEP words cover each text to its end,
so every stretch of up to PASSAGE - STEP words lies whole in one (both grow with the longest item).

The threshold of an item is what it scores with itself less its largest term scores, as many of these as shingles may be
missing: a passage that holds OVERLAP of an item's shingles has lost no more words than that, and is never missed. For a
passage, the terms' largest scores are added first; where their sum stays under every threshold it is skipped. Of its terms
in rising order of largest score, those before the pivot, at which the running sum reaches the least threshold, cannot bring
in an item alone, so only blocks of the terms from the pivot on are candidates. A candidate whose block maxima, over all terms
of the passage, stay under the block's least threshold is skipped; only the others' postings are scored. A retrieved
pair is then verified on words: of the item's GRAM-word shingles the whole must be met to OVERLAP, and its question part (the
first two thirds) and answer part (the rest) each to PART_OVERLAP, by shingles anywhere in the document.

Words are lower-cased (A-Z) and cut at white space. Items with a null id or without words are left out; items shorter than
GRAM words are one shingle. Repeated items are found each. Null texts have no passages; null doc_ids are reported as null.
Repeated rows are reported each. An empty table on either side gives no rows. Other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common, textkit as tk

GRAM, OVERLAP, PART_OVERLAP = 5, 0.8, 0.5
PASSAGE, STEP, BLOCK = 128, 64, 16
K1, B = 1.2, 0.75
INDEX_BYTES = 16 << 20
#: Passages are held against the index so many at a time that their table of block bounds has this many cells.
CELLS = 1 << 21
FOUND = "doc_id bigint, item_id bigint, score double, overlap double, question double, answer double"


@dataclass
class Index:
    items: np.ndarray
    terms: np.ndarray  # sorted hashes
    first: np.ndarray  # postings of each term, one more than terms
    item: np.ndarray
    score: np.ndarray
    most: np.ndarray  # largest score of each term
    run_first: np.ndarray  # runs (postings of a term in one block) of each term, one more than terms
    run_key: np.ndarray  # term * blocks + block of each run, ascending
    run_start: np.ndarray  # first posting of each run, one more than runs
    run_max: np.ndarray  # largest score of each run
    threshold: np.ndarray
    least: np.ndarray  # smallest threshold of each block
    grams: np.ndarray  # sorted distinct shingles of all items
    gram_first: np.ndarray  # (item, part) pairs of each shingle
    gram_item: np.ndarray
    gram_part: np.ndarray
    n_grams: np.ndarray  # items x parts
    reach: int


def shingles(w: tk.Words, d: int, n: int) -> np.ndarray:
    a, b = w.first[d], w.first[d + 1]
    if b - a < n:
        sums = tk.prefix(w.hash[a:b], tk._R)
        return tk.mix(tk.between(sums, tk._R, np.array([0]), np.array([b - a])) ^ np.uint64(b - a))
    sums = tk.prefix(w.hash[a:b], tk._Q)
    at = np.arange(b - a - n + 1)
    return tk.mix(tk.between(sums, tk._Q, at, at + n))


def build(ids: list[int], texts: list[str], gram: int = GRAM, overlap: float = OVERLAP) -> Index:
    data, off = tk.column(pa.array(texts, pa.string()))
    w = tk.split(data, off, fold=True)
    keep = np.flatnonzero(w.counts > 0)
    n = len(keep)
    grams = [shingles(w, d, gram) for d in keep]
    distinct = [np.unique(g, return_index=True) for g in grams]
    length = w.counts[keep].astype(float)
    # distinct (term, item) pairs, their frequencies and scores
    flat = np.concatenate([w.hash[w.first[d] : w.first[d + 1]] for d in keep]) if n else np.zeros(0, np.uint64)
    terms, at = np.unique(flat, return_inverse=True)
    code, tf = np.unique(at * max(n, 1) + np.repeat(np.arange(n), w.counts[keep]), return_counts=True)
    term, item = code // max(n, 1), code % max(n, 1)
    df = np.bincount(term, minlength=len(terms))
    idf = np.log1p((n - df + 0.5) / (df + 0.5))
    score = idf[term] * tf * (K1 + 1) / (tf + K1 * (1 - B + B * length[item] / max(length.mean(), 1) if n else 1))
    # what an item keeps at least when as many words go as shingles may
    falling = np.lexsort((-score, item))
    place = np.arange(len(item)) - np.searchsorted(item[falling], item[falling])
    lost = np.array([int((1 - overlap) * len(g) + 1e-9) for g, _ in distinct], np.int64)
    left = np.bincount(item[falling], weights=np.where(place < lost[item[falling]], 0.0, score[falling]), minlength=n) if n else np.zeros(0)
    rank = np.argsort(left, kind="stable")
    number = np.empty(n, np.int64)
    number[rank] = np.arange(n)
    item = number[item]
    order = np.lexsort((item, term))
    term, item, score = term[order], item[order], score[order]
    blocks = -(-n // BLOCK) or 1
    key = term * blocks + item // BLOCK
    run_key, run_start = np.unique(key, return_index=True)
    sizes = np.zeros((n, 2), np.int64)
    who, part = [], []
    for i, d in enumerate(rank):
        own = (distinct[d][1] >= -(-2 * len(grams[d]) // 3)).astype(np.int64)
        who.append(np.full(len(own), i))
        part.append(own)
        sizes[i] = np.bincount(own, minlength=2)
    flat = np.concatenate([distinct[d][0] for d in rank]) if n else np.zeros(0, np.uint64)
    order = np.argsort(flat, kind="stable")
    all_grams, gram_first = np.unique(flat[order], return_index=True)
    empty = np.zeros(0, np.int64)
    return Index(
        items=np.array(ids, np.int64)[keep][rank],
        terms=terms,
        first=np.searchsorted(term, np.arange(len(terms) + 1)),
        item=item,
        score=score,
        most=np.maximum.reduceat(score, np.searchsorted(term, np.arange(len(terms)))) if len(terms) else np.zeros(0),
        run_first=np.searchsorted(run_key, np.arange(len(terms) + 1) * blocks),
        run_key=run_key,
        run_start=np.append(run_start, len(term)),
        run_max=np.maximum.reduceat(score, run_start) if len(run_start) else np.zeros(0),
        threshold=left[rank],
        least=left[rank][::BLOCK],
        grams=all_grams,
        gram_first=np.append(gram_first, len(flat)),
        gram_item=np.concatenate(who)[order] if who else empty,
        gram_part=np.concatenate(part)[order] if part else empty,
        n_grams=sizes,
        reach=int(length.max()) if n else 0,
    )


def lookup(index: Index, passage: np.ndarray, block: np.ndarray, first: np.ndarray, count: np.ndarray, terms: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Runs of the terms of (passage, block) candidates: candidate numbers and run numbers. first and count say where a passage's terms lie."""
    n = count[passage]
    of, t = np.repeat(np.arange(len(passage)), n), terms[tk.spread(first[passage], n)]
    key = t * len(index.least) + block[of]
    at = np.minimum(np.searchsorted(index.run_key, key), len(index.run_key) - 1)
    hit = index.run_key[at] == key
    return of[hit], at[hit]


def retrieve(index: Index, w: tk.Words, passage: int, step: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(document, item, score) of all passages that reach an item's threshold; a pair may come from several."""
    none = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
    if not len(index.terms) or not len(w.hash):
        return none
    at = np.minimum(np.searchsorted(index.terms, w.hash), len(index.terms) - 1)
    hit = index.terms[at] == w.hash
    n = np.maximum(-(-(w.counts - (passage - step)) // step), (w.counts > 0).astype(np.int64))
    begin = np.repeat(w.first[:-1], n) + step * tk.spread(np.zeros_like(n), n)
    doc = np.repeat(np.arange(len(n)), n)
    end = np.minimum(begin + passage, w.first[1:][doc])
    low = index.least[0] - 1e-6
    most = np.concatenate([[0.0], np.cumsum(np.where(hit, index.most[at], 0.0))])
    alive = np.flatnonzero(most[end] - most[begin] >= low)  # repeats only raise the bound
    words, blocks = np.flatnonzero(hit), len(index.least)
    lo, hi = np.searchsorted(words, begin), np.searchsorted(words, end)
    out, per = [], max(1, CELLS // blocks)
    for s in range(0, len(alive), per):
        p = alive[s : s + per]
        own = np.repeat(np.arange(len(p)), hi[p] - lo[p])
        code = np.unique(own * len(index.terms) + at[words[tk.spread(lo[p], hi[p] - lo[p])]])
        own, term = code // len(index.terms), code % len(index.terms)
        rising = np.lexsort((index.most[term], own))
        own, term = own[rising], term[rising]
        first = np.searchsorted(own, np.arange(len(p) + 1))
        sums = np.concatenate([[0.0], np.cumsum(index.most[term])])
        running = sums[1:] - sums[first[own]]
        ahead = running >= low  # the pivot and the terms after it
        count = np.diff(first)
        n_before = np.bincount(own[~ahead], minlength=len(p))
        before = sums[first[:-1] + n_before] - sums[first[:-1]]
        runs = index.run_first[term[ahead] + 1] - index.run_first[term[ahead]]
        run = tk.spread(index.run_first[term[ahead]], runs)
        bound = np.bincount(np.repeat(own[ahead], runs) * blocks + index.run_key[run] % blocks, weights=index.run_max[run], minlength=len(p) * blocks).reshape(len(p), blocks)
        x, b = np.nonzero((bound > 0) & (bound + before[:, None] >= index.least - 1e-6))
        if not len(x):
            continue
        of, run = lookup(index, x, b, first[:-1], n_before, term)
        whole = bound[x, b] + np.bincount(of, weights=index.run_max[run], minlength=len(x))
        live = whole >= index.least[b] - 1e-6
        x, b = x[live], b[live]
        if not len(x):
            continue
        of, run = lookup(index, x, b, first[:-1], count, term)
        size = index.run_start[run + 1] - index.run_start[run]
        post = tk.spread(index.run_start[run], size)
        key, back = np.unique(x[np.repeat(of, size)] * len(index.items) + index.item[post], return_inverse=True)
        total = np.bincount(back, weights=index.score[post])
        item = key % len(index.items)
        ok = total >= index.threshold[item] - 1e-6
        out.append((doc[p[key[ok] // len(index.items)]], item[ok], total[ok]))
    return tuple(np.concatenate(c) for c in zip(*out, strict=True)) if out else none


def pairs(docs: DataFrame, items: DataFrame, gram: int = GRAM, overlap: float = OVERLAP, part_overlap: float = PART_OVERLAP) -> DataFrame:
    """FOUND: every pair of a document (doc_id, text) and a benchmark item (item_id, text) that it holds."""
    spark = docs.sparkSession
    common.ship(spark)
    clean = items.where("item_id is not null and text is not null").select(F.col("item_id").cast("bigint").alias("item_id"), F.col("text").cast("string").alias("text"))
    size = clean.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0)).alias("n")).head().n
    shares = -(-int(size) // INDEX_BYTES) or 1
    rows = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text"))
    out = None
    for k in range(shares):  # one, unless the items outgrow an index
        own = clean.where(F.pmod(F.xxhash64("item_id"), F.lit(shares)) == k).orderBy("item_id", "text").toArrow()
        found = scan(rows, build(own.column(0).to_pylist(), own.column(1).to_pylist(), gram, overlap), gram, overlap, part_overlap)
        out = found if out is None else out.unionByName(found)
    return out


def scan(rows: DataFrame, index: Index, gram: int, overlap: float, part_overlap: float) -> DataFrame:
    sent = rows.sparkSession.sparkContext.broadcast(index)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ix = sent.value
        # items longer than a step are met by passages that hold them whole
        step = max(STEP, ix.reach)
        passage = max(PASSAGE, 2 * step)
        for batch in batches:
            for lo, hi, data, off in tk.pieces(batch.column(1)):
                w = tk.split(data, off, fold=True)
                doc, item, score = retrieve(ix, w, passage, step)
                best: dict[tuple[int, int], float] = {}
                for d, i, s in zip(doc.tolist(), item.tolist(), score.tolist(), strict=True):
                    best[d, i] = max(best.get((d, i), 0.0), s)
                got, held = [], {}
                for (d, i), s in sorted(best.items()):
                    if d not in held:
                        own = shingles(w, d, gram)
                        short = np.concatenate([own, *(tk.mix(tk.between(tk.prefix(w.hash[w.first[d] : w.first[d + 1]], tk._R), tk._R, a := np.arange(max(w.counts[d] - n + 1, 0)), a + n) ^ np.uint64(n)) for n in range(1, gram))]) if (ix.n_grams.sum(1) == 1).any() else own
                        at = np.minimum(np.searchsorted(ix.grams, short), len(ix.grams) - 1)
                        at = np.unique(at[ix.grams[at] == short])
                        post = tk.spread(ix.gram_first[at], ix.gram_first[at + 1] - ix.gram_first[at])
                        met = np.zeros(ix.n_grams.shape, np.int64)
                        np.add.at(met, (ix.gram_item[post], ix.gram_part[post]), 1)
                        held[d] = met
                    met, n = held[d][i], ix.n_grams[i]
                    share = met.sum() / n.sum()
                    parts = [m / k if k else 1.0 for m, k in zip(met, n, strict=True)]
                    if share >= overlap - 1e-12 and min(parts) >= part_overlap - 1e-12:
                        got.append((d, i, s, share, *parts))
                if got:
                    cols = list(zip(*got, strict=True))
                    yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo).take(pa.array(cols[0])), pa.array(ix.items[list(cols[1])]), *(pa.array(c, pa.float64()) for c in cols[2:])], ["doc_id", "item_id", "score", "overlap", "question", "answer"])

    return rows.mapInArrow(run, FOUND)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pairs(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def clean(docs: DataFrame, items: DataFrame) -> DataFrame:
    """docs without those that hold a benchmark item; null ids stay, as no id tells them apart."""
    hit = common.saved(pairs(docs, items).where("doc_id is not null").select("doc_id").distinct(), "leaks")
    return docs.join(common.small(hit, 16), "doc_id", "left_anti").select(*docs.columns)
