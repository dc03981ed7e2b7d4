"""Operator 9: duplicate passages by relative Lempel-Ziv factors.

The reference of a document is every document with a smaller doc_id. It is indexed in blocks by anchors: the anchor of a
window of WINDOW words is the smallest hash of its GRAM-word grams, so equal windows have equal anchors in equal places. Only
anchors that occur in two different texts make a block. A block holds each place of its anchor with the words on both
sides that a window around it can reach.

A document is parsed against every block that one of its windows points to. Around the anchor the longest stretch that it
has in common with each earlier text of the block is found word by word; of these factors the parse keeps, from left to
right, each that reaches farther than those that begin before it. Factors of WINDOW words or more are duplicate spans, and
a window that crosses the end of one is settled by the next factor, so boundaries are exact to the word. Words are compared by
64-bit hashes.

A block of more than BLOCK places would be one task's work, and in a window that holds its anchor twice the place is not
unique. Windows of either kind, which equal windows share, are looked up as wholes instead: the smallest doc_id of each
window, by hashes of 64 and 32 bits of all its words, is a partial aggregate that splits a common window over all tasks.
Within a piece of input, what a smaller doc_id also has is known before anything moves. Copies of a whole word sequence are
found first, by two 64-bit hashes and the length, and one of them stands for all.

Rows with a null doc_id are never sources and lose nothing; a null text has no words; rows that share
a doc_id are one document id, and never sources of each other; xxhash64 of the text tells them apart. An empty table gives an
empty result. Other columns are not
read. The texts cross the network once, to meet the anchors that they share; those that share some are written to the
shared folder, and what follows reads only these. A text that shares nothing is settled by the first pass.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common, textkit as tk

WINDOW, GRAM = 50, 8
#: A reference block has so many places at most; PAIRS of them are compared at a time.
BLOCK, PAIRS = 32, 4096
PROFILE = "doc_id bigint, tag bigint, n_words bigint, fp bigint, fp2 bigint, sha string, anchors array<bigint>"
FOUND = "doc_id bigint, tag bigint, kind int, pos int, run int, key bigint, key2 int, before int, after int, words binary"
#: Kinds of FOUND: a span of windows that is settled, a window to look up as a whole, a place of an anchor (key) with its words.
SETTLED, WHOLE, PLACE = range(3)


def whole(w: tk.Words) -> tuple[np.ndarray, np.ndarray]:
    """Two hashes of each document's word sequence."""
    a, b = tk.prefix(w.hash, tk._Q), tk.prefix(w.hash, tk._R)
    n = w.counts.astype(np.uint64)
    return tuple(tk.signed(tk.mix(tk.between(x, base, w.first[:-1], w.first[1:]) + n)) for x, base in ((a, tk._Q), (b, tk._R)))


def anchors(w: tk.Words, at: np.ndarray, window: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For windows that begin at the words in at, the smallest hash of their grams, and its first and last place."""
    if not len(at):
        return np.zeros(0, np.uint64), at, at
    sums = tk.prefix(w.hash, tk._Q)
    first = np.arange(len(w.hash) - gram + 1)
    last = first
    low = tk.mix(tk.between(sums, tk._Q, first, first + gram) ^ np.uint64(0x5851F42D4C957F2D))

    def join(i: np.ndarray | slice, j: np.ndarray | slice) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        left, right = low[i], low[j]
        return np.minimum(left, right), np.where(left <= right, first[i], first[j]), np.where(right <= left, last[j], last[i])

    width, need = 1, window - gram + 1
    while 2 * width <= need:
        low, first, last = join(slice(None, -width), slice(width, None))
        width *= 2
    return join(at, at + need - width)


def profile(docs: DataFrame, window: int, gram: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo, hi, data, off in tk.pieces(batch.column(1), tk.STEP):
                w = tk.split(data, off)
                at, counts = w.windows(window)
                low, _, _ = anchors(w, at, window, gram)
                doc = np.repeat(np.arange(hi - lo), counts)
                new = np.ones(len(low), bool)
                new[1:] = (low[1:] != low[:-1]) | (doc[1:] != doc[:-1])
                fp, fp2 = whole(w)
                raw = data.tobytes()
                # bytes.split() cuts at these same separators
                sha = [hashlib.sha256(b" ".join(raw[a:b].split())).hexdigest() for a, b in zip(off[:-1].tolist(), off[1:].tolist(), strict=True)]
                own = [batch.column(i).slice(lo, hi - lo) for i in (0, 2)]
                yield pa.RecordBatch.from_arrays([*own, pa.array(w.counts), pa.array(fp), pa.array(fp2), pa.array(sha, pa.string()), tk.lists(tk.signed(low[new]), np.bincount(doc[new], minlength=hi - lo))], ["doc_id", "tag", "n_words", "fp", "fp2", "sha", "anchors"])

    return docs.mapInArrow(run, PROFILE)


def repeats(key: np.ndarray, key2: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """Which rows have a key that a row with a smaller id also has."""
    order = np.lexsort((ids, key2, key))
    k, k2 = key[order], key2[order]
    head = np.ones(len(k), bool)
    head[1:] = (k[1:] != k[:-1]) | (k2[1:] != k2[:-1])
    out = np.zeros(len(k), bool)
    out[order] = ids[order] > ids[order][np.flatnonzero(head)][np.cumsum(head) - 1]
    return out


def look_up(candidates: DataFrame, window: int, gram: int) -> DataFrame:
    """FOUND rows of candidates (doc_id, tag, text, light, heavy), whose last two columns are their shared anchors."""
    reach = window - gram

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo, hi, data, off in tk.pieces(batch.column(2)):
                w = tk.split(data, off)
                at, counts = w.windows(window)
                if not len(at):
                    continue
                doc = np.repeat(np.arange(hi - lo), counts)
                low, first, last = anchors(w, at, window, gram)
                tag = lambda anchor, d: tk.mix(anchor + d.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
                shared = []
                for c in (3, 4):
                    lists = batch.column(c).slice(lo, hi - lo)
                    flat, own = lists.flatten().to_numpy(zero_copy_only=False).view(np.uint64), np.repeat(np.arange(hi - lo), lists.value_lengths().fill_null(0).to_numpy(zero_copy_only=False))
                    shared.append(np.isin(tag(low, doc), tag(flat, own)))
                ids, tags = (batch.column(i).slice(lo, hi - lo).to_numpy(zero_copy_only=False) for i in (0, 1))
                sums, salted = tk.prefix(w.hash, tk._Q), tk.prefix(w.hash, tk._R)
                yield from places(w, doc, low, first, shared[0] & (first == last), sums, ids, tags)
                yield from wholes(w, at, doc, (shared[0] & (first != last)) | shared[1], sums, salted, ids, tags)

    def places(w, doc, low, first, keep, sums, ids, tags):
        doc, low, q = doc[keep], low[keep], first[keep]
        new = np.ones(len(q), bool)
        new[1:] = q[1:] != q[:-1]
        doc, low, q = doc[new], low[new], q[new]
        if not len(q):
            return
        before = np.minimum(q - w.first[doc], reach)
        after = np.minimum(w.first[doc + 1] - q - gram, reach)
        content = tk.mix(tk.between(sums, tk._Q, q - before, q + gram + after) + (before * 4096 + after).astype(np.uint64))
        known = repeats(content, low.view(np.int64), ids[doc])
        d, pos = doc[known], (q - before - w.first[doc])[known]
        yield rows(ids[d], tags[d], SETTLED, pos, (before + after - reach + 1)[known])
        go = np.flatnonzero(~known)
        for s in range(0, len(go), 4096):
            g = go[s : s + 4096]
            step = np.arange(1, reach + 1)
            side = np.concatenate([q[g][:, None] - step, q[g][:, None] + gram - 1 + step], 1)
            words = w.hash[np.clip(side, 0, len(w.hash) - 1)]
            words[:, :reach][step > before[g][:, None]] = 0
            words[:, reach:][step > after[g][:, None]] = 0
            d = doc[g]
            yield rows(ids[d], tags[d], PLACE, q[g] - w.first[d], np.zeros(len(g), np.int64), tk.signed(low[g]), None, before[g], after[g], words)

    def wholes(w, at, doc, keep, sums, salted, ids, tags):
        at, doc = at[keep], doc[keep]
        if not len(at):
            return
        key = tk.mix(tk.between(sums, tk._Q, at, at + window))
        key2 = (tk.mix(tk.between(salted, tk._R, at, at + window)) >> np.uint64(32)).astype(np.uint32).view(np.int32)
        pos = at - w.first[doc]
        known = repeats(key, key2, ids[doc])
        go = np.flatnonzero(~known)
        yield rows(ids[doc[go]], tags[doc[go]], WHOLE, pos[go], np.ones(len(go), np.int64), tk.signed(key[go]), key2[go])
        hit = np.flatnonzero(known)
        if len(hit):
            first = np.ones(len(hit), bool)
            first[1:] = (doc[hit[1:]] != doc[hit[:-1]]) | (pos[hit[1:]] != pos[hit[:-1]] + 1)
            heads = np.flatnonzero(first)
            length = np.diff(np.append(heads, len(hit)))
            hit = hit[heads]
            yield rows(ids[doc[hit]], tags[doc[hit]], SETTLED, pos[hit], length)

    def rows(ids, tags, kind, pos, length, key=None, key2=None, before=None, after=None, words=None):
        n = len(ids)
        whole = lambda x, t: pa.nulls(n, t) if x is None else pa.array(x.astype(t.to_pandas_dtype()))
        raw = pa.nulls(n, pa.binary()) if words is None else pa.array([x.tobytes() for x in words], pa.binary())
        return pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(tags, pa.int64()), pa.array(np.full(n, kind, np.int32)), whole(pos, pa.int32()), whole(length, pa.int32()), whole(key, pa.int64()), whole(key2, pa.int32()), whole(before, pa.int32()), whole(after, pa.int32()), raw], ["doc_id", "tag", "kind", "pos", "run", "key", "key2", "before", "after", "words"])

    return candidates.mapInArrow(run, FOUND)


def factors_of(doc: np.ndarray, key: np.ndarray, before: np.ndarray, after: np.ndarray, words: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, words before the anchor, words after its first) of the factors of places of whole blocks, ordered by key.

    words has the hashes before the anchor, nearest first, then those after it. Rows of equal words are one place, first
    had by the smallest doc; only these places are compared.
    """
    reach = words.shape[1] // 2
    content = tk.mix(words @ tk.powers(tk._P, 2 * reach + 1)[0][1 : 2 * reach + 1] + (before.astype(np.uint64) * np.uint64(4096) + after.astype(np.uint64)))
    order = np.lexsort((doc, content, key))
    head = np.ones(len(order), bool)
    head[1:] = (key[order[1:]] != key[order[:-1]]) | (content[order[1:]] != content[order[:-1]])
    place = np.empty(len(order), np.int64)
    place[order] = np.cumsum(head) - 1
    one = order[head]
    full = np.flatnonzero(doc > doc[one][place])
    out = [(full, before[full], after[full])]
    # places of one block are neighbours: each meets all others of its block
    k = key[one]
    start = np.flatnonzero(np.append(True, k[1:] != k[:-1])) if len(k) else np.zeros(0, np.int64)
    many = np.diff(np.append(start, len(k)))
    owner, width = np.repeat(start, many), np.repeat(many, many)
    x_all, y_at = [], []
    for s in np.split(np.arange(len(k)), np.flatnonzero(np.diff(np.cumsum(width) // PAIRS)) + 1):
        x = np.repeat(s, width[s])
        y = tk.spread(owner[s], width[s])
        ok = doc[one[y]] < doc[one[x]]
        x, y = x[ok], y[ok]
        for t in range(0, len(x), PAIRS):
            a, b = one[x[t : t + PAIRS]], one[y[t : t + PAIRS]]
            same = words[a] == words[b]
            same = np.concatenate([same[:, :reach], np.zeros((len(a), 1), bool), same[:, reach:], np.zeros((len(a), 1), bool)], 1)
            left = np.minimum(same[:, : reach + 1].argmin(1), np.minimum(before[a], before[b]))
            right = np.minimum(same[:, reach + 1 :].argmin(1), np.minimum(after[a], after[b]))
            ok = left + right >= reach
            x_all.append(x[t : t + PAIRS][ok])
            y_at.append(np.stack([left[ok], right[ok]], 1))
    if x_all and sum(map(len, x_all)):
        x, (left, right) = np.concatenate(x_all), np.concatenate(y_at).T
        by = np.lexsort((-right, -left, x))
        x, left, right = x[by], left[by], right[by]
        far = np.maximum.accumulate(x * 4096 + right)  # reaches farther than those that begin before it
        keep = np.ones(len(x), bool)
        keep[1:] = (x[1:] * 4096 + right[1:]) > far[:-1]
        x, left, right = x[keep], left[keep], right[keep]
        # all rows of a place that are its first doc's
        own = order[doc[order] == doc[one][place[order]]]
        first = np.searchsorted(place[own], x)
        n = np.searchsorted(place[own], x, "right") - first
        out.append((own[tk.spread(first, n)], np.repeat(left, n), np.repeat(right, n)))
    return tuple(np.concatenate(c) for c in zip(*out, strict=True))


def parse(found: DataFrame, window: int, gram: int) -> DataFrame:
    """(doc_id, tag, pos, run) of the factors of all blocks."""
    reach = window - gram

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, (key, doc, tag, pos, before, after, words) in tk.runs(batches, 1 << 40):
            at, left, right = factors_of(doc, key, before, after, words)
            yield pa.RecordBatch.from_arrays([pa.array(doc[at]), pa.array(tag[at]), pa.array((pos[at] - left).astype(np.int32)), pa.array((left + right - reach + 1).astype(np.int32))], ["doc_id", "tag", "pos", "run"])

    n = common.partitions(found.sparkSession)
    blocks = found.where(F.col("kind") == PLACE).select("key", "doc_id", "tag", "pos", "before", "after", "words")
    return blocks.repartition(n, "key").sortWithinPartitions("key").mapInArrow(run, "doc_id bigint, tag bigint, pos int, run int")


def settled(docs: DataFrame, window: int = WINDOW, gram: int = GRAM) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Three frames by (doc_id, tag): all texts with n_words and the hash of all their words; those that copy a smaller doc_id
    as a whole; and those that lose some words, with n_removed, the hash and the text of what stays."""
    common.ship(docs.sparkSession)
    rows = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text"))
    rows = rows.select("doc_id", "text", F.xxhash64("text").alias("tag"))
    seen = common.saved(profile(rows, window, gram), "profile")
    long = seen.where(F.col("doc_id").isNotNull() & (F.col("n_words") >= window))
    classes = long.groupBy("n_words", "fp", "fp2").agg(F.min("doc_id").alias("first"), F.max("doc_id").alias("last")).where("first < last").select("n_words", "fp", "fp2", "first")
    copies = common.saved(long.select("doc_id", "tag", "n_words", "fp", "fp2").join(classes, ["n_words", "fp", "fp2"]).where("doc_id > first").select("doc_id", "tag").distinct(), "copies")
    # copies of a whole text need no look-up, only the first one of them
    grams = long.select("doc_id", "tag", "anchors").join(copies, ["doc_id", "tag"], "left_anti").select("doc_id", "tag", F.explode("anchors").alias("anchor"))
    shared = grams.groupBy("anchor").agg(F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi"), F.count("*").alias("n")).where("lo < hi").select("anchor", (F.col("n") > BLOCK).alias("many"))
    of = lambda many: F.collect_set(F.when(F.col("many") == many, F.col("anchor")))
    wanted = common.saved(grams.join(shared, "anchor").groupBy("doc_id", "tag").agg(of(False).alias("light"), of(True).alias("heavy")), "shared")
    candidates = common.saved(rows.where("doc_id is not null").join(wanted, ["doc_id", "tag"]).select("doc_id", "tag", "text", "light", "heavy"), "candidates")
    found = common.saved(look_up(candidates, window, gram), "windows")
    whole = found.where(F.col("kind") == WHOLE)
    least = whole.groupBy("key", "key2").agg(F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi")).where("lo < hi").select("key", "key2", "lo")
    late = whole.join(least, ["key", "key2"]).where("doc_id > lo").select("doc_id", "tag", "pos", "run")
    spans = found.where(F.col("kind") == SETTLED).select("doc_id", "tag", "pos", "run").unionByName(late).unionByName(parse(found, window, gram))
    factors = spans.groupBy("doc_id", "tag").agg(F.collect_list(F.struct("pos", "run")).alias("factors"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo, hi, data, off in tk.pieces(batch.column(2), tk.STEP):
                w = tk.split(data, off)
                gone = covered(w, batch.column(3).slice(lo, hi - lo), window)
                raw, sums, kept = data.tobytes(), np.concatenate([[0], np.cumsum(gone)]), []
                for d in range(hi - lo):
                    a, b = w.first[d], w.first[d + 1]
                    stay = np.flatnonzero(~gone[a:b]) + a
                    kept.append(b" ".join([raw[s:e] for s, e in zip(w.start[stay].tolist(), w.end[stay].tolist(), strict=True)]))
                drop = sums[w.first[1:]] - sums[w.first[:-1]]
                yield pa.RecordBatch.from_arrays([*(batch.column(i).slice(lo, hi - lo) for i in (0, 1)), pa.array(drop), pa.array([hashlib.sha256(x).hexdigest() for x in kept], pa.string()), pa.array([x.decode("utf-8", "replace") for x in kept], pa.string())], ["doc_id", "tag", "n_removed", "kept_sha256", "kept"])

    # rows that repeat both id and text have the same factors, so one of them is enough
    one = candidates.select("doc_id", "tag", "text").dropDuplicates(["doc_id", "tag"])
    changed = one.join(factors, ["doc_id", "tag"]).select("doc_id", "tag", "text", "factors").mapInArrow(run, "doc_id bigint, tag bigint, n_removed bigint, kept_sha256 string, kept string")
    return seen, copies, changed


def covered(w: tk.Words, factors: pa.Array, window: int) -> np.ndarray:
    """Which words lie in a factor."""
    edge = np.zeros(len(w.hash) + 1, np.int64)
    flat = factors.flatten()
    pos, run = (flat.field(k).to_numpy(zero_copy_only=False).astype(np.int64) for k in (0, 1))
    at = np.repeat(w.first[:-1], factors.value_lengths().fill_null(0).to_numpy(zero_copy_only=False)) + pos
    np.add.at(edge, at, 1)
    np.add.at(edge, at + run + window - 1, -1)
    return np.cumsum(edge[:-1]) > 0


def removed(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """(doc_id, n_words, n_removed, kept_sha256) of every row."""
    seen, copies, changed = settled(docs, window)
    fixed = copies.select("doc_id", "tag", F.lit(None).cast("bigint").alias("n_removed"), F.sha2(F.lit("").cast("binary"), 256).alias("kept_sha256"), F.lit(True).alias("all"))
    fixed = fixed.unionByName(changed.select("doc_id", "tag", "n_removed", "kept_sha256", F.lit(False).alias("all")))
    out = seen.select("doc_id", "tag", "n_words", "sha").join(fixed, ["doc_id", "tag"], "left")
    n = F.when(F.col("all"), F.col("n_words")).otherwise(F.coalesce("n_removed", F.lit(0)))
    return out.select("doc_id", "n_words", n.alias("n_removed"), F.coalesce("kept_sha256", "sha").alias("kept_sha256"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return removed(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))


def clean(docs: DataFrame) -> DataFrame:
    """docs with duplicate passages taken out: a changed text is its kept words joined by spaces, all others stay as they
    are. No row goes. n_chars, where there is such a column, follows a changed text."""
    _, copies, changed = settled(docs)
    i, t, kept = common.free(docs.columns, "id_", "tag_", "kept_")
    new = changed.select(F.col("doc_id").alias(i), F.col("tag").alias(t), F.col("kept").alias(kept)).unionAll(copies.select("doc_id", "tag", F.lit("")))
    out = docs.join(new, (docs["doc_id"].cast("bigint") == F.col(i)) & (F.xxhash64(docs["text"].cast("string")) == F.col(t)), "left")
    cols = [F.coalesce(F.col(kept), docs[c]).alias(c) if c == "text" else F.when(F.col(kept).isNotNull(), F.length(kept).cast("bigint")).otherwise(docs[c]).alias(c) if c == "n_chars" else docs[c] for c in docs.columns]
    return out.select(*cols)
