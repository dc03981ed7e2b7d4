"""Operator 2: exact n-gram Jaccard join with set-relation skipping.

A document's set holds the 64-bit hashes of its SHINGLE-word shingles (of its whole word sequence where it
has fewer words). Two sets link when 100 * |intersection| >= PERCENT * |union|. Steps:

1. Documents with equal sets fall into classes by two 64-bit set hashes and the size; the smallest id
   of a class stands for it.
2. Each representative posts its prefix, the |x| - ceil(PERCENT/100 |x|) + 1 first shingles in a global order,
   to index lists (shingle -> document, set size, position). The order puts the most frequent
   shingles last (a list of at most HEAVY_MAX, found from partial counts over all documents); which
   shingles those are changes the cost, never the result.
3. In each list the first document becomes the pivot of those of a compatible size, and the pair is verified on the
   full texts, which leaves the pivot's overlap with every partner and the partner's difference from it. The answers of a
   partner are derived from these alone (answer skipping): partners that link to the pivot are one component with it, and for
   one that does not, its overlap with each other partner y is the pivot's overlap with y, less the shingles of y that it
   lacks, plus those that it has beyond the pivot.
4. What is left in lists of three or more is compared across components only: the entries outside the list's largest
   component against all, in blocks of BLOCK entries ordered by size and position. A pair of blocks whose sizes or positions
   rule out the needed overlap, or that holds a single component, is skipped as a whole (block skipping). Of the
   others only pairs leave the task whose parity signatures, folded to SKETCH bits beside each entry, allow a link.
5. Before texts move, pairs must pass the same bound on whole parity signatures, which never drops a link. The survivors
   are verified.

So a group of n near copies costs about n verified pairs per pivot, not n squared, and no list has to stay in
memory beyond 2 * LIST_ROWS entries. All joins on doc_id broadcast only counted, bounded sides.

Null or empty texts have empty sets and link with nothing. Rows with a null doc_id link with nothing and have a null
component. Rows that share a doc_id count as one document: where their texts differ, their
sets are joined as if linked.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common, textkit as tk

SHINGLE, PERCENT = 4, 85
#: A shingle is heavy from so many documents on; the list of heavy ones is at most so long (16 bytes each).
HEAVY, HEAVY_MAX, LOCAL = 48, 200_000, 4
BLOCK, LIST_ROWS, GROUP_ROWS = 128, 65_536, 256
#: Bits of a set's parity signature (how often its hashes fall on each place, modulo two): a power of two, the set's size or more within these bounds.
BITS, MOST_BITS = 1024, 1 << 16
#: Bits of the signature that goes with an entry of an index list.
SKETCH = 2048
PROFILE = "doc_id bigint, n bigint, fp bigint, fp2 bigint, parity array<bigint>, sketch binary, heavy array<bigint>, counts array<bigint>"
LISTED = "pair boolean, token bigint, a bigint, b bigint, size int, pos int"


def sets(data: np.ndarray, off: np.ndarray, shingle: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes document by document, and their numbers."""
    w = tk.split(data, off, fold=True)
    _, h, counts = w.grams(shingle)
    few = np.flatnonzero((w.counts > 0) & (w.counts < shingle))
    doc = np.repeat(np.arange(len(off) - 1), counts)
    if len(few):
        sums = tk.prefix(w.hash, tk._R)
        own = tk.mix(tk.between(sums, tk._R, w.first[few], w.first[few + 1]) ^ w.counts[few].astype(np.uint64))
        doc, h = np.concatenate([doc, few]), np.concatenate([h, own])
    order = np.lexsort((h, doc))
    doc, h = doc[order], h[order]
    new = np.ones(len(h), bool)
    new[1:] = (h[1:] != h[:-1]) | (doc[1:] != doc[:-1])
    return h[new], np.bincount(doc[new], minlength=len(off) - 1)


def needed(a: np.ndarray, b: np.ndarray, percent: int) -> np.ndarray:
    """The least overlap of sets of sizes a and b that link."""
    return -(-percent * (a + b) // (100 + percent))


def room(a: np.ndarray, b: np.ndarray, percent: int) -> np.ndarray:
    """The most shingles that only one of two linked sets of sizes a and b can have."""
    return a + b - 2 * needed(a, b, percent)


def profile(docs: DataFrame, shingle: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo, hi, data, off in tk.pieces(batch.column(1)):
                h, n = sets(data, off, shingle)
                ends = np.concatenate([[0], np.cumsum(n)])
                total = lambda x: (s := np.concatenate([np.zeros(1, np.uint64), np.cumsum(x)]))[ends[1:]] - s[ends[:-1]]
                fp, fp2 = tk.signed(total(tk.mix(h))), tk.signed(total(tk.mix(h ^ np.uint64(0x8CB92BA72F3D8DD7))))
                _, one = np.unique(fp, return_index=True)  # copies count once
                flat = np.concatenate([h[ends[d] : ends[d + 1]] for d in one]) if len(one) else h
                keys, times = np.unique(flat, return_counts=True)
                keys, times = keys[times >= LOCAL], times[times >= LOCAL]
                size = np.zeros(hi - lo, np.int64)
                size[0] = len(keys)
                bits = np.clip(1 << np.ceil(np.log2(np.maximum(n, 1))).astype(np.int64), BITS, MOST_BITS)
                base, doc = np.cumsum(bits) - bits, np.repeat(np.arange(hi - lo), n)
                place = base[doc] + (h & (bits[doc] - 1).astype(np.uint64)).astype(np.int64)
                parity = np.packbits((np.bincount(place, minlength=bits.sum()) & 1).astype(np.uint8)).view(np.int64)
                sketch = np.bincount(doc * SKETCH + (h & np.uint64(SKETCH - 1)).astype(np.int64), minlength=(hi - lo) * SKETCH) & 1
                sketch = np.packbits(sketch.astype(np.uint8)).reshape(hi - lo, SKETCH // 8)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo), pa.array(n), pa.array(fp), pa.array(fp2), tk.lists(parity, bits // 64), pa.array([x.tobytes() for x in sketch], pa.binary()), tk.lists(tk.signed(keys), size), tk.lists(times, size)], ["doc_id", "n", "fp", "fp2", "parity", "sketch", "heavy", "counts"])

    return docs.mapInArrow(run, PROFILE)


def heavy(seen: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Sorted hashes and counts of the most frequent shingles, HEAVY_MAX at most."""
    rows = seen.where(F.size("heavy") > 0).select(F.explode(F.arrays_zip("heavy", "counts")).alias("x")).select("x.heavy", "x.counts")
    top = rows.groupBy("heavy").agg(F.sum("counts").alias("n")).where(F.col("n") >= HEAVY).orderBy(F.desc("n"), "heavy").limit(HEAVY_MAX).toArrow()
    keys, n = top.column(0).to_numpy().view(np.uint64), top.column(1).to_numpy()
    order = np.argsort(keys)
    return keys[order], n[order]


def postings(docs: DataFrame, frequent: tuple[np.ndarray, np.ndarray], shingle: int, percent: int) -> DataFrame:
    sent = docs.sparkSession.sparkContext.broadcast(frequent)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, times = sent.value
        for batch in batches:
            for lo, hi, data, off in tk.pieces(batch.column(1), tk.STEP):
                h, n = sets(data, off, shingle)
                doc = np.repeat(np.arange(hi - lo), n)
                count = np.zeros(len(h), np.int64)
                if len(keys):
                    at = np.minimum(np.searchsorted(keys, h), len(keys) - 1)
                    hit = keys[at] == h
                    count[hit] = times[at[hit]]
                order = np.lexsort((h, count, doc))
                keep = n - (percent * n + 99) // 100 + 1
                keep[n == 0] = 0
                which = order[tk.spread(np.cumsum(n) - n, keep)]
                pos = tk.spread(np.zeros(hi - lo, np.int64), keep)
                d = doc[which]
                yield pa.RecordBatch.from_arrays([pa.array(tk.signed(h[which])), batch.column(0).slice(lo, hi - lo).take(pa.array(d)), pa.array(n[d].astype(np.int32)), pa.array(pos.astype(np.int32))], ["token", "doc", "size", "pos"])

    return docs.mapInArrow(run, "token bigint, doc bigint, size int, pos int")


def star(posted: DataFrame, percent: int) -> DataFrame:
    """Pairs (pivot, document) of every list, and the entries of lists of three or more."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, (token, doc, size, pos) in tk.runs(batches, LIST_ROWS):
            new = np.ones(len(token), bool)
            new[1:] = token[1:] != token[:-1]
            heads = np.flatnonzero(new)
            n = np.diff(np.append(heads, len(token)))
            rest = tk.spread(heads[n > 1], n[n > 1])
            far = tk.spread(heads, n) if part else tk.spread(heads[n > 2], n[n > 2])
            yield rows(False, token[far], doc[far], doc[far], size[far], pos[far])
            a, b = [], []
            while len(rest):
                first = np.ones(len(rest), bool)
                first[1:] = token[rest[1:]] != token[rest[:-1]]
                pivot = rest[first][np.cumsum(first) - 1]
                x, y = size[rest].astype(np.int64), size[pivot].astype(np.int64)
                fits = (100 * x >= percent * y) & (100 * y >= percent * x)
                near = fits & ~first & (1 + np.minimum(x - pos[rest] - 1, y - pos[pivot] - 1) >= needed(x, y, percent)) & (doc[pivot] != doc[rest])
                a.append(doc[pivot[near]])
                b.append(doc[rest[near]])
                rest = rest[~fits]
            if a:
                both = np.unique(np.stack([np.concatenate(a), np.concatenate(b)], 1), axis=0)
                yield rows(True, both[:, 0] * 0, both[:, 0], both[:, 1], (both[:, 0] * 0).astype(np.int32), (both[:, 0] * 0).astype(np.int32))

    def rows(pair, token, a, b, size, pos):
        return pa.RecordBatch.from_arrays([pa.array(np.full(len(a), pair)), *map(pa.array, (token, a, b, size, pos))], ["pair", "token", "a", "b", "size", "pos"])

    n = common.partitions(posted.sparkSession)
    return posted.repartition(n, "token").sortWithinPartitions("token", "doc").select("token", "doc", "size", "pos").mapInArrow(run, LISTED)


def meet(size: np.ndarray, pos: np.ndarray, comp: np.ndarray, percent: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Places (x, y) of one list's entries, of different components, that sizes and positions allow to link.

    All pairs have an entry outside the list's largest component. Blocks that cannot hold such a pair are skipped.
    """
    names, back, many = np.unique(comp, return_inverse=True, return_counts=True)
    if len(names) < 2:
        return
    major = back == many.argmax()
    order = np.lexsort((pos, size))
    few, most = order[~major[order]], order[major[order]]
    for other, own in ((few, True), (most, False)):
        cut = np.arange(0, len(other), BLOCK)
        end = np.minimum(cut + BLOCK, len(other))
        least, large = size[other[cut]], size[other[end - 1]]
        room_left = large - np.minimum.reduceat(pos[other], cut)
        low, high = np.minimum.reduceat(comp[other], cut), np.maximum.reduceat(comp[other], cut)
        for s in range(0, len(few), BLOCK):
            i = few[s : s + BLOCK]
            live = (100 * size[i[-1]] >= percent * least) & (100 * large >= percent * size[i[0]])
            live &= np.minimum((size[i[-1]] - pos[i].min()), room_left) >= needed(size[i[0]], least, percent)
            live &= ~((low == high) & (comp[i].min() == low) & (comp[i].max() == low))
            if own:
                live &= cut >= s
            for j in np.flatnonzero(live):
                k = other[cut[j] : end[j]]
                x, y = size[i][:, None], size[k][None, :]
                ok = (comp[i][:, None] != comp[k][None, :]) & (100 * x >= percent * y) & (100 * y >= percent * x)
                ok &= 1 + np.minimum(x - pos[i][:, None] - 1, y - pos[k][None, :] - 1) >= needed(x, y, percent)
                if own and cut[j] == s:
                    ok &= np.triu(np.ones(ok.shape, bool), 1)
                a, b = np.nonzero(ok)
                if len(a):
                    yield i[a], k[b]


def across(entries: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b), a < b, of entries (token, doc, size, pos, comp, part, sketch) of one list and different components that may link.

    Lists are bounded by the caller. Where a list holds several parts, only pairs of different parts count.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, (token, doc, size, pos, comp, part, sketch) in tk.runs(batches, 1 << 40):
            size, pos = size.astype(np.int64), pos.astype(np.int64)
            new = np.ones(len(token), bool)
            new[1:] = token[1:] != token[:-1]
            heads = np.append(np.flatnonzero(new), len(token))
            out = [np.zeros((0, 2), np.int64)]
            for lo, hi in zip(heads[:-1], heads[1:], strict=True):
                several = part[lo:hi].min() < part[lo:hi].max()
                for x, y in meet(size[lo:hi], pos[lo:hi], comp[lo:hi], percent):
                    x, y = x + lo, y + lo
                    ok = (doc[x] != doc[y]) & ((part[x] != part[y]) if several else True)
                    x, y = x[ok], y[ok]
                    ok = np.bitwise_count(sketch[x] ^ sketch[y]).sum(1, dtype=np.int64) <= room(size[x], size[y], percent)
                    x, y = x[ok], y[ok]
                    if len(x):
                        out.append(np.stack([np.minimum(doc[x], doc[y]), np.maximum(doc[x], doc[y])], 1))
            both = np.unique(np.concatenate(out), axis=0)
            yield pa.RecordBatch.from_arrays([pa.array(both[:, 0]), pa.array(both[:, 1])], ["a", "b"])

    n = common.partitions(entries.sparkSession)
    return entries.repartition(n, "token").sortWithinPartitions("token").select("token", "doc", "size", "pos", "comp", "part", "sketch").mapInArrow(run, "a bigint, b bigint").distinct()


def plausible(pairs: DataFrame, seen: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b) whose parity signatures allow a link: places that differ are shingles that only one of the two has, and a link leaves room for few."""
    own = seen.where("doc_id is not null and n > 0").select("doc_id", "n", "parity")
    xor = lambda x, y: x.bitwiseXOR(y)
    # the longer of two signatures folds to the length of the other: its halves are added modulo two
    fold = lambda x, y: F.when(F.size(x) > F.size(y), F.zip_with(F.slice(x, 1, F.size(y)), F.slice(x, F.size(y) + 1, F.size(y)), xor)).otherwise(F.col(x))
    differ = F.aggregate(F.zip_with(fold("pa", "pb"), fold("pb", "pa"), lambda x, y: F.bit_count(xor(x, y))), F.lit(0), lambda s, x: s + x)
    total = F.col("na") + F.col("nb")
    room = total - 2 * F.ceil(percent * total / (100 + percent))
    both = pairs.join(own.toDF("a", "na", "pa"), "a").join(own.toDF("b", "nb", "pb"), "b")
    return both.where(F.coalesce(differ <= room, F.lit(True))).select("a", "b").distinct()


def derived(near: list[tuple[int, int, np.ndarray, bool]], percent: int) -> list[tuple[int, int]]:
    """Links among the partners of one pivot, from what each differs by from the pivot.

    near holds (id, set size, sorted shingles that only it or only the pivot has, links to the pivot). Pairs of which both
    link to the pivot are left out: they are one component already.
    """
    out = []
    if not near or all(x[3] for x in near):
        return out
    size, gap, owner = np.array([x[1] for x in near]), np.array([len(x[2]) for x in near]), np.repeat(np.arange(len(near)), [len(x[2]) for x in near])
    flat = np.concatenate([x[2] for x in near])
    for i, (own, n, only, linked) in enumerate(near):
        if linked:
            continue
        at = np.minimum(np.searchsorted(only, flat), max(len(only) - 1, 0))
        both = np.bincount(owner[only[at] == flat], minlength=len(near)) if len(only) else np.zeros(len(near), np.int64)
        ok = gap + gap[i] - 2 * both <= room(size, n, percent)
        out += [(near[j][0], own) for j in np.flatnonzero(ok).tolist() if near[j][0] != own and (near[j][3] or j < i)]
    return out


def verified(docs: DataFrame, pairs: DataFrame, shingle: int, percent: int) -> DataFrame:
    """Those of the distinct, saved pairs (a, b) that link, by their whole texts, and links among the partners of one a.

    Partners are gathered around their a in groups of about GROUP_ROWS, to each of which a's text is sent.
    """
    many = pairs.groupBy("a").agg(F.ceil(F.count("*") / GROUP_ROWS).cast("int").alias("groups"))
    salted = pairs.join(many, "a").select(F.col("a"), F.pmod(F.xxhash64("b"), F.col("groups")).cast("int").alias("salt"), F.col("b").alias("doc_id"), F.lit(1).alias("turn"))
    pivots = many.select("a", F.explode(F.sequence(F.lit(0), F.col("groups") - 1)).alias("salt"), F.col("a").alias("doc_id"), F.lit(0).alias("turn"))
    roles = common.small(common.saved(salted.unionByName(pivots), "roles"), 40)
    texts = docs.join(roles, "doc_id").select("a", "salt", "turn", "doc_id", "text")

    def links(found: list[tuple[int, int]]) -> pa.RecordBatch:
        a, b = zip(*found, strict=True) if found else ((), ())
        return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        group, pivot, near = None, [], []
        for batch in batches:
            keys = list(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True))
            turn, ids = batch.column(2).to_pylist(), batch.column(3).to_pylist()
            found = []
            for lo, hi, data, off in tk.pieces(batch.column(4), tk.STEP):
                h, n = sets(data, off, shingle)
                parts = np.split(h, np.cumsum(n)[:-1])
                for i in range(lo, hi):
                    if keys[i] != group:
                        found += derived(near, percent)
                        group, pivot, near = keys[i], [], []
                    y = parts[i - lo]
                    if turn[i] == 0:
                        pivot.append(y)
                        continue
                    for k, x in enumerate(pivot):
                        if len(x) and len(y):
                            at = np.searchsorted(x, y)
                            at[at == len(x)] = 0
                            both = x[at] == y
                            links_here = np.count_nonzero(both) >= needed(len(x), len(y), percent)
                            if links_here:
                                found.append((keys[i][0], ids[i]))
                            # a partner much farther from the pivot than a link allows is left to across()
                            if k == 0 and len(x) + len(y) - 2 * np.count_nonzero(both) <= 2 * room(len(x), len(y), percent) + 2:
                                lacks = np.ones(len(x), bool)
                                lacks[at[both]] = False
                                near.append((ids[i], len(y), np.sort(np.concatenate([y[~both], x[lacks]])), links_here))
            yield links(found)
        yield links(derived(near, percent))

    n = common.partitions(docs.sparkSession)
    return texts.repartition(n, "a", "salt").sortWithinPartitions("a", "salt", "turn").mapInArrow(run, "a bigint, b bigint")


def join(docs: DataFrame, shingle: int = SHINGLE, percent: int = PERCENT) -> DataFrame:
    """(doc_id, n_shingles, component_id) of every row of documents (doc_id, text)."""
    common.ship(docs.sparkSession)
    rows = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text"))
    seen = common.saved(profile(rows, shingle), "sets")
    known = seen.where("doc_id is not null and n > 0").select("doc_id", "n", "fp", "fp2")
    classes = known.groupBy("n", "fp", "fp2").agg(F.min("doc_id").alias("first"), F.count("*").alias("members"))
    placed = common.saved(known.join(classes.where("members > 1"), ["n", "fp", "fp2"], "left").select("doc_id", F.coalesce("first", "doc_id").alias("first")).distinct(), "classes")
    firsts = common.small(common.saved(placed.select(F.col("first").alias("doc_id")).distinct(), "firsts"), 16)
    texts = rows.join(firsts, "doc_id", "left_semi")
    listed = common.saved(star(postings(texts, heavy(seen), shingle, percent), percent), "lists")
    tried = common.saved(listed.where("pair").select("a", "b").distinct(), "pairs")
    links = common.saved(verified(rows, common.saved(plausible(tried, seen, percent), "plausible"), shingle, percent), "links")
    tree = common.components(links)
    tied = common.small(tree.select(F.col("v").alias("doc"), F.col("component").alias("comp")), 32)
    entries = listed.where("not pair").select("token", F.col("a").alias("doc"), "size", "pos").join(tied, "doc", "left").withColumn("comp", F.coalesce("comp", "doc"))
    entries = common.saved(entries, "entries")
    mixed = entries.groupBy("token").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), F.ceil(F.count("*") / LIST_ROWS).alias("parts")).where("lo < hi").select("token", "parts")
    # a list of over LIST_ROWS entries is dealt in parts, and every two parts meet in a list of their own
    own = F.pmod(F.xxhash64("doc"), F.col("parts"))
    dealt = entries.join(mixed, "token").withColumn("part", own).withColumn("other", F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("parts") - 1)))
    dealt = dealt.withColumn("token", F.xxhash64("token", F.least("part", "other"), F.greatest("part", "other")))
    # rows that share an id bring a sketch each, so the right one is among them
    dealt = dealt.join(seen.where("doc_id is not null and n > 0").select(F.col("doc_id").alias("doc"), F.col("n").cast("int").alias("size"), "sketch").distinct(), ["doc", "size"])
    more = across(dealt, percent)
    untried = more.join(tried.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")), ["a", "b"], "left_anti")
    untried = common.saved(plausible(untried, seen, percent), "plausible")
    found = verified(rows, untried, shingle, percent)
    copies = placed.where("doc_id <> first").select(F.col("first").alias("a"), F.col("doc_id").alias("b"))
    whole = common.components(tree.select(F.col("component").alias("a"), F.col("v").alias("b")).unionByName(found).unionByName(copies))
    final = common.small(whole.withColumnRenamed("v", "doc_id"), 32)
    return seen.select("doc_id", F.col("n").alias("n_shingles")).join(final, "doc_id", "left").select("doc_id", "n_shingles", F.coalesce("component", "doc_id").alias("component_id"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return join(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))


def clean(docs: DataFrame, shingle: int = 5, percent: int = 80) -> DataFrame:
    """docs without those of a component other than its smallest doc_id; null ids, documents without words and repeated rows of a kept id stay."""
    found = common.saved(join(docs, shingle, percent).where("doc_id <> component_id").select("doc_id").distinct(), "dropped")
    return docs.join(common.small(found, 16), "doc_id", "left_anti")
