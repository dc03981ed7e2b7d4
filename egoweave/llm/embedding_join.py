"""Operator 7: exact embedding near-duplicates by a subspace pigeonhole join.

Unit vectors x, y with cosine >= t have |x - y|^2 <= 2 (1 - t). A fixed rotation spreads this over blocks of about
BLOCK coordinates (twice as many from WIDE rows on, as a longer block tells more apart); if every block had more than its share
(in proportion to its coordinates) the sum would exceed the budget, so at least one block lies within its own. Each block
is joined by range on a grid over its first coordinates, so many that a cell holds about CELL_ROWS of the counted rows: a vector
lives in one cell and is sent as a query to the cells whose nearest corner or side is within the block's share. So the pairs
met grow with the rows, and as a power of them far under two, until all coordinates of a block are in use. In a cell, block
distances are matrix products; the pairs within the block's budget are verified in full by cosine in double precision, and
counted in the first block only in which they qualify. A query goes to its own and later cells only. So every link is found once.

A cell of very many vectors is dealt in parts of DATA_ROWS x QUERY_ROWS that meet pairwise. A task gives out counts and
a spanning forest, never its pairs, so a group of near copies costs rows in proportion to its size.

Vectors that are null, empty, zero or hold null or non-finite components link with nothing, nor do those with a null id;
vectors of different length never link. Rows that share vec_id and vector are one. Rows that share a vec_id alone do not link
with each other; they are one vertex of the components, and n_links counts the links of each. An empty table gives an empty result.
Other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common, textkit as tk

THRESHOLD, BLOCK, WIDE, CELL_ROWS = 0.95, 8, 1 << 22, 2048
DATA_ROWS, QUERY_ROWS, STEP = 16384, 32768, 256
SLACK = 1e-9


def rotation(d: int) -> np.ndarray:
    q, r = np.linalg.qr(np.random.default_rng(7000 + d).normal(size=(d, d)))
    return q * np.sign(np.diag(r))


def normal(x: np.ndarray) -> np.ndarray:
    """Rows at length one. Coordinates are added in turn, so that a row's bits do not depend on its neighbours."""
    total = np.zeros(len(x))
    for j in range(x.shape[1]):
        total += x[:, j] * x[:, j]
    return x / np.sqrt(total)[:, None]


def turned(x: np.ndarray, by: np.ndarray) -> np.ndarray:
    out = np.zeros_like(x)
    for j in range(x.shape[1]):
        out += x[:, j : j + 1] * by[j]
    return out


def layout(d: int, threshold: float, rows: int) -> tuple[list[slice], list[float], int]:
    """Blocks, their shares of the squared distance, and the coordinates of a block that its grid takes."""
    size = BLOCK if rows < WIDE else 2 * BLOCK
    cuts = np.linspace(0, d, max(1, d // size) + 1).astype(int)
    blocks = [slice(int(a), int(b)) for a, b in zip(cuts[:-1], cuts[1:], strict=True)]
    # a coordinate of a unit vector falls into about three cells
    axes = int(np.clip(np.ceil(np.log(max(rows, 1) / CELL_ROWS) / np.log(3)), 2, min(b.stop - b.start for b in blocks)))
    return blocks, [(2 - 2 * threshold + SLACK) * (b.stop - b.start) / d for b in blocks], axes


def cells(y: np.ndarray, block: slice, share: float, axes: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Home cell of each rotated row, and (row, cell) of the cells from there on that its ball touches."""
    radius = np.sqrt(share) * (1 + 1e-9) + 1e-12
    width, axes = 2 * radius, min(axes, block.stop - block.start)
    base = int(2 / width) + 4
    home, row, cell, gap = np.zeros(len(y), np.int64), np.arange(len(y)), np.zeros(len(y), np.int64), np.zeros(len(y))
    for j in range(block.start, block.start + axes):
        home = home * base + np.floor(y[:, j] / width).astype(np.int64) + base // 2
        at = np.floor(y[row, j] / width).astype(np.int64)
        # the cell itself and one on either side: the ball is as wide as a cell
        step = np.tile(np.array([-1, 0, 1]), len(row))
        row, gap, at = np.repeat(row, 3), np.repeat(gap, 3), np.repeat(at, 3) + step
        side = np.where(step > 0, at * width - y[row, j], np.where(step < 0, y[row, j] - (at + 1) * width, 0.0))
        gap = gap + side * side
        near = gap <= radius * radius
        row, gap, cell = row[near], gap[near], (np.repeat(cell, 3) * base + at + base // 2)[near]
    ahead = cell >= home[row]  # of two cells the pair meets in the later one
    return home, row[ahead], cell[ahead]


def merge(label: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
    """Give linked places the smallest label among them."""
    while True:
        la, lb = label[a], label[b]
        if (la == lb).all():
            return
        least = np.minimum(la, lb)
        np.minimum.at(label, la, least)
        np.minimum.at(label, lb, least)
        while (label[label] != label).any():
            label[:] = label[label]


def near(vectors: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """(vec_id, n_links, component_id, kept) of every row of vectors (vec_id, embedding)."""
    spark = vectors.sparkSession
    common.ship(spark)
    # floats travel as floats: they are the same numbers in double precision
    kind = np.float32 if dict(vectors.dtypes)["embedding"] == "array<float>" else np.float64
    rows = vectors.select(F.col("vec_id").cast("bigint").alias("vec_id"), F.col("embedding").cast("array<float>" if kind == np.float32 else "array<double>").alias("v"))
    sound = F.coalesce(F.size("v") > 0, F.lit(False)) & F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists("v", lambda x: x != 0)
    good = rows.where(F.col("vec_id").isNotNull() & F.coalesce(sound, F.lit(False))).dropDuplicates(["vec_id", "v"])

    def matrix(col: pa.Array, at: np.ndarray, d: int) -> np.ndarray:
        return col.take(pa.array(at)).flatten().to_numpy(zero_copy_only=False).reshape(len(at), d)

    def unit(x: np.ndarray) -> np.ndarray:
        x = x.astype(np.float64)
        return normal(x / np.abs(x).max(1)[:, None])

    def by_width(batch: pa.RecordBatch) -> Iterator[tuple[int, np.ndarray]]:
        d = batch.column(1).value_lengths().to_numpy(zero_copy_only=False)
        for k in np.unique(d):
            yield int(k), np.flatnonzero(d == k)

    def tally(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for d, at in by_width(batch):
                y = turned(unit(matrix(batch.column(1), at, d)), rotation(d))
                blocks, shares, axes = layout(d, threshold, n_rows)
                for b, (block, share) in enumerate(zip(blocks, shares, strict=True)):
                    home, _, cell = cells(y, block, share, axes)
                    ids = np.unique(np.concatenate([home, cell]))
                    nd, nq = (np.bincount(np.searchsorted(ids, c), minlength=len(ids)) for c in (home, cell))
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(ids), d)), pa.array(np.full(len(ids), b)), *map(pa.array, (ids, nd, nq))], ["d", "block", "cell", "nd", "nq"])

    good = common.saved(good, "vectors")
    n_rows = good.count()
    tallied = good.mapInArrow(tally, "d bigint, block bigint, cell bigint, nd bigint, nq bigint").groupBy("d", "block", "cell").agg(F.sum("nd").alias("nd"), F.sum("nq").alias("nq"))
    # only cells of clusters are so full; they are at most the rows met over QUERY_ROWS
    parts = {(r.d, r.block, r.cell): (-(-r.nd // DATA_ROWS) or 1, -(-r.nq // QUERY_ROWS) or 1) for r in tallied.where((F.col("nd") > DATA_ROWS) | (F.col("nq") > QUERY_ROWS)).collect()}
    sent = spark.sparkContext.broadcast(parts)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for d, at in by_width(batch):
                ids = batch.column(0).to_numpy(zero_copy_only=False)[at]
                x = matrix(batch.column(1), at, d)
                y = turned(unit(x), rotation(d))
                blocks, shares, axes = layout(d, threshold, n_rows)
                salt = (tk.mix(ids.view(np.uint64)) >> np.uint64(33)).astype(np.int64)
                raw = [r.tobytes() for r in x]
                for b, (block, share) in enumerate(zip(blocks, shares, strict=True)):
                    home, row, cell = cells(y, block, share, axes)
                    for query, (r, c) in enumerate(((np.arange(len(x)), home), (row, cell))):
                        names, back = np.unique(c, return_inverse=True)
                        split = np.array([sent.value.get((d, b, k), (1, 1)) for k in names.tolist()], np.int64).reshape(-1, 2)
                        own, other = split[back, query], split[back, 1 - query]
                        mine = np.repeat(salt[r] % own, other)
                        yours = tk.spread(np.zeros_like(other), other)
                        r, c = np.repeat(r, other), np.repeat(c, other)
                        q, p = (mine, yours) if query else (yours, mine)
                        key = tk.mix(tk.mix(tk.mix(tk.mix(c.view(np.uint64)) + np.uint64(b)) + q.view(np.uint64)) ^ (p * 65536 + d).view(np.uint64))
                        for lo in range(0, len(r), 4096):
                            s = slice(lo, lo + 4096)
                            n = len(r[s])
                            yield pa.RecordBatch.from_arrays([pa.array(tk.signed(key[s])), pa.array(np.full(n, b, np.int32)), pa.array((query * (1 + (c[s] != home[r[s]]))).astype(np.int32)), pa.array(ids[r[s]]), pa.array([raw[i] for i in r[s].tolist()], pa.binary())], ["key", "block", "query", "vec_id", "x"])

    def match(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, held = None, []
        for batch in batches:
            k = batch.column(0).to_numpy()
            heads = np.append(np.flatnonzero(np.append(True, k[1:] != k[:-1])), len(k))
            for lo, hi in zip(heads[:-1].tolist(), heads[1:].tolist(), strict=True):
                if lo == hi:
                    continue
                if k[lo] != key:
                    yield from solve(held)
                    key, held = k[lo], []
                held.append(batch.slice(lo, hi - lo))
        yield from solve(held)

    def solve(held: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if not held:
            return
        t = pa.Table.from_batches(held)
        query = t.column("query").to_numpy()
        if (query > 0).all() or not query.any():
            return
        b, ids = t.column("block")[0].as_py(), t.column("vec_id").to_numpy()
        x = unit(np.frombuffer(b"".join(t.column("x").to_pylist()), kind).reshape(len(ids), -1))
        d = x.shape[1]
        y = turned(x, rotation(d))
        blocks, shares, _ = layout(d, threshold, n_rows)
        low = np.ascontiguousarray(y[:, blocks[b]], np.float32)
        norm, one = (low * low).sum(1)[:, None], np.ones((len(ids), 1), np.float32)
        data, ask = np.flatnonzero(query == 0), np.flatnonzero(query > 0)
        # squared distances as one product
        left, right = np.hstack([-2 * low, one, norm]), np.ascontiguousarray(np.hstack([low, norm, one])[data].T)
        label, count = np.arange(len(ids)), np.zeros(len(ids), np.int64)
        # the rows of one vector, as data and as query, are one place
        _, first, back = np.unique(ids, return_index=True, return_inverse=True)
        merge(label, np.arange(len(ids)), first[back])
        for lo in range(0, len(ask), STEP):
            q = ask[lo : lo + STEP]
            at = np.flatnonzero(left[q] @ right <= shares[b] + 1e-5)
            i, j = q[at // len(data)], data[at % len(data)]
            other = np.where(query[i] == 1, ids[i] < ids[j], ids[i] != ids[j])
            i, j = i[other], j[other]
            for s in range(0, len(i), 1 << 16):
                p, o = i[s : s + (1 << 16)], j[s : s + (1 << 16)]
                gap = (y[p] - y[o]) ** 2
                ok = gap[:, blocks[b]].sum(1) <= shares[b]
                for e in range(b):
                    ok &= gap[:, blocks[e]].sum(1) > shares[e]
                p, o = p[ok], o[ok]
                ok = np.einsum("ij,ij->i", x[p], x[o]) >= threshold
                p, o = p[ok], o[ok]
                if len(p):
                    count += np.bincount(p, minlength=len(ids)) + np.bincount(o, minlength=len(ids))
                    merge(label, p, o)
        out = np.flatnonzero((count > 0) | (ids[label] != ids))
        if len(out):
            yield pa.RecordBatch.from_arrays([pa.array(ids[out]), pa.array(count[out]), pa.array(ids[label[out]])], ["vec_id", "n", "root"])

    n = common.partitions(spark)
    dealt = good.mapInArrow(deal, "key bigint, block int, query int, vec_id bigint, x binary").repartition(4 * n, "key").sortWithinPartitions("key", "query")
    found = common.saved(dealt.mapInArrow(match, "vec_id bigint, n bigint, root bigint"), "links")
    links = found.groupBy("vec_id").agg(F.sum("n").alias("n_links"))
    tree = common.components(found.where("vec_id <> root").select(F.col("vec_id").alias("a"), F.col("root").alias("b"))).withColumnRenamed("v", "vec_id")
    out = rows.select("vec_id").join(links, "vec_id", "left").join(tree, "vec_id", "left")
    component = F.coalesce("component", "vec_id")
    return out.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("bigint").alias("n_links"), component.alias("component_id"), F.coalesce(F.col("vec_id") == component, F.lit(True)).alias("kept"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near(spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding"))


def sql() -> str:
    """The query in DuckDB's SQL, by comparing all pairs."""
    return f"""
with recursive n as (select distinct vec_id, embedding::double[] as v from embeddings where vec_id is not null and embedding is not null and len(embedding) > 0
  and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0 and len(list_filter(embedding, lambda x: x <> 0)) > 0),
e as (select a.vec_id as a, b.vec_id as b from n a join n b on a.vec_id <> b.vec_id and len(a.v) = len(b.v) where list_cosine_similarity(a.v, b.v) >= {THRESHOLD}),
reach as (select distinct a as v, a as l from e union select e.b, r.l from reach r join e on e.a = r.v),
c as (select v, min(l) as component from reach group by 1), k as (select a, count(*) as n_links from e group by 1)
select vec_id, coalesce(n_links, 0) as n_links, coalesce(component, vec_id) as component_id, coalesce(vec_id = coalesce(component, vec_id), true) as kept
from embeddings left join k on k.a = vec_id left join c on c.v = vec_id"""
