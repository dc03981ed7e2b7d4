"""Triangles of graphs whose wedges would fill a disk: edges meet by ranges of their ends, and wedges are tested inside a task.

Vertices are cut into ranges of about equal numbers of edge ends. A triangle's corners lie in three ranges, which name the one task
that finds it; an edge goes to the tasks of its two ranges and any third one with edges to both. Where ids are local, few ranges
have edges between them and an edge is written about once; in a graph without structure it is written once a range.

Where only some corners are asked for, an edge lies opposite to those that both its ends are linked with, so the short lists of these
come to the edges, and no triangle of other corners is looked at.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph import PropertyGraph
from ..session import cut

#: Ranges at the finest, edges that a task may hold, and edges that are dealt at once.
RANGES, TASK_EDGES, DEALT = 128, 4_000_000, 1 << 20
#: What a dealt piece holds, and entries of lists that are looked up in one step.
EDGE, SPOKE, LOOKED_UP = 0, 1, 1 << 22


def plan(held: np.ndarray, limit: int) -> tuple[int, np.ndarray]:
    """(step, tasks): how many fine ranges make one, and the tasks (i, j, k), i <= j <= k, from the edges between fine ranges.

    Of the steps whose tasks stay within the limit, the one that writes the fewest edges; else the finest.
    """
    found = []
    for step in (1 << k for k in range(len(held).bit_length())):
        n = -(-len(held) // step)
        at = np.arange(len(held)) // step
        e = np.zeros((n, n), np.int64)
        np.add.at(e, (np.minimum(at[:, None], at), np.maximum(at[:, None], at)), held)
        has = e > 0
        rows = []
        for i, j in zip(*np.nonzero(has), strict=True):
            k = j + np.flatnonzero(has[i, j:] & has[j, j:])
            rows.append(np.column_stack([np.full(len(k), i), np.full(len(k), j), k]))
        t = np.concatenate(rows) if rows else np.zeros((0, 3), np.int64)
        i, j, k = t.T
        load = e[i, j] + np.where(k == j, 0, e[i, k]) + np.where(i == j, 0, e[j, k])
        over = load.max(initial=0) > limit
        found.append((over, step if over else load.sum(), step, t))
    _, _, step, t = min(found, key=lambda x: x[:3])
    return step, t


def _ranges(values: np.ndarray, bounds: np.ndarray, step: int = 1) -> np.ndarray:
    return np.searchsorted(bounds, values, "right") // step


def closed(src: np.ndarray, dst: np.ndarray, bounds: np.ndarray, step: int, mixed: bool) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(a, b, c) of the triangles of some edges, in pieces; mixed: only those whose corners are not all in one range.

    Edges point from lower to higher degree. The ends of a vertex's edges are marked, and the ends of theirs looked up.
    """
    if mixed:  # a triangle of two ranges has two edges between them, so both ends of its third edge have such an edge
        cross = _ranges(src, bounds, step) != _ranges(dst, bounds, step)
        ends = np.unique(np.concatenate([src[cross], dst[cross]]))
        keep = np.isin(src, ends) & np.isin(dst, ends)
        src, dst = src[keep], dst[keep]
    ids, both = np.unique(np.concatenate([src, dst]), return_inverse=True)
    degree = np.bincount(both, minlength=len(ids))
    rank = np.empty(len(ids), np.int64)
    rank[np.argsort(degree, kind="stable")] = np.arange(len(ids))
    ids = ids[np.argsort(rank)]
    a, b = rank[both[: len(src)]], rank[both[len(src) :]]
    a, b = np.minimum(a, b), np.maximum(a, b)
    order = np.argsort(a * len(ids) + b)
    a, b = a[order], b[order]
    at = np.searchsorted(a, np.arange(len(ids) + 1))
    size = np.diff(at)
    home = _ranges(ids, bounds, step) if mixed else None
    wedges = np.add.reduceat(np.append(size[b], 0), at[:-1]) if len(ids) else size
    mark = np.zeros(len(ids), bool)
    for v in np.flatnonzero((size > 1) & (wedges > 0)).tolist():
        near = b[at[v] : at[v + 1]]
        n = size[near]
        total = int(n.sum())
        to = b[np.arange(total) + np.repeat(at[near] - (np.cumsum(n) - n), n)]
        mark[near] = True
        hit = np.flatnonzero(mark[to])
        mark[near] = False
        if len(hit):
            x, y = near[np.searchsorted(np.cumsum(n), hit, "right")], to[hit]
            if mixed:
                keep = (home[x] != home[v]) | (home[y] != home[v])
                x, y = x[keep], y[keep]
            yield np.full(len(x), ids[v]), ids[x], ids[y]


def _gathered(parts: Iterator[tuple[np.ndarray, ...]]) -> list[np.ndarray]:
    held = list(parts)
    return [np.concatenate([p[side] for p in held]) if held else np.zeros(0, np.int64) for side in range(3)]


def _found(g: PropertyGraph, emit: Callable, schema: str) -> DataFrame:
    """Rows of schema by emit(triangles of a task) from every task."""
    und, columns = g.arcs("both").where("src < dst").select("src", "dst"), ["src", "dst"]
    cuts = und.select(F.explode(F.array("src", "dst")).alias("v")).approxQuantile("v", [k / RANGES for k in range(1, RANGES)], 0.001)
    bounds = np.unique(np.array(cuts, np.float64).astype(np.int64))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n = len(bounds) + 1
        held = np.zeros(n * n, np.int64)
        for batch in batches:
            held += np.bincount(_ranges(batch.column(0).to_numpy(), bounds) * n + _ranges(batch.column(1).to_numpy(), bounds), minlength=n * n)
        pair = np.flatnonzero(held)
        yield pa.RecordBatch.from_arrays([pa.array(pair), pa.array(held[pair])], ["pair", "n"])

    held = np.zeros((len(bounds) + 1) ** 2, np.int64)
    for r in und.mapInArrow(count, "pair bigint, n bigint").groupBy("pair").agg(F.sum("n").alias("n")).collect():  # RANGES ** 2 rows at most
        held[r.pair] = r.n
    step, tasks = plan(held.reshape(len(bounds) + 1, -1), TASK_EDGES)
    of: dict[tuple[int, int], list[int]] = {}
    for t, (i, j, k) in enumerate(tasks.tolist()):
        for pair in {(i, j), (i, k), (j, k)}:
            of.setdefault(pair, []).append(t)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        waiting: list[pa.RecordBatch] = []

        def flush() -> Iterator[pa.RecordBatch]:
            t = pa.Table.from_batches(waiting)
            waiting.clear()
            cols = [t.column(c).to_numpy() for c in columns]
            i, j = (_ranges(x, bounds, step) for x in cols[:2])
            order = np.lexsort((cols[1], cols[0], j, i))
            cols, i, j = [x[order] for x in cols], i[order], j[order]
            starts = np.flatnonzero(np.append(True, (i[1:] != i[:-1]) | (j[1:] != j[:-1]))) if len(i) else []
            for lo, hi in zip(starts, [*starts[1:], len(i)], strict=True):
                to = of.get((int(i[lo]), int(j[lo])), ())
                if len(to):
                    data = [pa.array([x[lo:hi].tobytes()] * len(to), pa.binary()) for x in cols]
                    yield pa.RecordBatch.from_arrays([pa.array(to, pa.int64()), *data], ["task", *columns])

        for batch in batches:
            waiting.append(batch)
            if sum(b.num_rows for b in waiting) >= DEALT:
                yield from flush()
        if waiting:
            yield from flush()

    def run(t: pa.Table) -> pa.Table:
        i, j, k = tasks[t.column("task")[0].as_py()].tolist()
        src, dst = (np.frombuffer(b"".join(t.column(c).to_pylist()), np.int64) for c in columns)
        return emit(closed(src, dst, bounds, step, i < k and (i == j or j == k)))

    dealt = und.mapInArrow(deal, "task bigint, " + ", ".join(f"{c} binary" for c in columns))
    return dealt.repartition(max(1, min(len(tasks), 2000)), "task").groupBy("task").applyInArrow(run, schema)


def corner_counts(g: PropertyGraph) -> DataFrame:
    """(sg_id, links): triangles through each vertex that has any."""

    def emit(found: Iterator) -> pa.Table:
        ids, n = np.unique(np.concatenate(_gathered(found)), return_counts=True)
        return pa.table({"sg_id": ids, "links": n})

    return _found(g, emit, "sg_id bigint, links bigint").groupBy("sg_id").agg(F.sum("links").alias("links"))


def _places(ids: np.ndarray, side: int) -> np.ndarray:
    """Row or column of the grid for each id."""
    return ((ids.astype(np.int64).view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(33)) % np.uint64(side)


def shared_seeds(v: np.ndarray, s: np.ndarray, src: np.ndarray, dst: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(seed, place of the edge) of every edge and every seed that both its ends are linked with by spokes (v, s), in pieces.

    The shorter list of an edge is looked up in the longer one: in a table of marks by hash, and what passes among the sorted spokes.
    """
    ids, v = np.unique(v, return_inverse=True)
    seeds, s = np.unique(s, return_inverse=True)
    if not len(ids) or not len(src):
        return
    keys = np.unique(v * len(seeds) + s)
    v, s = np.divmod(keys, len(seeds))
    at = np.searchsorted(v, np.arange(len(ids) + 1))
    size = np.diff(at)
    shift = np.uint64(64 - max(10, len(keys).bit_length() + 3))
    place = lambda x: (x.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> shift
    mark = np.zeros(1 << (64 - int(shift)), bool)
    mark[place(keys)] = True
    a, b = (np.minimum(np.searchsorted(ids, x), len(ids) - 1) for x in (src, dst))
    keep = np.flatnonzero((ids[a] == src) & (ids[b] == dst))
    a, b = a[keep], b[keep]
    swap = size[a] > size[b]
    a, b = np.where(swap, b, a), np.where(swap, a, b)
    so_far = np.cumsum(size[a])
    for part in np.split(np.arange(len(a)), np.flatnonzero(np.diff(so_far // LOOKED_UP)) + 1) if len(a) else ():
        n = size[a[part]]
        starts = np.cumsum(n) - n
        which = s[np.arange(n.sum()) + np.repeat(at[a[part]] - starts, n)]
        key = which + np.repeat(b[part] * len(seeds), n)
        maybe = np.flatnonzero(mark[place(key)])
        key = key[maybe]
        hit = maybe[keys[np.minimum(np.searchsorted(keys, key), len(keys) - 1)] == key]
        yield seeds[which[hit]], keep[part[np.searchsorted(starts, hit, "right") - 1]]


def shared(edges: DataFrame, spokes: DataFrame) -> DataFrame:
    """(sg_id, src, dst, and w where there is one) of every edge and every s that both its ends have in spokes (v, s); both are read twice.

    Edges are dealt to a grid of tasks by both their ends, and spokes to the row and the column of their vertex, so an edge is
    written once and a spoke once for each task of these.
    """
    # pieces are bytes of numbers of one width
    edges, spokes = (x.select(*(F.col(c).cast("bigint").alias(c) for c in x.columns)) for x in (edges, spokes))
    side = max(1, math.ceil((edges.count() / TASK_EDGES) ** 0.5), -(-spokes.count() // (2 * TASK_EDGES)))
    out, columns = ["sg_id", *edges.columns], ["x", "y", "w"] if "w" in edges.columns else ["x", "y"]

    def deal(kind: int, tasks_of: Callable) -> Callable:
        def flush(waiting: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            t = pa.Table.from_batches(waiting)
            cols = [x.to_numpy() for x in t.columns]
            cell = tasks_of(*cols[:2])
            order = np.argsort(cell, kind="stable")
            cell, cols = cell[order], [x[order] for x in cols]
            starts = np.flatnonzero(np.append(True, cell[1:] != cell[:-1])).tolist() if len(cell) else []
            for lo, hi in zip(starts, [*starts[1:], len(cell)], strict=True):
                c = int(cell[lo])
                # spokes go to the tasks of a row and of a column
                to = [c] if kind == EDGE else sorted({c * side + k for k in range(side)} | {k * side + c for k in range(side)})
                n = len(to)
                data = [x[lo:hi].tobytes() for x in cols] + [b""] * (len(columns) - len(cols))
                yield pa.RecordBatch.from_arrays([pa.array(to, pa.int32()), pa.array([kind] * n, pa.int32()), *(pa.array([x] * n, pa.binary()) for x in data)], ["task", "kind", *columns])

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            waiting: list[pa.RecordBatch] = []
            rows = 0
            for batch in batches:
                waiting.append(batch)
                rows += batch.num_rows
                if rows >= DEALT:
                    yield from flush(waiting)
                    waiting, rows = [], 0
            if waiting:
                yield from flush(waiting)

        return run

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list[list[bytes]]] = {kind: [[] for _ in columns] for kind in (EDGE, SPOKE)}
        for batch in batches:
            for kind, *data in zip(*(batch.column(c).to_pylist() for c in ("kind", *columns)), strict=True):
                for to, x in zip(held[kind], data, strict=True):
                    to.append(x)
        v, s = (np.frombuffer(b"".join(x), np.int64) for x in held.pop(SPOKE)[:2])
        cols = [np.frombuffer(b"".join(x), np.int64) for x in held.pop(EDGE)]
        for seed, at in shared_seeds(v, s, *cols[:2]):
            yield from pa.table([pa.array(seed, pa.int64()), *(pa.array(x[at], pa.int64()) for x in cols)], out).to_batches(max_chunksize=1 << 16)

    form = "task int, kind int, " + ", ".join(f"{c} binary" for c in columns)
    dealt = edges.mapInArrow(deal(EDGE, lambda x, y: _places(x, side) * np.uint64(side) + _places(y, side)), form)
    dealt = dealt.unionAll(spokes.mapInArrow(deal(SPOKE, lambda x, y: _places(x, side)), form))
    return dealt.repartitionById(side * side, F.col("task")).mapInArrow(meet, ", ".join(f"{c} bigint" for c in out))


def opposite_edges(g: PropertyGraph, seed_ids: DataFrame) -> DataFrame:
    """(sg_id, src, dst), src < dst: the edges among the neighbours of each seed.

    A vertex's spokes are the seeds that it is linked with.
    """
    und = g.arcs("both").where("src < dst").select("src", "dst")
    arcs = und.unionAll(und.select("dst", "src"))
    # written, so that few seeds are seen to be few and no arc is moved to find them
    few = cut(seed_ids.select(F.col("id").alias("dst")).distinct(), "seeds")
    spokes = cut(arcs.join(few, "dst", "left_semi").select(F.col("src").alias("v"), F.col("dst").alias("s")), "spokes")
    return shared(und, spokes)
