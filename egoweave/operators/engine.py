"""Run an ordinary graph program once per subgraph, each bin loaded once and shared through bitmaps."""

from __future__ import annotations

import pickle
from collections.abc import Callable, Iterable, Iterator
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from ..functions.bitmaps import CLASSES
from ..graph import PropertyGraph
from ..plans.extract import induced_edges
from ..session import cut
from ..spec import ExecOptions
from . import closing

#: Edges from which bins get theirs by a grid of tasks.
MANY_EDGES = 1 << 18


@dataclass(frozen=True)
class Program:
    """fn(view) gives rows of schema for one subgraph."""

    schema: str
    fn: Callable[[SubgraphView], Iterable[tuple]]


class BinGraph:
    """The union of a bin's subgraphs as compressed rows over dense vertex numbers."""

    def __init__(self, ids: np.ndarray, src: np.ndarray, dst: np.ndarray, directed: bool, weight: np.ndarray | None = None):
        self.ids = np.unique(ids)
        self.at = dict(zip(self.ids.tolist(), range(len(self.ids)), strict=True))
        keep = np.isin(src, self.ids) & np.isin(dst, self.ids)
        a, b = np.searchsorted(self.ids, src[keep]), np.searchsorted(self.ids, dst[keep])
        w = np.ones(len(a), np.int64) if weight is None else weight[keep]
        self.directed = directed
        if not directed:
            a, b, w = np.concatenate([a, b]), np.concatenate([b, a]), np.concatenate([w, w])
        self.out_rows, self.in_rows = self._rows(a, b, w), self._rows(b, a, w)

    def _rows(self, a: np.ndarray, b: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        order = np.lexsort((b, a))
        return np.searchsorted(a[order], np.arange(len(self.ids) + 1)), b[order], w[order]


class SubgraphView:
    """All that a program may see: the vertices and edges of its own subgraph."""

    def __init__(self, g: BinGraph, inside: Callable[[int], bool], center: int, members: np.ndarray, mask: np.ndarray | None = None):
        self._g, self._in, self._members, self._mask = g, inside, members, mask
        self.center = center
        self.directed = g.directed
        self._out: dict[int, list[int]] = {}
        self._back: dict[int, list[int]] = {}
        self.state: dict[int, object] = {}

    def vertices(self) -> list[int]:
        return self._g.ids[self._members].tolist()

    def _near(self, v: int, rows, cache: dict[int, list[int]]) -> list[int]:
        if v not in cache:
            i = self._g.at.get(v)
            if i is None or not self._in(i):
                raise KeyError(f"vertex {v} is not in this subgraph")
            at, to, _ = rows
            near = to[at[i] : at[i + 1]]
            # a whole list is tested at once where the subgraph's bits lie side by side
            near = near[self._mask[near]] if self._mask is not None else [j for j in near.tolist() if self._in(j)]
            cache[v] = self._g.ids[near].tolist()
        return cache[v]

    def out(self, v: int) -> list[int]:
        return self._near(v, self._g.out_rows, self._out)

    def in_(self, v: int) -> list[int]:
        return self._near(v, self._g.in_rows, self._back)

    def has_edge(self, u: int, v: int) -> bool:
        return v in self.out(u)

    def weight(self, u: int, v: int) -> int:
        i, j = self._g.at[u], self._g.at[v]
        at, to, w = self._g.out_rows
        return int(w[at[i] + np.searchsorted(to[at[i] : at[i + 1]], j)])

    def set_state(self, v: int, value: object) -> None:
        """Only the centre's state may be written."""
        if v != self.center:
            raise PermissionError(f"vertex {v} is not the centre of this subgraph")
        self.state[v] = value


def materialize_bins(g: PropertyGraph, members: DataFrame, assignment: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(bin_id, sg_id, slot, v) and (bin_id, src, dst, w): every bin gets its vertices and edges once."""
    rows = members.select("sg_id", "v").join(assignment.select("sg_id", "bin_id", "slot"), "sg_id").select("bin_id", "sg_id", "slot", "v")
    unions = rows.select(F.col("bin_id").alias("sg_id"), "v").distinct()
    w = F.col("weight").cast("bigint") if "weight" in g.edges.columns else F.lit(1).cast("bigint")
    # a written graph is counted for nothing; in a large one an edge meets the bins of its ends, not every edge of every bin's vertices
    if hasattr(g.edges, "_egoweave_path") and g.edges.count() >= MANY_EDGES:
        edges = closing.shared(g.edges.where("src is not null and dst is not null").select("src", "dst", *(["weight"] if "weight" in g.edges.columns else [])).withColumnRenamed("weight", "w"), cut(unions.select("v", F.col("sg_id").alias("s")), "unions"))
        return rows, edges.select(F.col("sg_id").alias("bin_id"), "src", "dst", F.col("w") if "w" in edges.columns else F.lit(1).cast("bigint").alias("w"))
    edges = induced_edges(unions, g)
    return rows, edges.select(F.col("sg_id").alias("bin_id"), "src", "dst", w.alias("w"))


def run_bin(g: BinGraph, slots: dict[int, tuple[int, np.ndarray]], fn: Callable, options: ExecOptions) -> Iterator[tuple]:
    """Results of all subgraphs of a bin. slots: slot -> (sg_id, ids of its vertices)."""
    order = sorted(slots)
    size = {"vector": len(order), "batched": options.batch_size, "single": 1}[options.mode] or 1
    for lo in range(0, len(order), size):
        batch = order[lo : lo + size]
        if options.mode == "single":
            mask = np.zeros(len(g.ids), bool)
        else:
            bits = CLASSES[options.bitmap](len(g.ids), len(batch))
        places = {s: np.searchsorted(g.ids, np.sort(slots[s][1])) for s in batch}
        for k, s in enumerate(batch):
            if options.mode == "single":
                mask[places[s]] = True
            elif options.bitmap == "words":
                bits.words[places[s], k >> 6] |= np.uint64(1) << np.uint64(k & 63)
            else:
                for i in places[s].tolist():
                    bits.set(i, k)

        def one(k: int) -> list[tuple]:
            s, own = batch[k], None
            if options.mode == "single":
                own = mask
            elif options.bitmap == "words":
                own = (bits.words[:, k >> 6] >> np.uint64(k & 63)) & np.uint64(1) == 1
            inside = own.__getitem__ if own is not None else lambda i: bits.get(i, k)
            return list(fn(SubgraphView(g, inside, slots[s][0], places[s], own)))

        if options.threads > 1 and options.mode != "single":
            with ThreadPoolExecutor(options.threads) as pool:
                for rows in pool.map(one, range(len(batch))):
                    yield from rows
        else:
            for k in range(len(batch)):
                yield from one(k)


def _arrow(schema: StructType):
    from pyspark.sql.pandas.types import to_arrow_schema

    return to_arrow_schema(schema)


def run(g: PropertyGraph, members: DataFrame, assignment: DataFrame, program: Program, options: ExecOptions = ExecOptions()) -> DataFrame:
    """Rows of the program's schema for every subgraph.

    One group is one bin (mode replicate: one subgraph, its vertices and edges copied); groups pass through a task one after another, so memory holds a bin at a time.
    """
    if options.mode == "replicate":
        assignment = assignment.select("sg_id", F.col("sg_id").alias("bin_id"), F.lit(0).alias("slot"))
    return run_loaded(*materialize_bins(g, members, assignment), g.directed, program, options)


def run_loaded(rows: DataFrame, edges: DataFrame, directed: bool, program: Program, options: ExecOptions = ExecOptions()) -> DataFrame:
    """run() on bins that are loaded already, rows (bin_id, sg_id, slot, v) and edges (bin_id, src, dst, w)."""
    edges = edges.withColumnRenamed("bin_id", "of")
    if options.sequential:
        rows, edges = rows.coalesce(1), edges.coalesce(1)
    schema = StructType.fromDDL(program.schema)
    inner, fn = options if options.mode != "replicate" else ExecOptions(mode="single"), program.fn

    def kernel(left: pa.Table, right: pa.Table) -> pa.Table:
        arrow = _arrow(schema)
        sg, slot, v = (left.column(c).to_numpy() for c in ("sg_id", "slot", "v"))
        src, dst, w = (right.column(c).to_numpy() for c in ("src", "dst", "w"))
        graph = BinGraph(v, src, dst, directed, w)
        order = np.argsort(slot, kind="stable")
        cuts = np.flatnonzero(np.append(True, slot[order][1:] != slot[order][:-1]))
        slots = {int(slot[part[0]]): (int(sg[part[0]]), v[part]) for part in np.split(order, cuts[1:]) if len(part)}
        out = list(run_bin(graph, slots, fn, inner))
        cols = list(zip(*out, strict=True)) if out else [[] for _ in arrow]
        return pa.Table.from_arrays([pa.array(c, f.type) for c, f in zip(cols, arrow, strict=True)], schema=arrow)

    return rows.groupBy("bin_id").cogroup(edges.groupBy("of")).applyInArrow(kernel, schema)


def aggregate_results(results: DataFrame, *aggs) -> DataFrame:
    """Local partial and then final aggregation of program results."""
    return results.agg(*aggs)


@dataclass(frozen=True)
class Aggregator:
    """A user's aggregate of program results: state from init(), add(state, row), merge(state, state), and a row of schema from finish(state)."""

    schema: str
    init: Callable[[], object]
    add: Callable[[object, dict], object]
    merge: Callable[[object, object], object]
    finish: Callable[[object], tuple]


def aggregate(results: DataFrame, by: Aggregator) -> DataFrame:
    """One row: states are built where the results are, a state a partition, and only these meet."""
    schema = StructType.fromDDL(by.schema)

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state = by.init()
        for batch in batches:
            for row in batch.to_pylist():
                state = by.add(state, row)
        yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(state)], pa.binary())], ["state"])

    def final(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state = by.init()
        for batch in batches:
            for part in batch.column(0).to_pylist():
                state = by.merge(state, pickle.loads(part))
        arrow = _arrow(schema)
        yield pa.RecordBatch.from_arrays([pa.array([x], f.type) for x, f in zip(by.finish(state), arrow, strict=True)], schema=arrow)

    return results.mapInArrow(local, "state binary").repartition(1).mapInArrow(final, schema)


def run_pandas(members: DataFrame, edges: DataFrame, fn: Callable, schema: str) -> DataFrame:
    """A program over pandas frames: fn(sg_id, vertices, edges) gives a frame of schema for every subgraph; for programs that need no bins."""

    def each(key, left, right):
        return fn(key[0], left, right)

    return members.groupBy("sg_id").cogroup(edges.withColumnRenamed("sg_id", "of").groupBy("of")).applyInPandas(each, schema)


def write_results(results: DataFrame, path: str, fmt: str = "parquet", by: str | None = None) -> None:
    w = results.write.mode("overwrite").format(fmt)
    (w.partitionBy(by) if by else w).save(path)
