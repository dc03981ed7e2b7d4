"""Bulk-synchronous programs over bins with owned and ghost vertices."""

from __future__ import annotations

import itertools
import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Observation, Row
from pyspark.sql import functions as F

from ..graph import PropertyGraph
from ..session import cut, let_go


@dataclass
class BinState:
    """What a program sees of a bin in one superstep: states of all vertices held, and arcs into the owned ones."""

    ids: np.ndarray
    cur: np.ndarray
    own: np.ndarray  # which vertices are owned
    src: np.ndarray  # places in ids
    dst: np.ndarray
    out_degree: np.ndarray  # of the whole graph, by place
    shared: dict  # what the coordinator sends to all bins


@dataclass(frozen=True)
class Iterative:
    """A superstep program of a user.

    init is an expression over the vertex table's id. step gives new states of all places of a bin; only those of owned
    vertices are kept. aggregates are expressions over v, old, cur and out_degree of all owned vertices; stop, from their row and the
    round, ends the loop, and share says what the next round's bins see of them (first of the row of the initial states).
    """

    init: Callable[[int], Column]
    step: Callable[[BinState], np.ndarray]
    kind: str = "bigint"
    direction: str = "both"
    aggregates: tuple[Column, ...] = ()
    stop: Callable[[Row, int], bool] = lambda row, rounds: row.changed == 0
    share: Callable[[Row], dict] = lambda row: {}


@dataclass
class Run:
    """Final states (v, cur), the number of rounds, and of each round: changed vertices, ghost rows sent, and seconds of the slowest bin's compute, of waiting for all bins and of sending."""

    state: DataFrame
    rounds: int
    metrics: list[tuple] = field(default_factory=list)


def rounds_until(most: int | None) -> Iterator[int]:
    """1, 2, ... for a loop that leaves when nothing changes; raises where that takes more than most rounds."""
    for n in itertools.count(1):
        if most is not None and n > most:
            raise RuntimeError(f"labels still change after {most} rounds")
        yield n


def ghosts(placement: DataFrame) -> DataFrame:
    """(bin_id, n_owned, n_ghost)."""
    own = F.col("owned").cast("int")
    return placement.groupBy("bin_id").agg(F.sum(own).alias("n_owned"), F.sum(1 - own).alias("n_ghost"))


def supersteps(g: PropertyGraph, bins: DataFrame, program: Iterative, max_steps: int | None = None, changed_only: bool = True) -> Run:
    """Run a program until its stop rule holds; max_steps raises where that takes more rounds.

    bins (v, bin_id) says who owns a vertex. In a superstep every bin updates its owned vertices in one kernel from the states
    that it holds (old states stay as they are until the round ends); then only changed states travel to the bins that hold the
    vertex as a ghost (all of them with changed_only off). A round writes its states and the refreshed ghosts, and counts on the way.
    """
    kind, n = program.kind, g.vertices.count()
    arcs = g.arcs(program.direction)
    owned = bins.select("v", "bin_id")
    degree = arcs.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("out_degree"))
    local = cut(arcs.join(owned.withColumnRenamed("v", "dst"), "dst").select(F.col("bin_id").alias("of"), "src", "dst"), "arcs")
    start = owned.join(degree, "v", "left").select("bin_id", "v", F.coalesce("out_degree", F.lit(0)).alias("out_degree"), program.init(n).cast(kind).alias("cur"))
    state = cut(start, "states")
    holds = local.select(F.col("of").alias("bin_id"), F.col("src").alias("v")).distinct().join(state.select("v", F.col("bin_id").alias("home"), "out_degree", "cur"), "v").where("bin_id <> home")
    seen = cut(holds.select("bin_id", "v", "out_degree", "cur"), "ghosts")
    schema = f"bin_id bigint, v bigint, out_degree bigint, old {kind}, cur {kind}, took double"
    column = lambda t, name: t.column(name).to_numpy(zero_copy_only=False) if isinstance(t.column(name), pa.Array) else t.column(name).combine_chunks().to_numpy(zero_copy_only=False)
    step = program.step

    def kernel(shared: dict):
        def run(key, left: pa.Table, right: pa.Table) -> pa.Table:
            began = time.perf_counter()
            ids = column(left, "v")
            order = np.argsort(ids)
            ids, cur, own, k = ids[order], column(left, "cur")[order], column(left, "own")[order].astype(bool), column(left, "out_degree")[order]
            at = lambda name: np.searchsorted(ids, column(right, name))
            new = step(BinState(ids, cur.copy(), own, at("src"), at("dst"), k, shared))
            m = int(own.sum())
            bin_id = key[0].as_py()
            return pa.table({"bin_id": pa.array([bin_id] * m, pa.int64()), "v": ids[own], "out_degree": k[own], "old": cur[own], "cur": new[own].astype(cur.dtype), "took": np.full(m, time.perf_counter() - began)})

        return run

    totals = (F.sum((F.col("old") != F.col("cur")).cast("bigint")).alias("changed"), *program.aggregates)
    shared = program.share(state.withColumn("old", F.col("cur")).agg(*totals).head())
    metrics = []
    for rounds in rounds_until(max_steps):
        began = time.perf_counter()
        held = state.select("bin_id", "v", "out_degree", "cur", F.lit(True).alias("own")).unionAll(seen.select("bin_id", "v", "out_degree", "cur", F.lit(False).alias("own")))
        watch = Observation()
        out = held.groupBy("bin_id").cogroup(local.groupBy("of")).applyInArrow(kernel(shared), schema)
        new = cut(out.observe(watch, *totals, F.max("took").alias("took")), "states")
        row, between = Row(**watch.get), time.perf_counter()
        done = program.stop(row, rounds)
        sent = 0
        if not done:
            travels = new.where("old <> cur") if changed_only else new
            count = Observation()
            fresh = seen.join(travels.select("v", F.col("cur").alias("new")), "v", "left")
            fresh = cut(fresh.observe(count, F.count("new").alias("n")).select("bin_id", "v", "out_degree", F.coalesce("new", "cur").alias("cur")), "ghosts")
            sent = count.get["n"]
            let_go(seen)
            seen = fresh
        ended = time.perf_counter()
        metrics.append((rounds, row.changed, sent, row.took or 0.0, max(0.0, between - began - (row.took or 0.0)), ended - between))
        let_go(state)
        state, shared = new, program.share(row)
        if done:
            return Run(state.select("v", "cur"), rounds, metrics)


def min_label(local_fix: bool = False) -> Iterative:
    """The smallest id that reaches a vertex. local_fix lets a bin run to its own fixed point first, which takes fewer rounds to the same labels."""

    def step(b: BinState) -> np.ndarray:
        cur = b.cur
        while True:
            new = cur.copy()
            np.minimum.at(new, b.dst, cur[b.src])
            if not local_fix or (new == cur).all():
                return new
            cur = new

    return Iterative(lambda n: F.col("v"), step)


def rank_program(n: int, damping: float = 0.85, rounds: int = 10, tolerance: float = 0.0) -> Iterative:
    """PageRank: vertices without out-arcs give their score to all in equal parts, by way of the coordinator."""

    def step(b: BinState) -> np.ndarray:
        got = np.zeros(len(b.ids))
        np.add.at(got, b.dst, b.cur[b.src] / b.out_degree[b.src])
        return (1 - damping) / n + damping * (got + b.shared["lost"] / n)

    lost = F.coalesce(F.sum(F.when(F.col("out_degree") == 0, F.col("cur"))), F.lit(0.0)).alias("lost")
    moved = F.coalesce(F.sum(F.abs(F.col("cur") - F.col("old"))), F.lit(0.0)).alias("moved")
    return Iterative(lambda n: F.lit(1.0 / n), step, "double", "out", (lost, moved), lambda row, r: r >= rounds or row.moved <= tolerance, lambda row: {"lost": row.lost})


def components(g: PropertyGraph, bins: DataFrame, max_steps: int | None = None, local_fix: bool = False, changed_only: bool = True) -> tuple[DataFrame, int, list[tuple]]:
    """((v, component), rounds, metrics) of global minimum labels; rounds go on until no label changes."""
    run = supersteps(g, bins, min_label(local_fix), max_steps, changed_only)
    return run.state.select("v", F.col("cur").alias("component")), run.rounds, run.metrics


def pagerank_bins(g: PropertyGraph, bins: DataFrame, damping: float = 0.85, rounds: int = 10, tolerance: float = 0.0) -> DataFrame:
    """(v, score) by the program above over bins and ghosts."""
    return supersteps(g, bins, rank_program(g.vertices.count(), damping, rounds, tolerance)).state.select("v", F.round("cur", 9).alias("score"))


def pagerank(g: PropertyGraph, damping: float = 0.85, rounds: int = 10) -> DataFrame:
    """(v, score) over the whole graph; vertices without out-edges give their score to all in equal parts."""
    n = g.vertices.count()
    arcs = g.arcs("out")
    out = arcs.groupBy("src").agg(F.count("*").alias("k"))
    arcs = arcs.join(out, "src")
    ids = g.vertices.select(F.col("id").alias("v")).join(out.withColumnRenamed("src", "v"), "v", "left")
    score = ids.select("v", "k", F.lit(1.0 / n).alias("s"))
    for _ in range(rounds):
        lost = score.where("k is null").agg(F.coalesce(F.sum("s"), F.lit(0.0)).alias("lost"))
        moved = arcs.join(score.select(F.col("v").alias("src"), "s"), "src").groupBy(F.col("dst").alias("v")).agg(F.sum(F.col("s") / F.col("k")).alias("x"))
        score = ids.join(moved, "v", "left").join(F.broadcast(lost)).select("v", "k", (F.lit((1 - damping) / n) + damping * (F.coalesce("x", F.lit(0.0)) + F.col("lost") / n)).alias("s"))
        score = cut(score, "rank")  # two readers follow
    return score.select("v", F.round("s", 9).alias("score"))
