"""Extraction: subgraphs as (sg_id, v, hop) rows, by one equi-join per hop."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.minhash import A, B, P
from ..graph import PropertyGraph
from ..spec import AttributeSpec, ListSpec, NeighborhoodSpec, PairSpec


def mark_seeds(g: PropertyGraph, pred: str | None) -> DataFrame:
    """(id, is_seed) of all vertices; a predicate that is null does not make a seed."""
    return g.vertices.select("id", F.coalesce(F.expr(pred), F.lit(False)).alias("is_seed") if pred else F.lit(True).alias("is_seed"))


def seeds(g: PropertyGraph, pred: str | None) -> DataFrame:
    return (g.vertices.where(pred) if pred else g.vertices).select("id")


def sample_seeds(g: PropertyGraph, count: int, salt: int = 0) -> DataFrame:
    """count vertices of smallest hash: the same ones on every run."""
    h = F.expr(f"({A[0]} * pmod(id + {salt}, {P}) + {B[0]}) % {P}")
    return g.vertices.select("id", h.alias("h")).orderBy("h", "id").limit(count).select("id")


def filter_graph(g: PropertyGraph, v_pred: str | None = None, e_pred: str | None = None) -> PropertyGraph:
    """Only vertices and edges that pass; an edge needs both its ends."""
    vertices = g.vertices.where(v_pred) if v_pred else g.vertices
    edges = g.edges.where(e_pred) if e_pred else g.edges
    if v_pred:
        ids = vertices.select("id")
        edges = edges.join(ids.withColumnRenamed("id", "src"), "src", "left_semi").join(ids.withColumnRenamed("id", "dst"), "dst", "left_semi")
    return PropertyGraph(vertices, edges.select(*g.edges.columns), g.directed)


def hop_join(frontier: DataFrame, arcs: DataFrame) -> DataFrame:
    """(sg_id, v) one step on from every frontier row."""
    return frontier.withColumnRenamed("v", "src").join(arcs, "src").select("sg_id", F.col("dst").alias("v"))


def khop_members(g: PropertyGraph, spec: NeighborhoodSpec, seed_ids: DataFrame | None = None) -> DataFrame:
    """(sg_id, v, hop) with the least hop of each vertex; the centre has hop 0.

    pre: vertex and edge rules hold before walking (the centre is exempt from the vertex rule unless
    keep_center is off). post: walk on everything, then drop vertices that fail the vertex rule.
    """
    start = seed_ids if seed_ids is not None else seeds(g, spec.seed_pred)
    pre = spec.filter_mode == "pre"
    passing = g.vertices.where(spec.v_pred).select(F.col("id").alias("v")) if spec.v_pred else None
    if passing is not None and not spec.keep_center:
        start = start.join(passing.withColumnRenamed("v", "id"), "id", "left_semi")
    walk = PropertyGraph(g.vertices, g.edges.where(spec.e_pred) if pre and spec.e_pred else g.edges, g.directed)
    arcs = walk.arcs(spec.direction)
    inner = arcs
    if pre and passing is not None:  # steps may end in passing vertices only; the first starts at the exempt centre
        arcs = arcs.join(passing.withColumnRenamed("v", "dst"), "dst", "left_semi").select("src", "dst")
        inner = arcs
    members = start.select(F.col("id").alias("sg_id"), F.col("id").alias("v"), F.lit(0).alias("hop"))
    frontier = members.select("sg_id", "v")
    for hop in range(1, spec.k + 1):
        reached = hop_join(frontier, arcs if hop == 1 else inner).distinct()
        fresh = reached.where("v <> sg_id") if hop == 1 else reached.join(members.select("sg_id", "v"), ["sg_id", "v"], "left_anti")
        members = members.unionAll(fresh.select("sg_id", "v", F.lit(hop).alias("hop")))
        frontier = fresh
    if not pre and passing is not None:
        members = members.where("v = sg_id").unionAll(members.where("v <> sg_id").join(passing, "v", "left_semi").select("sg_id", "v", "hop"))
    return members


def local_members(g: PropertyGraph, spec: NeighborhoodSpec) -> DataFrame:
    """As khop_members, on one executor in compressed rows: for a filtered structure that fits one task; the caller has to know that it does."""
    if spec.filter_mode == "post" and spec.v_pred:
        raise ValueError("the local strategy filters first")
    start = seeds(g, spec.seed_pred)
    arcs = PropertyGraph(g.vertices, g.edges.where(spec.e_pred) if spec.e_pred else g.edges, g.directed).arcs(spec.direction)
    if spec.v_pred:
        passing = g.vertices.where(spec.v_pred).select("id")
        arcs = arcs.join(passing.withColumnRenamed("id", "dst"), "dst", "left_semi")
        if not spec.keep_center:
            start = start.join(passing, "id", "left_semi")
    rows = arcs.select("src", "dst").unionAll(start.select(F.col("id").alias("src"), F.lit(None).cast("bigint").alias("dst")))
    k = spec.k

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(list(batches), pa.schema([("src", pa.int64()), ("dst", pa.int64())]))
        is_seed = np.asarray(t.column(1).is_null())
        src, dst = t.column(0).to_numpy()[~is_seed], t.column(1).fill_null(0).to_numpy()[~is_seed]
        order = np.argsort(src, kind="stable")
        src, dst = src[order], dst[order]
        for c in t.column(0).to_numpy()[is_seed].tolist():
            seen, frontier, hop = np.array([c]), np.array([c]), [np.zeros(1, np.int32)]
            out = [seen]
            for j in range(1, k + 1):
                lo, hi = np.searchsorted(src, frontier), np.searchsorted(src, frontier, "right")
                reach = np.unique(np.concatenate([dst[a:b] for a, b in zip(lo, hi, strict=True)])) if len(frontier) else frontier
                frontier = np.setdiff1d(reach, seen, assume_unique=True)
                seen = np.union1d(seen, frontier)
                out.append(frontier)
                hop.append(np.full(len(frontier), j, np.int32))
            v = np.concatenate(out)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(v), c)), pa.array(v), pa.array(np.concatenate(hop))], ["sg_id", "v", "hop"])

    return rows.repartition(1).mapInArrow(run, "sg_id bigint, v bigint, hop int")


#: Bytes of filtered structure up to which one task extracts: an edge takes 16, twice where walks go both ways.
LOCAL_BYTES = 256 << 20


def choose_strategy(g: PropertyGraph, spec: NeighborhoodSpec, budget: int = LOCAL_BYTES) -> str:
    """local where the counted structure after filtering fits the budget of one task, else distributed; a post filter is always distributed."""
    if spec.filter_mode == "post" and spec.v_pred:
        return "distributed"
    arcs = PropertyGraph(g.vertices, g.edges.where(spec.e_pred) if spec.e_pred else g.edges, g.directed).arcs(spec.direction)
    return "local" if 16 * arcs.count() <= budget else "distributed"


def members(g: PropertyGraph, spec: NeighborhoodSpec, budget: int = LOCAL_BYTES) -> DataFrame:
    """(sg_id, v, hop) by the strategy that the sizes call for."""
    return (local_members if choose_strategy(g, spec, budget) == "local" else khop_members)(g, spec)


def project(members: DataFrame, g: PropertyGraph, spec: NeighborhoodSpec) -> tuple[DataFrame, DataFrame]:
    """members with the vertex attributes that the spec names, and induced edges with its edge attributes; nothing else is read."""
    v = g.vertices.select(F.col("id").alias("v"), *spec.attrs_v)
    keep = PropertyGraph(g.vertices, g.edges.select("src", "dst", *spec.attrs_e), g.directed)
    return members.join(v, "v", "left").select(*members.columns, *spec.attrs_v), induced_edges(members, keep)


def attribute_members(g: PropertyGraph, spec: AttributeSpec) -> DataFrame:
    """(sg_id, v, hop) with the attribute's value as sg_id."""
    return g.vertices.where(F.col(spec.column).isNotNull()).select(F.col(spec.column).alias("sg_id"), F.col("id").alias("v"), F.lit(0).alias("hop")).distinct()


def edge_pairs(g: PropertyGraph) -> DataFrame:
    """(a, b): the ends of every edge."""
    return g.edges.select(F.col("src").alias("a"), F.col("dst").alias("b"))


def pair_members(g: PropertyGraph, spec: PairSpec) -> DataFrame:
    """(a, b, v): union or intersection of the balls around a and b."""
    ends = spec.pairs.select(F.col("a").alias("id")).union(spec.pairs.select(F.col("b").alias("id"))).distinct()
    balls = khop_members(g, NeighborhoodSpec(k=spec.k, direction="both"), ends).select("sg_id", "v")
    of = lambda side: spec.pairs.join(balls, F.col(side) == F.col("sg_id")).select("a", "b", "v")
    return of("a").union(of("b")).distinct() if spec.op == "union" else of("a").intersect(of("b"))


def list_members(spec: ListSpec) -> DataFrame:
    """Given lists without rows that lack an id or repeat."""
    return spec.members.where("sg_id is not null and v is not null").select("sg_id", "v", F.lit(0).alias("hop")).distinct()


def vertex_weights(g: PropertyGraph, model: str = "unit", attrs_v: tuple[str, ...] = (), attrs_e: tuple[str, ...] = ()) -> DataFrame:
    """(id, w): unit 1; degree 1 + degree; bytes 16 and attribute widths, and per neighbour 8 and edge attribute widths; else an expression over the vertex columns."""
    if model == "unit":
        return g.vertices.select("id", F.lit(1).cast("bigint").alias("w"))
    if model not in ("degree", "bytes"):
        return g.vertices.select("id", F.expr(model).cast("bigint").alias("w"))
    degree = F.coalesce("degree", F.lit(0))
    rows = g.vertices.join(g.degrees(), "id", "left")
    if model == "degree":
        return rows.select("id", (1 + degree).cast("bigint").alias("w"))
    fixed = {"tinyint": 1, "smallint": 2, "int": 4, "float": 4, "boolean": 1}
    own = lambda frame, names: sum(fixed.get(t, 8) for c, t in frame.dtypes if c in names and t != "string")
    texts = [F.coalesce(F.octet_length(c), F.lit(0)) for c, t in g.vertices.dtypes if c in attrs_v and t == "string"]
    return rows.select("id", (16 + own(g.vertices, attrs_v) + sum(texts, F.lit(0)) + degree * (8 + own(g.edges, attrs_e))).cast("bigint").alias("w"))


def attach_weights(members: DataFrame, weights: DataFrame) -> DataFrame:
    """members with w; vertices outside the weight table weigh nothing there and are dropped."""
    return members.join(weights.withColumnRenamed("id", "v"), "v").select("sg_id", "v", "hop", "w")


def subgraph_sizes(members: DataFrame) -> DataFrame:
    """(sg_id, n_vertices, load) of weighted members."""
    return members.groupBy("sg_id").agg(F.count("*").alias("n_vertices"), F.sum("w").alias("load"))


def induced_edges(members: DataFrame, g: PropertyGraph) -> DataFrame:
    """(sg_id, src, dst, edge attributes) with both ends in the subgraph."""
    m = members.select("sg_id", "v")
    rest = [c for c in g.edges.columns if c not in ("src", "dst")]
    first = m.withColumnRenamed("v", "src").join(g.edges, "src")
    return first.join(m.withColumnRenamed("v", "dst"), ["sg_id", "dst"], "left_semi").select("sg_id", "src", "dst", *rest)


def edge_membership(members: DataFrame, g: PropertyGraph) -> DataFrame:
    """(src, dst, sgs): the subgraphs that each edge belongs to."""
    return induced_edges(members, g).groupBy("src", "dst").agg(F.sort_array(F.collect_set("sg_id")).alias("sgs"))
