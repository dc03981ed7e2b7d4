"""The experiments as functions: grids over graphs, packers, models and modes, in the layout of a table or a plot series.

A packing grid runs one instance a task: the items of each cell meet in one group, and a kernel orders and packs them. What is
counted is exact; seconds and bytes are measured in the task or taken from the status store of the session.
"""

from __future__ import annotations

import time
import tracemalloc
from collections.abc import Callable, Iterable, Iterator
from dataclasses import replace
from functools import reduce

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import metrics
from .functions import bitmaps, minhash
from .graph import PropertyGraph, from_edges
from .operators import baselines, engine, iterate, kernels, packing, programs, relational, sampling
from .plans import extract
from .session import cut, let_go
from .sources import graphs
from .spec import ExecOptions, NeighborhoodSpec, PackOptions

GRID = "packer string, capacity int, max_items int, n_hashes int, percentile double, n_buckets int"
CELL = [c.split()[0] for c in GRID.split(", ")]
PLACED = f"instance string, {GRID}, bucket bigint, sg_id bigint, local bigint, lower bigint, upper bigint, seconds double, bytes bigint"
#: Nodes that the exact search visits at most, so that its answer does not depend on a clock.
NODES = 20_000


def union(frames: Iterable[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def cell(packer: str, capacity: int = 90, max_items: int | None = 12, n_hashes: int = 6, percentile: float = 10.0, n_buckets: int = 1) -> tuple:
    return packer, capacity, max_items, n_hashes, percentile, n_buckets


def place(packer: str, ids: list[int], sets: list[frozenset], capacity: int, max_items: int | None, n_hashes: int, percentile: float) -> tuple[list[int], list[int], int, int]:
    """(ids, bins, lower bound, upper bound) by one packer; the order of the ids is the order of placement."""
    rows = list(zip(ids, sets, strict=True))
    rows.sort(key=lambda r: r[0])
    if packer == "size_desc":
        rows.sort(key=lambda r: (-len(r[1]), r[0]))
    elif packer == "sketch":
        rows = [r for _, r in sorted(zip(kernels.signatures([r[1] for r in rows], n_hashes), rows, strict=True), key=lambda x: (x[0], x[1][0]))]
    p = kernels.Problem([r[0] for r in rows], [r[1] for r in rows], capacity, max_items)
    if packer == "exact":
        lower, upper, bins = kernels.exact(p, float("inf"), NODES)
        return p.ids, bins, lower, upper
    if packer == "agglomerative":
        bins = kernels.agglomerate(p, percentile=percentile, n_hashes=n_hashes)
    elif packer == "kmeans":
        bins = kernels.kmeans(p, max_iter=3)
    else:
        bins = kernels.place_greedy(replace(p, overlap=packer != "no_overlap"))
    return p.ids, bins, kernels.lower_bound(p), max(bins, default=0)


def _measured(fn: Callable, *args) -> tuple:
    """Result, seconds and the most bytes of Python objects that fn held."""
    tracemalloc.start()
    began = time.perf_counter()
    out = fn(*args)
    seconds = time.perf_counter() - began
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    return out, seconds, most


def packed_grid(items: DataFrame, grid: list[tuple], timed: bool = True) -> DataFrame:
    """PLACED rows of items (instance, sg_id, vs) in every cell of the grid (tuples of cell()); a group is a cell's bucket of an instance.

    Tracing of memory slows a kernel several times, so seconds and bytes are null unless timed.
    """
    spark = items.sparkSession
    s1 = F.array_min(F.transform("vs", lambda v: (v % minhash.P * minhash.A[0] + minhash.B[0]) % minhash.P))
    rows = cut(items.withColumn("s1", s1), "items")
    # a task a group, those of large instances first: dealt by hash, several would meet in one task
    firsts, last = [], 0
    for r in rows.groupBy("instance").count().orderBy(F.desc("count"), "instance").collect():  # a few dozen rows at most
        for c in grid:
            firsts.append((r["instance"], *c, last))
            last += c[-1]
    table = spark.createDataFrame(firsts, f"of string, {GRID}, first int")
    rows = rows.join(F.broadcast(table), F.col("instance").eqNullSafe(F.col("of"))).withColumn("bucket", F.coalesce("s1", F.lit(0)) % F.col("n_buckets")).drop("s1", "of")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = list(batches)
        t = pa.Table.from_batches(held) if held else None
        if not t:
            return
        one = {c: t.column(c)[0].as_py() for c in ["instance", *CELL, "bucket"]}
        run_it = _measured if timed else lambda fn, *args: (fn(*args), None, None)
        with kernels.uncollected():
            (ids, bins, lower, upper), seconds, most = run_it(place, one["packer"], t.column("sg_id").to_pylist(), [frozenset(x) for x in t.column("vs").to_pylist()], one["capacity"], one["max_items"], one["n_hashes"], one["percentile"])
        n = len(ids)
        types = {"instance": pa.string(), "packer": pa.string(), "capacity": pa.int32(), "max_items": pa.int32(), "n_hashes": pa.int32(), "percentile": pa.float64(), "n_buckets": pa.int32(), "bucket": pa.int64()}
        fixed = {c: pa.array([v] * n, types[c]) for c, v in one.items()}
        out = pa.table(fixed | {"sg_id": pa.array(ids, pa.int64()), "local": pa.array(bins, pa.int64()), "lower": pa.array([lower] * n, pa.int64()), "upper": pa.array([upper] * n, pa.int64()), "seconds": pa.array([seconds] * n, pa.float64()), "bytes": pa.array([most] * n, pa.int64())})
        yield from out.to_batches()

    return rows.repartitionById(max(1, last), (F.col("first") + F.col("bucket")).cast("int")).drop("first").mapInArrow(run, PLACED)


def items_of(members: DataFrame, instance: str | Column = "all") -> DataFrame:
    name = F.lit(instance) if isinstance(instance, str) else instance
    return members.groupBy("sg_id").agg(F.sort_array(F.collect_list("v")).alias("vs")).select(name.alias("instance"), "sg_id", "vs")


def bin_counts(placed: DataFrame) -> DataFrame:
    """(instance, cell, n_sg, n_bins)."""
    per = placed.groupBy("instance", *CELL, "bucket").agg(F.count("*").alias("n"), F.max("local").alias("bins"))
    return per.groupBy("instance", *CELL).agg(F.sum("n").alias("n_sg"), F.sum("bins").alias("n_bins"))


def costs(placed: DataFrame) -> DataFrame:
    """bin_counts with the seconds of all buckets, of the slowest one, and the most bytes of one bucket's packing."""
    per = placed.groupBy("instance", *CELL, "bucket").agg(F.count("*").alias("n"), F.max("local").alias("bins"), F.first("seconds").alias("s"), F.first("bytes").alias("b"))
    return per.groupBy("instance", *CELL).agg(F.sum("n").alias("n_sg"), F.sum("bins").alias("n_bins"), F.sum("s").alias("effort_seconds"), F.max("s").alias("wall_seconds"), F.max("b").alias("peak_bytes"))


# ---------------------------------------------------------------- inputs


def part_graph(spark: SparkSession, d: str, name: str = "returned") -> PropertyGraph:
    """A graph over parts with the part attributes on its vertices."""
    return graphs.with_parts(spark, d, graphs.kept(graphs.GRAPHS[name](spark, d)))


def sized_items(spark: SparkSession, d: str, rules: dict[str, str], k: int = 1) -> DataFrame:
    """Items of the returned graph, an instance for each seed rule."""
    g = part_graph(spark, d)
    return union(items_of(extract.khop_members(g, NeighborhoodSpec(rule, k)), name) for name, rule in rules.items())


RULES = {"few": "p_size > 48", "some": "p_size > 45"}
ORDERS = ("arrival", "size_desc", "sketch")


def orders_by_size(spark: SparkSession, d: str, rules: dict[str, str] = RULES, capacity: int = 90, max_items: int | None = 12, k: int = 1) -> DataFrame:
    """Bins, effort, wall seconds and memory of the three orders as subgraphs grow in number."""
    return costs(packed_grid(sized_items(spark, d, rules, k), [cell(o, capacity, max_items) for o in ORDERS]))


def distribution_by_order(spark: SparkSession, d: str, rules: dict[str, str] = RULES) -> DataFrame:
    """Five numbers of subgraphs per bin for each order."""
    placed = packed_grid(sized_items(spark, d, rules), [cell(o) for o in ORDERS], False)
    n = placed.groupBy("instance", "packer", "local").agg(F.count("*").alias("n"))
    return n.groupBy("instance", "packer").agg(*(F.round(F.expr(f"percentile(n, {q}D)"), 6).alias(name) for q, name in ((0.0, "low"), (0.25, "q1"), (0.5, "median"), (0.75, "q3"), (1.0, "high"))))


def heuristics(spark: SparkSession, d: str, names: tuple[str, ...] = ("returned", "copurchase", "handoff"), seeds: int = 100, capacity: int = 300) -> DataFrame:
    """Signature order, agglomerative, k-means and partition-grow on several graphs, from so many random seeds."""
    out = []
    for name in names:
        g = graphs.kept(graphs.GRAPHS[name](spark, d))
        m = cut(extract.khop_members(g, NeighborhoodSpec(), extract.sample_seeds(g, seeds)), "members")
        out.append(costs(packed_grid(items_of(m, name), [cell(x, capacity, None) for x in ("sketch", "agglomerative", "kmeans")])).select("instance", "packer", "n_sg", "n_bins", "effort_seconds", "peak_bytes"))
        w = m.withColumn("w", F.lit(1).cast("bigint"))
        began = time.perf_counter()
        grown = cut(packing.pack_partition_grow(g, w, 20, PackOptions(capacity, None)), "grown")
        took = time.perf_counter() - began
        out.append(grown.agg(F.count("*").alias("n_sg"), F.countDistinct("bin_id").alias("n_bins")).select(F.lit(name).alias("instance"), F.lit("partition_grow").alias("packer"), "n_sg", "n_bins", F.lit(took).alias("effort_seconds"), F.lit(None).cast("bigint").alias("peak_bytes")))
    return union(out)


def attachment_instances(count: int = 64) -> list[tuple[int, int, int]]:
    """(vertices, edges a vertex, seed) from 100 vertices and 500 edges to 1,000 and nearly 20,000."""
    return [(100 + 900 * (k // 4) // max(1, -(-count // 4) - 1), 5 * (k % 4 + 1), k + 1) for k in range(count)]


def attachment_packers(spark: SparkSession, d: str = "", count: int = 64, packers: tuple[str, ...] = (*ORDERS, "agglomerative", "kmeans", "exact")) -> DataFrame:
    """(n, m, seed, packer, n_bins, lower, upper): every packer on every synthetic graph, an instance and packer a task; exact's bounds are equal where its search ended."""
    grid = spark.createDataFrame([(*i, p) for i in attachment_instances(count) for p in packers], "n bigint, m bigint, seed bigint, packer string")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                near: dict[int, set[int]] = {}
                for a, b in graphs.attachment_edges(r["n"], r["m"], r["seed"]):
                    near.setdefault(a, {a}).add(b)
                    near.setdefault(b, {b}).add(a)
                ids = sorted(near)
                sets = [frozenset(near[v]) for v in ids]
                _, bins, lower, upper = place(r["packer"], ids, sets, int(1.5 * max(map(len, sets))), None, 6, 10.0)
                yield pa.RecordBatch.from_pylist([r | {"n_bins": max(bins), "lower": lower, "upper": upper}])

    return grid.repartition(len(grid.collect()), "n", "m", "seed", "packer").mapInArrow(run, "n bigint, m bigint, seed bigint, packer string, n_bins bigint, lower bigint, upper bigint")


def gaps(instances: DataFrame) -> DataFrame:
    """(packer, n, solved, mean_gap, worst_gap): bins over the best known of each instance; solved counts proven optima met."""
    key = ["n", "m", "seed"]
    best = instances.groupBy(*key).agg(F.min("n_bins").alias("best"), F.max("lower").alias("bound"))
    rows = instances.join(best, key)
    return rows.groupBy("packer").agg(F.count("*").alias("instances"), F.sum((F.col("n_bins") == F.col("bound")).cast("bigint")).alias("at_bound"), F.sum((F.col("n_bins") == F.col("best")).cast("bigint")).alias("best_known"), F.round(F.avg(F.col("n_bins") / F.col("best")), 6).alias("mean_gap"), F.round(F.max(F.col("n_bins") / F.col("best")), 6).alias("worst_gap"))


def planning_buckets(spark: SparkSession, d: str, buckets: tuple[int, ...] = (1, 2, 4, 6, 8, 16), rules: dict[str, str] = RULES) -> DataFrame:
    """Central (one bucket) and distributed planning: bins, effort, slowest bucket and its memory by buckets and number of subgraphs."""
    return costs(packed_grid(sized_items(spark, d, rules), [cell("sketch", n_buckets=b) for b in buckets]))


def central_or_distributed(spark: SparkSession, d: str, machines: int = 6) -> DataFrame:
    """planning_buckets with one and with so many buckets, with the strategy that the rule on sizes would take."""
    g = part_graph(spark, d)
    return planning_buckets(spark, d, (1, machines)).withColumn("rule", F.lit(extract.choose_strategy(g, NeighborhoodSpec(RULES["some"]))))


def hash_and_threshold_sweeps(spark: SparkSession, d: str) -> DataFrame:
    """Bins by the number of hashes (signature order) and by the threshold's percentile (agglomerative)."""
    grid = [cell("sketch", n_hashes=n) for n in (1, 2, 4, 6, 8)] + [cell("agglomerative", percentile=p) for p in (5.0, 10.0, 20.0, 30.0)]
    return bin_counts(packed_grid(sized_items(spark, d, {"some": RULES["some"]}), grid, False))


def item_caps(spark: SparkSession, d: str, caps: tuple[int | None, ...] = (None, 64, 16)) -> DataFrame:
    """Bins and balance by the cap on items, on the supplier-part graph with random seeds on both sides (hubs and small vertices)."""
    g = graphs.kept(graphs.supplier_part(spark, d))
    m = extract.khop_members(g, NeighborhoodSpec(), extract.sample_seeds(g, 100))
    placed = packed_grid(items_of(m, "supplier_part"), [cell("sketch", 600, c) for c in caps])
    n = placed.groupBy("max_items", "local").agg(F.count("*").alias("n"))
    return n.groupBy("max_items").agg(F.count("*").alias("n_bins"), F.max("n").alias("most_items"), F.round(F.max("n") / F.avg("n"), 6).alias("imbalance"))


# ---------------------------------------------------------------- engine and models

APPS = ("lcc", "feed_forward", "triangles", "weak_ties", "ppr")


def app_by_model(app: str, model: str, g: PropertyGraph, seed_ids: DataFrame) -> DataFrame:
    """One application under one execution model: engine, relational, bsp, gas or triplet."""
    if app == "ppr":
        if model in ("engine", "relational"):
            m = cut(extract.khop_members(g, NeighborhoodSpec(k=2), seed_ids), "members")
            if model == "relational":
                return relational.ppr(m, extract.induced_edges(m, g), g.directed)
            return _engine(g, m, programs.ppr(), 2000)
        return {"bsp": baselines.gathered_ppr, "gas": baselines.gas_ppr, "triplet": baselines.triplet_ppr}[model](g, seed_ids)
    if app == "feed_forward":
        if model == "engine":
            return _engine(g, cut(extract.khop_members(g, NeighborhoodSpec(direction="out")), "members"), programs.motif("feed_forward"), 2000)
        if model == "relational":
            return relational.feed_forward(g)
        return {"bsp": baselines.bsp_motif, "gas": baselines.gas_motif, "triplet": baselines.triplet_motif}[model](g, "feed_forward")
    if model == "engine":
        return _engine(g, cut(extract.khop_members(g, NeighborhoodSpec(direction="both")), "members"), {"lcc": programs.lcc, "triangles": programs.triangles, "weak_ties": programs.weak_ties}[app](), 2000)
    links = {"relational": relational.links, "bsp": baselines.bsp_links, "gas": baselines.gas_links, "triplet": baselines.triplet_links}[model](g)
    return of_links(app, links)


def of_links(app: str, links: DataFrame) -> DataFrame:
    """Clustering, triangles or weak ties from neighbour links."""
    if app == "lcc":
        return relational.with_lcc(links)
    n = F.col("links") if app == "triangles" else F.expr("degree * (degree - 1) div 2") - F.col("links")
    return links.select("sg_id", n.alias("n"))


def _engine(g: PropertyGraph, members: DataFrame, program: engine.Program, capacity: int, options: ExecOptions = ExecOptions(), buckets: int = 8) -> DataFrame:
    weighted = members.withColumn("w", F.lit(1).cast("bigint"))
    assignment = cut(packing.numbered(packing.pack(weighted, PackOptions(capacity, None, n_buckets=buckets))), "assignment")
    return engine.run(g, weighted, assignment, program, options)


def model_grid(spark: SparkSession, d: str, app: str, names: tuple[str, ...], models: tuple[str, ...] = ("engine", "bsp", "gas", "triplet")) -> DataFrame:
    """A block of the raw comparison: rows out, node-seconds, wall seconds, shuffled records and bytes and peak execution memory of each model on each graph; a model that fails has a label and nulls."""
    out = []
    for name in names:
        g = graphs.kept(graphs.GRAPHS[name](spark, d))
        seed_ids = cut(extract.sample_seeds(g, max(1, g.vertices.count() // 100)), "seeds")
        for model in models:
            got = metrics.measured(spark, lambda a=app, m=model, g=g, s=seed_ids: app_by_model(a, m, g, s).agg(F.count("*").alias("n")).head().n)
            out.append((app, name, model, got["status"], got["result"], got["node_seconds"], got["seconds"], got["shuffle_records"], got["shuffle_bytes"], got["peak_bytes"]))
    return spark.createDataFrame(out, "app string, graph string, model string, status string, n bigint, node_seconds double, wall_seconds double, shuffle_records bigint, shuffle_bytes bigint, peak_bytes bigint")


#: The blocks of the raw comparison and the graphs of ours that each runs on.
BLOCKS = {"lcc": ("returned", "handoff"), "feed_forward": ("next_line", "handoff"), "triangles": ("returned",), "weak_ties": ("returned", "supplier_part"), "ppr": ("returned",)}


def improvement(blocks: DataFrame, measure: str = "node_seconds") -> DataFrame:
    """(app, graph, model, factor): another model over the engine; null where it failed."""
    ours = blocks.where("model = 'engine'").select("app", "graph", F.col(measure).alias("ours"))
    others = blocks.where("model <> 'engine'").select("app", "graph", "model", F.when(F.col("status") == "ok", F.col(measure)).alias("other"))
    return metrics.ratios(others.join(ours, ["app", "graph"]), "ours", "other").select("app", "graph", "model", "factor")


def all_blocks(spark: SparkSession, d: str) -> DataFrame:
    return union(model_grid(spark, d, app, names) for app, names in BLOCKS.items())


def modes_and_bitmaps(spark: SparkSession, d: str, capacities: tuple[int, ...] = (300, 2000), name: str = "returned") -> DataFrame:
    """Vector mode under each bitmap class and single-bit mode, as bins grow fewer: bins, bitmap bytes and node-seconds.

    All modes run on bins that are loaded once a capacity; each row's seconds are those of that load and of its own run.
    """
    g = graphs.kept(graphs.GRAPHS[name](spark, d))
    m = cut(extract.khop_members(g, NeighborhoodSpec()).withColumn("w", F.lit(1).cast("bigint")), "members")
    out = []
    for capacity in capacities:
        a = cut(packing.numbered(packing.pack(m, PackOptions(capacity, None, n_buckets=4))), "assignment")
        n_bins = a.agg(F.countDistinct("bin_id").alias("n")).head().n
        held = bitmap_bytes(m, a)
        loaded = metrics.measured(spark, lambda a=a: [cut(x, "bin") for x in engine.materialize_bins(g, m, a)])
        for mode, bitmap in (*(("vector", k) for k in bitmaps.CLASSES), ("single", "words")):
            got = metrics.measured(spark, lambda o=ExecOptions(mode, bitmap=bitmap), x=loaded["result"]: engine.run_loaded(*x, g.directed, programs.lcc(), o).agg(F.count("*").alias("n")).head().n)
            seconds = [None if got[c] is None else loaded[c] + got[c] for c in ("node_seconds", "seconds")]
            out.append((capacity, n_bins, mode, bitmap, held[bitmap] if mode == "vector" else n_bins, got["result"], *seconds))
        for x in loaded["result"] or ():
            let_go(x)
    return spark.createDataFrame(out, "capacity int, n_bins bigint, mode string, bitmap string, bitmap_bytes bigint, n bigint, node_seconds double, wall_seconds double")


def bitmap_bytes(members: DataFrame, assignment: DataFrame) -> dict[str, int]:
    """Bytes of all bins' bitmaps by the model of each class: words of 8 bytes over the bin's slots for every vertex, or a header and 4 bytes a set bit."""
    rows = members.join(assignment.select("sg_id", "bin_id"), "sg_id")
    width = assignment.groupBy("bin_id").agg(F.ceil(F.count("*") / 64).alias("words"))
    per = rows.groupBy("bin_id", "v").agg(F.count("*").alias("set")).join(width, "bin_id")
    model = {"words": 8 * F.col("words"), "growable": 8 * F.col("words") + 16, "sparse": 134 + 4 * F.col("set")}
    got = per.agg(*(F.sum(model[k]).alias(k) for k in bitmaps.CLASSES)).head()
    return {k: got[k] or 0 for k in bitmaps.CLASSES}


def batch_sizes(spark: SparkSession, d: str, sizes: tuple[int, ...] = (8, 64, 512, 4096), name: str = "returned") -> DataFrame:
    """Batched mode by batch size: bytes of a batch's words in the widest bin, and node-seconds."""
    g = graphs.kept(graphs.GRAPHS[name](spark, d))
    m = cut(extract.khop_members(g, NeighborhoodSpec()).withColumn("w", F.lit(1).cast("bigint")), "members")
    a = cut(packing.numbered(packing.pack(m, PackOptions(2000, None, n_buckets=4))), "assignment")
    widest = packing.bins(m, a).agg(F.max(F.struct("n_vertices", "n_sg")).alias("b")).head().b
    out = []
    for size in sizes:
        got = metrics.measured(spark, lambda o=ExecOptions("batched", size): engine.run(g, m, a, programs.lcc(), o).agg(F.count("*").alias("n")).head().n)
        out.append((size, widest.n_vertices * 8 * -(-min(size, widest.n_sg) // 64), got["result"], got["node_seconds"], got["seconds"]))
    return spark.createDataFrame(out, "batch_size int, bitmap_bytes bigint, n bigint, node_seconds double, wall_seconds double")


def stages(spark: SparkSession, d: str, app: str = "lcc", name: str = "returned", share: float = 1.0, capacity: int = 2000) -> DataFrame:
    """(stage, node_seconds, wall_seconds, share) of extraction and packing, loading and execution, with n subgraphs and bins; share is that of the vertices that are (random) seeds."""
    g = graphs.kept(graphs.GRAPHS[name](spark, d))
    start = extract.sample_seeds(g, int(share * g.vertices.count())) if share < 1 else None
    held: dict = {}

    def extract_and_pack() -> int:
        held["m"] = cut(extract.khop_members(g, NeighborhoodSpec(direction="out" if g.directed else "both"), start).withColumn("w", F.lit(1).cast("bigint")), "members")
        held["a"] = cut(packing.numbered(packing.pack(held["m"], PackOptions(capacity, None, n_buckets=4))), "assignment")
        return held["a"].count()

    def load() -> int:
        held["rows"], held["edges"] = (cut(x, "bin") for x in engine.materialize_bins(g, held["m"], held["a"]))
        return held["edges"].count()

    program = programs.motif("feed_forward") if app == "feed_forward" else programs.lcc()
    steps = [("extract and pack", extract_and_pack), ("load", load), ("execute", lambda: engine.run_loaded(held["rows"], held["edges"], g.directed, program).agg(F.count("*").alias("n")).head().n)]
    rows = [(stage, metrics.measured(spark, fn)) for stage, fn in steps]
    total = sum(r["node_seconds"] or 0 for _, r in rows) or 1.0
    n_bins = held["a"].agg(F.countDistinct("bin_id").alias("n")).head().n
    return spark.createDataFrame([(app, name, stage, rows[0][1]["result"], n_bins, r["node_seconds"], r["seconds"], (r["node_seconds"] or 0) / total) for stage, r in rows], "app string, graph string, stage string, n_sg bigint, n_bins bigint, node_seconds double, wall_seconds double, share double")


def end_to_end(spark: SparkSession, d: str, shares: tuple[float, ...] = (0.1, 0.5, 1.0), capacity: int = 2000) -> DataFrame:
    """Clustering from extraction to result with a fixed capacity, as subgraphs grow in number."""
    return union(stages(spark, d, share=share, capacity=capacity).withColumn("seeds", F.lit(share)) for share in shares).groupBy("seeds").agg(F.max("n_sg").alias("n_sg"), F.max("n_bins").alias("n_bins"), F.sum("node_seconds").alias("node_seconds"), F.sum("wall_seconds").alias("wall_seconds"))


def large_graph(spark: SparkSession, d: str) -> DataFrame:
    """Motif counting on the largest directed graph, through bins: memberships, effort and peak memory."""
    return stages(spark, d, "feed_forward", "next_line")


def superstep_times(spark: SparkSession, d: str, bins: tuple[int, ...] = (5, 10), name: str = "returned") -> DataFrame:
    """(n_bins, round, changed, ghost_rows, compute_s, barrier_s, message_s) of components over hash bins."""
    g = graphs.kept(graphs.GRAPHS[name](spark, d))
    out = []
    for n in bins:
        own = packing.pack_hash(g.vertices.select(F.col("id").alias("sg_id")), n).toDF("v", "bin_id")
        out += [(n, *row) for row in iterate.components(g, own)[2]]
    return spark.createDataFrame(out, "n_bins int, round int, changed bigint, ghost_rows bigint, compute_s double, barrier_s double, message_s double")


def components_by_model(spark: SparkSession, d: str, name: str = "returned_same_kind") -> DataFrame:
    """Components in bins and in the three other models: distinct components, node-seconds, wall seconds."""
    g = graphs.kept(graphs.GRAPHS[name](spark, d))
    own = packing.pack_hash(g.vertices.select(F.col("id").alias("sg_id")), 10).toDF("v", "bin_id")
    forms = {"engine": lambda: iterate.components(g, own)[0], "bsp": lambda: baselines.message_components(g)[0], "gas": lambda: baselines.gas_components(g), "triplet": lambda: baselines.triplet_components(g)}
    rows = [(model, metrics.measured(spark, lambda f=f: f().agg(F.countDistinct("component").alias("n")).head().n)) for model, f in forms.items()]
    return spark.createDataFrame([(m, r["result"], r["node_seconds"], r["seconds"]) for m, r in rows], "model string, n_components bigint, node_seconds double, wall_seconds double")


def sampled_clustering(spark: SparkSession, d: str, names: tuple[str, ...] = ("returned", "copurchase"), ratios: tuple[float, ...] = (0.2, 0.4, 0.6, 0.8), runs: int = 10) -> DataFrame:
    """Mean and spread of sampled clustering by ratio, by node samples and by walks, on several graphs."""
    out = []
    for name in names:
        g = part_graph(spark, d, name)
        m = cut(extract.khop_members(g, NeighborhoodSpec("p_size > 48")), "members")
        links = sampling.links_of(g, m)
        out.append(sampling.lcc_study(g, m, list(ratios), runs, links).select(F.lit(name).alias("graph"), F.lit("node").alias("sampler"), "*"))
        out.append(sampling.walk_lcc_study(g, m, list(ratios), runs, links).select(F.lit(name).alias("graph"), F.lit("walk").alias("sampler"), "*"))
    return union(out)


def dataset_table(spark: SparkSession, d: str, names: tuple[str, ...] = ("returned", "copurchase", "handoff", "supplier_part", "returned_same_kind")) -> DataFrame:
    """The table of data: vertices, edges, mean degree, mean clustering, triangles and diameter of each graph."""
    rows = []
    for name in names:
        und = graphs.kept(from_edges(graphs.GRAPHS[name](spark, d).arcs("both").where("src < dst")))
        row = metrics.dataset_stats(und).join(metrics.diameter(und)).select(F.lit(name).alias("graph"), "n_vertices", "n_edges", "mean_degree", "mean_lcc", "n_triangles", "diameter")  # one row each
        rows.append(cut(row, "stats"))
        let_go(und.edges)
    return union(rows)


def cut_curve(spark: SparkSession, d: str, parts: tuple[int, ...] = (2, 4, 8, 16), grown: bool = False) -> DataFrame:
    """(n_parts, n_cut, largest): edges between disjoint parts as the parts grow in number."""
    g = graphs.kept(graphs.returned(spark, d))
    return union(packing.cut_edges(g, (packing.grow_parts if grown else packing.balanced_parts)(g, n)) for n in parts)
