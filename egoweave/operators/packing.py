"""Packing plans over DataFrames: order, bucket, run a kernel per bucket, merge leftovers, place, audit."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import replace

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import minhash
from ..graph import PropertyGraph
from ..session import cut
from ..spec import PackOptions
from . import kernels, sampling

#: Members that one packing task may hold, and under-filled bins that one merging task may.
TASK_MEMBERS, TASK_BINS = 5_000_000, 4096
PLACED = "bucket bigint, sg_id bigint, local bigint, slot int, oversized boolean"


def ordered(members: DataFrame, opts: PackOptions) -> DataFrame:
    """(sg_id, vs, ws, bucket, key) of every subgraph: its set, where it goes and a sortable array key for the chosen order, in one aggregate."""
    names = minhash.names(opts.n_hashes)
    key = {"arrival": F.array("sg_id"), "size_desc": F.array(-F.col("load"), F.col("sg_id")), "sketch": F.array(*names, "sg_id")}.get(opts.order)
    if key is None:
        raise ValueError(f"unknown order {opts.order!r}")
    signature = (F.min(minhash.hashed(i)).alias(x) for i, x in enumerate(names))
    items = members.groupBy("sg_id").agg(F.collect_list("v").alias("vs"), F.collect_list("w").alias("ws"), F.sum("w").alias("load"), *signature)
    n = opts.n_buckets or max(1, -(-members.count() // TASK_MEMBERS))
    if n == 1:
        items = items.withColumn("bucket", F.lit(0).cast("bigint"))
    elif opts.seed >= 0:
        items = minhash.bucket_by_hash(items, n, opts.key_hashes)
    else:
        items = minhash.bucket_by_range(items, n)
    return items.withColumn("key", key).drop("load", *names)


def _kernel(opts: PackOptions, params: dict):
    def run(t: pa.Table) -> pa.Table:
        rows = sorted(zip(t.column("key").to_pylist(), t.column("sg_id").to_pylist(), t.column("vs").to_pylist(), t.column("ws").to_pylist(), strict=True), key=lambda r: r[0])
        weights: dict[int, int] = {}
        if opts.weight_model != "unit":
            for _, _, vs, ws in rows:
                weights.update(zip(vs, ws, strict=True))
        p = kernels.Problem([r[1] for r in rows], [frozenset(r[2]) for r in rows], opts.capacity, opts.max_items, weights, opts.overlap)
        with kernels.uncollected():
            found = kernels.exact(p, **params) if opts.algorithm == "exact" else None
            bins = found[2] if found else {"greedy": kernels.place_greedy, "agglomerative": lambda p: kernels.agglomerate(p, **params), "kmeans": lambda p: kernels.kmeans(p, **params)}[opts.algorithm](p)
        slots: dict[int, int] = {}
        slot = []
        for b in bins:
            slot.append(slots.get(b, 0))
            slots[b] = slots.get(b, 0) + 1
        bucket = t.column("bucket")[0].as_py()
        n = len(bins)
        bounds = {"lower": pa.array([found[0]] * n, pa.int64()), "upper": pa.array([found[1]] * n, pa.int64())} if found else {}
        return pa.table({"bucket": pa.array([bucket] * n, pa.int64()), "sg_id": pa.array(p.ids, pa.int64()), "local": pa.array(bins, pa.int64()), "slot": pa.array(slot, pa.int32()), "oversized": pa.array([p.weight(s) > opts.capacity for s in p.sets], pa.bool_())} | bounds)

    return run


def pack(members: DataFrame, opts: PackOptions, **params) -> DataFrame:
    """PLACED rows of weighted members (sg_id, v, w); exact adds lower and upper, the bounds of its bucket's bins, which are equal where the search ended.

    One bucket gives the sequential result of a single machine; several pack buckets of similar
    signature in parallel, which is the form for large inputs: no task holds more than its bucket. Subgraphs over the capacity
    get a bin each (oversized="solo"), are cut down to a sample that fits ("sample"), or are refused ("error").
    """
    if opts.oversized == "sample":
        members = cut(sampling.fit(members, opts.capacity), "sampled")
    elif opts.oversized == "error":
        over = members.groupBy("sg_id").agg(F.sum("w").alias("w")).where(F.col("w") > opts.capacity).limit(1).count()
        if over:
            raise ValueError("a subgraph is larger than the capacity")
    opts = replace(opts, n_buckets=opts.n_buckets or max(1, -(-members.count() // TASK_MEMBERS)))
    kernel = _kernel(opts, params)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = list(batches)
        if held:
            yield from kernel(pa.Table.from_batches(held)).to_batches()

    # a task a bucket: dealt by hash, several would meet in one task
    return ordered(members, opts).repartitionById(opts.n_buckets, F.col("bucket").cast("int")).mapInArrow(run, PLACED + (", lower bigint, upper bigint" if opts.algorithm == "exact" else ""))


def numbered(placed: DataFrame) -> DataFrame:
    """(sg_id, bin_id, and slot, oversized and bounds where there are any) with bins numbered through over buckets."""
    placed = cut(placed, "placed")  # two readers follow, and packing is not to run twice
    bases = placed.groupBy("bucket").agg(F.max("local").alias("n")).withColumn("base", F.sum("n").over(Window.orderBy("bucket")) - F.col("n"))  # one row a bucket
    return placed.join(F.broadcast(bases.select("bucket", "base")), "bucket").select("sg_id", (F.col("base") + F.col("local")).alias("bin_id"), *(c for c in ("slot", "oversized", "lower", "upper") if c in placed.columns))


def bin_vertices(members: DataFrame, assignment: DataFrame) -> DataFrame:
    """(bin_id, v, w) of the unions."""
    return members.join(assignment.select("sg_id", "bin_id"), "sg_id").select("bin_id", "v", "w").distinct()


def bins(members: DataFrame, assignment: DataFrame) -> DataFrame:
    """(bin_id, load, n_sg, n_vertices)."""
    load = bin_vertices(members, assignment).groupBy("bin_id").agg(F.sum("w").alias("load"), F.count("*").alias("n_vertices"))
    return load.join(assignment.groupBy("bin_id").agg(F.count("*").alias("n_sg")), "bin_id").select("bin_id", "load", "n_sg", "n_vertices")


def merge_underfilled(members: DataFrame, assignment: DataFrame, opts: PackOptions) -> DataFrame:
    """(sg_id, bin_id) after bins under merge_fill of the capacity are placed again as wholes, in signature order of their unions.

    More than TASK_BINS of them are dealt to tasks by ranges of their signature, round by round, until one task can take
    what is left or a round merges under a tenth of them.
    """
    assignment = assignment.select("sg_id", "bin_id")
    while True:
        load = bins(members, assignment)
        low = cut(load.where(F.col("load") < opts.merge_fill * opts.capacity).select("bin_id", "n_sg"), "low")
        n = low.count()
        moved = cut(_merged(members, assignment, low, opts, -(-n // TASK_BINS)), "moved")
        assignment = assignment.join(moved, assignment.bin_id == moved.old, "left").select("sg_id", F.coalesce("new", "bin_id").alias("bin_id"))
        if n <= TASK_BINS or moved.where("old <> new").count() * 10 < n:
            return assignment
        assignment = cut(assignment, "assignment")


def _merged(members: DataFrame, assignment: DataFrame, low: DataFrame, opts: PackOptions, groups: int) -> DataFrame:
    unions = bin_vertices(members, assignment).join(low, "bin_id")
    items = unions.groupBy(F.col("bin_id").alias("sg_id")).agg(F.collect_list("v").alias("vs"), F.collect_list("w").alias("ws"), F.first("n_sg").alias("n"))
    keys = minhash.sketch(unions.select(F.col("bin_id").alias("sg_id"), "v"), opts.n_hashes)
    keys = minhash.bucket_by_range(keys, groups).select("sg_id", "bucket", F.array(*minhash.names(opts.n_hashes), "sg_id").alias("key"))

    def run(t: pa.Table) -> pa.Table:
        rows = sorted(zip(t.column("key").to_pylist(), t.column("sg_id").to_pylist(), t.column("vs").to_pylist(), t.column("ws").to_pylist(), t.column("n").to_pylist(), strict=True), key=lambda r: r[0])
        weights = {v: w for r in rows for v, w in zip(r[2], r[3], strict=True)}
        p = kernels.Problem([r[1] for r in rows], [frozenset(r[2]) for r in rows], opts.capacity, opts.max_items, weights)
        placed = kernels.place_greedy(p, [r[4] for r in rows])
        first: dict[int, int] = {}
        for b, i in zip(placed, p.ids, strict=True):
            first.setdefault(b, i)
        return pa.table({"old": pa.array(p.ids, pa.int64()), "new": pa.array([first[b] for b in placed], pa.int64())})

    return items.join(keys, "sg_id").groupBy("bucket").applyInArrow(run, "old bigint, new bigint")


def placement(members: DataFrame, assignment: DataFrame) -> DataFrame:
    """(bin_id, v, owned): a vertex is owned where its own subgraph lies."""
    rows = members.join(assignment.select("sg_id", "bin_id"), "sg_id")
    return rows.groupBy("bin_id", "v").agg(F.max(F.col("sg_id") == F.col("v")).alias("owned"))


def audit(members: DataFrame, assignment: DataFrame, capacity: int, max_items: int | None = None) -> DataFrame:
    """(rule, violations): every subgraph in one bin, unions in bounds unless a single subgraph is over, item cap, one owner a vertex."""
    ids = members.select("sg_id").distinct()
    per = assignment.groupBy("sg_id").agg(F.countDistinct("bin_id").alias("n"))
    b = bins(members, assignment)
    owners = placement(members, assignment).where("owned").groupBy("v").agg(F.count("*").alias("n"))
    one = lambda df, rule: df.agg(F.count("*").alias("violations")).select(F.lit(rule).alias("rule"), "violations")
    out = one(ids.join(per, "sg_id", "left").where("n is null or n <> 1"), "subgraph in one bin")
    out = out.unionAll(one(b.where((F.col("load") > capacity) & (F.col("n_sg") > 1)), "bin within capacity"))
    out = out.unionAll(one(b.where(F.col("n_sg") > (max_items or 1 << 60)), "items within cap"))
    return out.unionAll(one(owners.where("n > 1"), "one owner"))


def capacity_from_conf(executor_bytes: int, fraction: float = 0.5, tasks: int = 4) -> int:
    """Bytes a bin may take: a share of an executor's memory for each of its concurrent tasks."""
    return int(executor_bytes * fraction / max(1, tasks))


def merge_round(members: DataFrame, capacity: int, window: int, threshold: float) -> DataFrame:
    """(first, joined): one left-to-right pass of the agglomerative packer in signature order, in one task."""

    def run(t: pa.Table) -> pa.Table:
        p = kernels.Problem(t.column("sg_id").to_pylist(), [frozenset(x) for x in t.column("vs").to_pylist()], capacity)
        start = sorted((kernels.Cluster([i], s, kernels.signature(s)) for i, s in enumerate(p.sets)), key=lambda c: (c.sign, p.ids[c.items[0]]))
        merged = [c.items for c in kernels.merge_pass(p, start, window, threshold)[0] if len(c.items) > 1]
        return pa.table({"first": pa.array([p.ids[a] for a, _ in merged], pa.int64()), "joined": pa.array([p.ids[b] for _, b in merged], pa.int64())})

    return members.groupBy("sg_id").agg(F.collect_list("v").alias("vs")).withColumn("g", F.lit(0)).groupBy("g").applyInArrow(run, "first bigint, joined bigint")


def kmeans_starts(members: DataFrame, capacity: int) -> DataFrame:
    """(sg_id, cluster): the k subgraphs of smallest hash, k being the summed sizes over the capacity."""
    k = max(1, -(-members.count() // capacity))
    first = members.select("sg_id").distinct().withColumn("h", minhash.hashed(0, "sg_id")).orderBy("h", "sg_id").limit(k)
    return first.select("sg_id", (F.row_number().over(Window.orderBy("h", "sg_id")) - 1).cast("bigint").alias("cluster"))  # k rows


def pack_hash(assignees: DataFrame, n_bins: int) -> DataFrame:
    """(sg_id, bin_id) without packing: seeds dealt by their hash."""
    return assignees.select("sg_id", (minhash.hashed(0, "sg_id") % n_bins + 1).alias("bin_id"))


def balanced_parts(g: PropertyGraph, n_parts: int, rounds: int = 4) -> DataFrame:
    """(v, part): disjoint parts. Heavy-edge matching rounds collapse neighbours, then groups are dealt in snake order of size.

    Each round is a join and an aggregate; groups stop growing beyond n / n_parts.
    """
    group = cut(g.vertices.select(F.col("id").alias("v"), F.col("id").alias("grp")), "groups")
    arcs = cut(g.arcs("both"), "arcs")
    n = group.count()
    most = max(1, -(-n // n_parts))
    for _ in range(rounds):
        size = group.groupBy("grp").agg(F.count("*").alias("n"))
        ends = arcs.join(group.toDF("src", "a"), "src").join(group.toDF("dst", "b"), "dst").where("a <> b")
        heavy = ends.groupBy("a", "b").agg(F.count("*").alias("w")).join(size.toDF("a", "na"), "a").join(size.toDF("b", "nb"), "b").where(F.col("na") + F.col("nb") <= most)
        pick = heavy.groupBy("a").agg(F.max_by("b", F.struct("w", -F.col("b"))).alias("b"))
        mutual = pick.alias("x").join(pick.alias("y"), (F.col("x.b") == F.col("y.a")) & (F.col("x.a") == F.col("y.b"))).where("x.a < x.b").select(F.col("x.b").alias("grp"), F.col("x.a").alias("to"))
        group = group.join(mutual, "grp", "left").select("v", F.coalesce("to", "grp").alias("grp"))
        group = cut(group, "groups")
    # groups in falling order of size: a base for each size and bucket, then a rank within, so no task ranks them all
    size = group.groupBy("grp").agg(F.count("*").alias("n")).withColumn("bucket", F.pmod(F.xxhash64("grp"), F.lit(64)))
    per = size.groupBy("n", "bucket").agg(F.count("*").alias("k"))
    before = F.sum(F.col("n") * F.col("k")).over(Window.orderBy(F.desc("n"), "bucket").rowsBetween(Window.unboundedPreceding, -1))
    base = per.select("n", "bucket", F.coalesce(before, F.lit(0)).alias("base"))  # 64 rows for each size at most, and sizes end at n / n_parts
    rank = F.row_number().over(Window.partitionBy("n", "bucket").orderBy("grp")) - 1
    dealt = size.withColumn("r", rank).join(base, ["n", "bucket"]).withColumn("part", F.least(F.lit(n_parts - 1), F.floor((F.col("base") + F.col("r") * F.col("n")) / most)).cast("bigint"))
    return group.join(dealt.select("grp", "part"), "grp").select("v", "part")


def grow_parts(g: PropertyGraph, n_parts: int, rounds: int = 64) -> DataFrame:
    """(v, part): disjoint parts grown directly from n_parts start vertices, a hop a round; a vertex reached by several joins the smallest part.

    A part takes no more than its share of the vertices; what no part reaches, or has room for, is dealt by hash. The
    alternative to collapsing neighbours, as that makes parts of any graph without a matching.
    """
    ids, arcs = cut(g.vertices.select("id"), "ids"), cut(g.arcs("both"), "arcs")
    n = ids.count()
    most = max(1, -(-n // n_parts))
    order = minhash.hashed(0, "id")
    start = ids.select("id", order.alias("h")).orderBy("h", "id").limit(n_parts)
    held = cut(start.select(F.col("id").alias("v"), (F.row_number().over(Window.orderBy("h", "id")) - 1).cast("bigint").alias("part")), "parts")  # n_parts rows
    for _ in range(rounds):
        room = held.groupBy("part").agg((F.lit(most) - F.count("*")).alias("room")).where("room > 0")
        reach = held.join(F.broadcast(room), "part").join(arcs, F.col("v") == F.col("src")).select(F.col("dst").alias("v"), "part", "room")
        fresh = reach.join(held.select("v"), "v", "left_anti").groupBy("v").agg(F.min(F.struct("part", "room")).alias("p")).select("v", "p.*")
        within = F.row_number().over(Window.partitionBy("part").orderBy("v"))
        fresh = cut(fresh.withColumn("r", within).where("r <= room").select("v", "part"), "fresh")
        if not fresh.limit(1).count():
            break
        held = cut(held.unionAll(fresh), "parts")
    rest = ids.select(F.col("id").alias("v")).join(held.select("v"), "v", "left_anti")
    return held.unionAll(rest.select("v", (minhash.hashed(1, "v") % n_parts).alias("part")))


def cut_edges(g: PropertyGraph, parts: DataFrame) -> DataFrame:
    """(n_parts, n_cut, largest): edges between parts, and the vertices of the largest."""
    ends = g.edges.join(parts.toDF("src", "a"), "src").join(parts.toDF("dst", "b"), "dst")
    size = parts.groupBy("part").agg(F.count("*").alias("n")).agg(F.count("*").alias("n_parts"), F.max("n").alias("largest"))
    return size.join(ends.agg(F.coalesce(F.sum((F.col("a") != F.col("b")).cast("bigint")), F.lit(0)).alias("n_cut"))).select("n_parts", "n_cut", "largest")  # one row each


def pack_partition_grow(g: PropertyGraph, members: DataFrame, n_parts: int, opts: PackOptions, parts: DataFrame | None = None) -> DataFrame:
    """(sg_id, bin_id): disjoint parts grown by the subgraphs of their seeds, placed in signature order; a grown part over the bounds falls back to its subgraphs."""
    parts = balanced_parts(g, n_parts) if parts is None else parts
    owner = members.select("sg_id").distinct().join(parts, F.col("sg_id") == F.col("v")).select("sg_id", "part")
    rows = members.join(owner, "sg_id")
    size = rows.select("part", "v", "w").distinct().groupBy("part").agg(F.sum("w").alias("load")).join(owner.groupBy("part").agg(F.count("*").alias("n")), "part")
    fits = size.select("part", ((F.col("load") <= opts.capacity) & (F.col("n") <= (opts.max_items or 1 << 60))).alias("fits"))
    whole = owner.join(fits, "part").select("sg_id", F.when(F.col("fits"), -1 - F.col("part")).otherwise(F.col("sg_id")).alias("item"))
    grouped = members.join(whole, "sg_id")
    items = grouped.select(F.col("item").alias("sg_id"), "v", "w").distinct()
    counts = whole.groupBy("item").agg(F.count("*").alias("n"))
    packed = pack_counted(items, counts, opts)
    return whole.join(packed, whole.item == packed.sg_id).select(whole.sg_id, "bin_id")


def pack_counted(members: DataFrame, counts: DataFrame, opts: PackOptions) -> DataFrame:
    """(sg_id, bin_id) of items that stand for several subgraphs each."""
    rows = ordered(members, opts).join(counts.withColumnRenamed("item", "sg_id"), "sg_id")

    def run(t: pa.Table) -> pa.Table:
        got = sorted(zip(t.column("key").to_pylist(), t.column("sg_id").to_pylist(), t.column("vs").to_pylist(), t.column("ws").to_pylist(), t.column("n").to_pylist(), strict=True), key=lambda r: r[0])
        weights = {v: w for r in got for v, w in zip(r[2], r[3], strict=True)}
        p = kernels.Problem([r[1] for r in got], [frozenset(r[2]) for r in got], opts.capacity, opts.max_items, weights)
        return pa.table({"bucket": t.column("bucket"), "sg_id": pa.array(p.ids, pa.int64()), "local": pa.array(kernels.place_greedy(p, [r[4] for r in got]), pa.int64())})

    return numbered(rows.groupBy("bucket").applyInArrow(run, "bucket bigint, sg_id bigint, local bigint"))
