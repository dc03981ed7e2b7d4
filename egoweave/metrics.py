"""Cost measures over plans and runs."""

from __future__ import annotations

import contextlib
import time
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .graph import PropertyGraph
from .operators import closing, packing
from .session import cut


def bin_count(assignment: DataFrame) -> DataFrame:
    return assignment.agg(F.countDistinct("bin_id").alias("n_bins"))


def bin_distribution(assignment: DataFrame) -> DataFrame:
    """Five numbers of subgraphs per bin."""
    n = assignment.groupBy("bin_id").agg(F.count("*").alias("n"))
    return n.agg(*(F.round(F.expr(f"percentile(n, {q}D)"), 6).alias(name) for q, name in ((0.0, "low"), (0.25, "q1"), (0.5, "median"), (0.75, "q3"), (1.0, "high"))))


def replication(members: DataFrame, assignment: DataFrame) -> DataFrame:
    """Vertices summed over bins, distinct vertices, and their ratio."""
    v = packing.bin_vertices(members, assignment)
    return v.agg(F.count("*").alias("copies"), F.countDistinct("v").alias("vertices")).select("copies", "vertices", F.round(F.col("copies") / F.col("vertices"), 6).alias("replication"))


def bin_fill(members: DataFrame, assignment: DataFrame, capacity: int) -> DataFrame:
    """Mean fill and the largest load over the mean."""
    b = packing.bins(members, assignment)
    return b.agg(F.round(F.avg(F.col("load") / capacity), 6).alias("mean_fill"), F.round(F.max("load") / F.avg("load"), 6).alias("imbalance"))


def gap(n_bins: int, lower: int, upper: int) -> tuple[float, float]:
    """Bins over the best known and over the bound."""
    return n_bins / max(1, upper), n_bins / max(1, lower)


def ratios(df: DataFrame, base: str, other: str) -> DataFrame:
    """Other over ours; null where the other failed (null)."""
    return df.withColumn("factor", F.round(F.col(other) / F.col(base), 6))


def wall_seconds(action: Callable[[], object]) -> tuple[object, float]:
    began = time.perf_counter()
    out = action()
    return out, time.perf_counter() - began


def measured(spark: SparkSession, action: Callable[[], object]) -> dict:
    """What an action gave and what it cost, from the session's status store: node-seconds (run time summed over all tasks), wall
    seconds, shuffled records and bytes, and the largest execution memory of a stage. An action that runs out of memory, or fails
    otherwise, has a status and no figures."""
    sc, group = spark.sparkContext, f"measured-{uuid.uuid4().hex}"
    store = sc._jsc.sc().statusStore()
    sc.setJobGroup(group, group)
    began = time.perf_counter()
    out = dict.fromkeys(("result", "node_seconds", "seconds", "shuffle_records", "shuffle_bytes", "peak_bytes"))
    try:
        out |= {"status": "ok", "result": action(), "seconds": time.perf_counter() - began}
    except Exception as e:
        return out | {"status": "OOM" if "OutOfMemory" in str(e) or "MemoryError" in str(e) else "DNC"}
    finally:
        sc._jsc.clearJobGroup()
    sc._jsc.sc().listenerBus().waitUntilEmpty()
    stages = {s for j in sc.statusTracker().getJobIdsForGroup(group) for s in sc.statusTracker().getJobInfo(j).stageIds}
    ran = []
    for s in stages:
        with contextlib.suppress(Exception):  # a stage whose shuffle was there already never ran
            ran.append(store.lastStageAttempt(int(s)))
    return out | {"node_seconds": sum(s.executorRunTime() for s in ran) / 1000, "shuffle_records": sum(s.shuffleWriteRecords() for s in ran), "shuffle_bytes": sum(s.shuffleWriteBytes() for s in ran), "peak_bytes": max((s.peakExecutionMemory() for s in ran), default=0)}


def dataset_stats(g: PropertyGraph) -> DataFrame:
    """One row: vertices, edges, mean degree, mean clustering, triangles."""
    z = lambda c: F.coalesce(c, F.lit(0)).alias(c)
    n = g.vertices.select("id").join(g.degrees(), "id", "left").join(closing.corner_counts(g).withColumnRenamed("sg_id", "id"), "id", "left").select(z("degree"), z("links"))
    deg = F.col("degree")
    c = F.when(deg > 1, 2 * F.col("links") / (deg * (deg - 1))).otherwise(0.0)
    row = n.agg(F.count("*").alias("n_vertices"), F.round(F.avg("degree"), 6).alias("mean_degree"), F.round(F.avg(c), 6).alias("mean_lcc"), (F.sum("links") / 3).cast("bigint").alias("n_triangles"))
    return row.join(g.edges.agg(F.count("*").alias("n_edges"))).select("n_vertices", "n_edges", "mean_degree", "mean_lcc", "n_triangles")  # one row each


def levels(g: PropertyGraph, start: DataFrame) -> DataFrame:
    """(v, hop) of what start (v) reaches, a join a hop."""
    arcs = g.arcs("both")
    seen = cut(start.select("v", F.lit(0).alias("hop")), "levels")
    hop = 0
    while True:
        hop += 1
        ends = seen.where(F.col("hop") == hop - 1).join(arcs, F.col("v") == F.col("src")).select(F.col("dst").alias("v")).distinct()
        fresh = cut(ends.join(seen.select("v"), "v", "left_anti").select("v", F.lit(hop).alias("hop")), "levels")
        if not fresh.limit(1).count():
            return seen
        seen = cut(seen.unionAll(fresh), "levels")


def diameter(g: PropertyGraph, sweeps: int = 2) -> DataFrame:
    """(diameter): the longest of so many breadth-first sweeps, each from the farthest vertex of the one before (ties by id) and the first
    from the vertex of largest degree: a lower bound that double sweeps meet on most graphs."""
    at = g.degrees().orderBy(F.desc("degree"), "id").limit(1).select(F.col("id").alias("v"))
    most = 0
    for _ in range(sweeps):
        far = levels(g, at).orderBy(F.desc("hop"), "v").limit(1).head()
        if far is None:
            break
        most = max(most, far.hop)
        at = g.vertices.sparkSession.createDataFrame([(far.v,)], "v bigint")
    return g.vertices.sparkSession.createDataFrame([(most,)], "diameter bigint")
