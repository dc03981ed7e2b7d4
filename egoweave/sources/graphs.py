"""The graphs that the experiments run on, derived from the given tables."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..graph import PropertyGraph, canonical, from_edges
from ..session import cut



def left(key: str) -> Column:
    """Vertex of a key on the first side of a bipartite graph: an even number, whatever the size of the keys."""
    return F.col(key).cast("bigint") * 2


def right(key: Column | str) -> Column:
    """Vertex of a key on the other side: an odd number."""
    return (F.col(key) if isinstance(key, str) else key).cast("bigint") * 2 + 1


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _sharing(rows: DataFrame, key: str, item: str) -> DataFrame:
    """Pairs of distinct items that share a key."""
    one = rows.select(F.col(key).alias("k"), F.col(item).alias("i")).distinct()
    return one.alias("a").join(one.alias("b"), (F.col("a.k") == F.col("b.k")) & (F.col("a.i") < F.col("b.i"))).select(F.col("a.i").alias("src"), F.col("b.i").alias("dst")).distinct()


def kept(g: PropertyGraph) -> PropertyGraph:
    """The graph with its edges written once; its vertices are their ends."""
    return from_edges(cut(g.edges, "edges"), g.directed)


def with_parts(spark: SparkSession, sf_dir: str, g: PropertyGraph) -> PropertyGraph:
    """A graph over parts with the part attributes on its vertices, which are written once, as every extraction reads them."""
    part = table(spark, sf_dir, "part").withColumnRenamed("p_partkey", "id")
    return PropertyGraph(cut(part.join(g.vertices, "id", "left_semi"), "vertices"), g.edges, g.directed)


def returned(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Parts that were both returned in one order."""
    lines = table(spark, sf_dir, "lineitem").where("l_returnflag = 'R'")
    return from_edges(_sharing(lines, "l_orderkey", "l_partkey"))


def copurchase(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Parts in one order."""
    return from_edges(_sharing(table(spark, sf_dir, "lineitem"), "l_orderkey", "l_partkey"))


def next_line(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """From the part on a line to the part on the next line of the order."""
    w = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey")
    steps = table(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("src"), F.lead("l_partkey").over(w).alias("dst"))
    return from_edges(steps.where("dst is not null and src <> dst").distinct(), True)


def handoff(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """From the user of an event to the user of the next event, weight the number of times.

    The order is global, so each day is ordered by itself and its last event is tied to the first of the next day that has any.
    """
    events = table(spark, sf_dir, "events").select("ts", "event_id", "user_id", F.to_date("ts").alias("day"))
    w = Window.partitionBy("day").orderBy("ts", "event_id")
    within = events.select(F.col("user_id").alias("src"), F.lead("user_id").over(w).alias("dst"))
    ends = events.groupBy("day").agg(F.min_by("user_id", F.struct("ts", "event_id")).alias("first"), F.max_by("user_id", F.struct("ts", "event_id")).alias("last"))
    across = ends.select(F.col("last").alias("src"), F.lead("first").over(Window.orderBy("day")).alias("dst"))  # one row a day
    steps = within.unionAll(across).where("dst is not null and src <> dst")
    return from_edges(steps.groupBy("src", "dst").agg(F.count("*").alias("weight")), True)


def _orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    return table(spark, sf_dir, "lineitem").join(orders, F.col("l_orderkey") == F.col("o_orderkey"))


def customer_supplier(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    return from_edges(_orders(spark, sf_dir).select(left("o_custkey").alias("src"), right("l_suppkey").alias("dst")).distinct())


def customer_part(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    return from_edges(_orders(spark, sf_dir).select(left("o_custkey").alias("src"), right("l_partkey").alias("dst")).distinct())


def supplier_part(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    return from_edges(table(spark, sf_dir, "lineitem").select(left("l_partkey").alias("src"), right("l_suppkey").alias("dst")).distinct())


def customer_order(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    edges = table(spark, sf_dir, "orders").select(left("o_custkey").alias("src"), right("o_orderkey").alias("dst")).distinct()
    customers = table(spark, sf_dir, "customer").select(left("c_custkey").alias("id"))
    return PropertyGraph(customers.union(edges.select(F.col("dst").alias("id"))).distinct(), edges)


def user_key(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    key = F.get_json_object("props", "$.k").cast("bigint")
    return from_edges(table(spark, sf_dir, "events").select(left("user_id").alias("src"), right(key).alias("dst")).where("dst is not null").distinct())


def returned_same_kind(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Edges of the returned graph whose parts share brand and type."""
    part = table(spark, sf_dir, "part").select("p_partkey", F.struct("p_brand", "p_type").alias("kind"))
    g = returned(spark, sf_dir)
    a, b = part.toDF("src", "kind_a"), part.toDF("dst", "kind_b")
    return from_edges(g.edges.join(a, "src").join(b, "dst").where("kind_a = kind_b").select("src", "dst"))


def host_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(host, target) of the relative links of every page."""
    pages = table(spark, sf_dir, "pages")
    host = F.regexp_extract("url", "^[a-z]+://([^/?#]*)", 1)
    return pages.select(host.alias("host"), F.explode(F.regexp_extract_all("html", F.lit('href="(/[^"]*)"'), 1)).alias("target")).distinct()


def document_lines(spark: SparkSession, sf_dir: str, least: int = 40) -> DataFrame:
    """(id, key) of the lines of so many characters, a key a different line."""
    lines = table(spark, sf_dir, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("line")).where(F.length("line") >= least)
    return lines.select(F.col("doc_id").alias("id"), F.concat_ws(":", F.xxhash64("line"), F.md5("line")).alias("key"))


def shared_lines(spark: SparkSession, sf_dir: str, least: int = 40) -> PropertyGraph:
    """Documents that share a line of so many characters."""
    return from_edges(_sharing(document_lines(spark, sf_dir, least), "key", "id"))


#: Vectors of a block; two blocks meet in a task.
VECTORS = 2048


def similar_vectors(spark: SparkSession, sf_dir: str, over: float = 0.3) -> PropertyGraph:
    """Vectors whose dot product is over a bound; blocks of vectors meet pairwise by a matrix product, and pairs near the bound are summed again in order."""
    rows = table(spark, sf_dir, "embeddings").select("vec_id", "embedding").where("vec_id is not null and embedding is not null")
    parts = max(1, -(-rows.count() // VECTORS))
    dealt = rows.withColumn("p", F.pmod(F.xxhash64("vec_id"), F.lit(parts)).cast("int")).withColumn("q", F.explode(F.sequence(F.lit(0), F.lit(parts - 1))))
    dealt = dealt.select("vec_id", "embedding", "p", F.least("p", "q").alias("lo"), F.greatest("p", "q").alias("hi"))

    def run(t: pa.Table) -> pa.Table:
        t = t.combine_chunks()
        ids, home = t.column("vec_id").to_numpy(), t.column("p").to_numpy()
        lists = t.column("embedding").combine_chunks()
        size = lists.value_lengths().to_numpy()
        v = np.zeros((len(ids), max(1, size.max(initial=0))))
        v[np.arange(v.shape[1]) < size[:, None]] = lists.flatten().fill_null(0).to_numpy()
        lo, hi = t.column("lo")[0].as_py(), t.column("hi")[0].as_py()
        left, right = np.flatnonzero(home == lo), np.flatnonzero(home == hi)
        src, dst = [ids[:0]], [ids[:0]]
        for part in np.split(left, range(256, len(left), 256)):
            dot = v[part] @ v[right].T
            i, j = np.nonzero(~(dot < over - 1e-6))
            near = np.abs(dot[i, j] - over) <= 1e-6
            i, j = part[i], right[j]
            keep = ~near
            keep[near] = np.cumsum(v[i[near]] * v[j[near]], axis=1)[:, -1] > over
            keep &= (ids[i] < ids[j]) if lo == hi else (ids[i] != ids[j])
            src.append(np.minimum(ids[i[keep]], ids[j[keep]]))
            dst.append(np.maximum(ids[i[keep]], ids[j[keep]]))
        return pa.table({"src": np.concatenate(src), "dst": np.concatenate(dst)})

    return from_edges(dealt.groupBy("lo", "hi").applyInArrow(run, "src bigint, dst bigint"))


def attachment_edges(n: int, m: int, seed: int) -> list[tuple[int, int]]:
    """Preferential attachment with integer arithmetic: vertex v > m picks m ends among the ends so far by a linear congruential generator."""
    state, ends, edges = (seed * 48271 + 11) % 2147483647 or 1, [], set()
    for v in range(1, n):
        picked = set()
        for _ in range(min(m, v)):
            state = state * 48271 % 2147483647
            u = ends[state % len(ends)] if ends else 0
            picked.add(u if u not in picked else state % v)
        for u in sorted(picked):
            edges.add((min(u, v), max(u, v)))
            ends += [u, v]
    return sorted(edges)


def attachment(spark: SparkSession, n: int, m: int, seed: int) -> PropertyGraph:
    """A preferential-attachment graph of a thousand vertices at most; the sequential rule runs once, here."""
    return from_edges(spark.createDataFrame(attachment_edges(n, m, seed), "src bigint, dst bigint"))


def attached(keys: DataFrame, m: int, seed: int) -> PropertyGraph:
    """A preferential-attachment graph over given keys (id), each of which joins those below it; each step needs the one before, so one task takes them all."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids = [v for b in batches for v in b.column(0).to_pylist()]
        edges = attachment_edges(len(ids), m, seed)
        yield pa.RecordBatch.from_arrays([pa.array([ids[e[side]] for e in edges], pa.int64()) for side in (0, 1)], ["src", "dst"])

    ordered = keys.select("id").where("id is not null").distinct().repartition(1).sortWithinPartitions("id")
    return from_edges(ordered.mapInArrow(run, "src bigint, dst bigint"))


GRAPHS: dict[str, Callable[[SparkSession, str], PropertyGraph]] = {
    "returned": returned,
    "copurchase": copurchase,
    "next_line": next_line,
    "handoff": handoff,
    "customer_supplier": customer_supplier,
    "customer_part": customer_part,
    "supplier_part": supplier_part,
    "customer_order": customer_order,
    "user_key": user_key,
    "returned_same_kind": returned_same_kind,
}
