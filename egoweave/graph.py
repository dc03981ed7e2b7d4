"""Property graphs as pairs of DataFrames."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


@dataclass(frozen=True)
class PropertyGraph:
    """vertices(id, attributes...) and edges(src, dst, attributes...); undirected edges are stored once, src < dst."""

    vertices: DataFrame
    edges: DataFrame
    directed: bool = False

    def arcs(self, direction: str = "out") -> DataFrame:
        """(src, dst) steps that a walk may take; undirected graphs give both ways."""
        out = self.edges.select("src", "dst")
        back = self.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
        if not self.directed:
            return out.unionAll(back)
        if direction == "both":
            return out.unionAll(back).distinct()
        return out if direction == "out" else back

    def degrees(self) -> DataFrame:
        """(id, degree) of vertices with edges: neighbours in either direction, each once."""
        both = self.arcs("both").where("src <> dst")
        return both.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("degree"))

    def adjacency(self) -> DataFrame:
        """(id, degree, nbrs) with the neighbours in ascending order."""
        arcs = self.arcs("out").where("src <> dst")
        return arcs.groupBy(F.col("src").alias("id")).agg(F.sort_array(F.collect_set("dst")).alias("nbrs")).select("id", F.size("nbrs").cast("bigint").alias("degree"), "nbrs")


def from_edges(edges: DataFrame, directed: bool = False) -> PropertyGraph:
    """A graph whose vertices are the end points of its edges."""
    ends = edges.select(F.col("src").alias("id")).union(edges.select(F.col("dst").alias("id"))).distinct()
    return PropertyGraph(ends, edges, directed)


def canonical(pairs: DataFrame, a: str = "src", b: str = "dst") -> DataFrame:
    """Distinct undirected edges src < dst of a pair table; loops go."""
    return pairs.where(F.col(a) != F.col(b)).select(F.least(a, b).alias("src"), F.greatest(a, b).alias("dst")).distinct()


def dense_ids(keys: DataFrame, column: str, buckets: int = 64) -> DataFrame:
    """(key, id) with ids 0.. in key order within hash buckets: counts per bucket give each bucket its base, so no single task ranks all keys."""
    rows = keys.select(F.col(column).alias("key")).distinct().withColumn("bucket", F.pmod(F.xxhash64("key"), F.lit(buckets)))
    bases = rows.groupBy("bucket").agg(F.count("*").alias("n"))
    bases = bases.withColumn("base", F.sum("n").over(Window.orderBy("bucket")) - F.col("n")).select("bucket", "base")  # at most `buckets` rows
    rank = F.row_number().over(Window.partitionBy("bucket").orderBy("key")) - 1
    return rows.withColumn("r", rank).join(F.broadcast(bases), "bucket").select("key", (F.col("base") + F.col("r")).alias("id"))
