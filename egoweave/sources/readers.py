"""Readers and writers of graphs in other forms."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read_edge_list(spark: SparkSession, path: str, sep: str = r"\s+", comment: str = "#") -> DataFrame:
    """(src, dst) of a text file with an edge a line; lines that are no edge go."""
    parts = F.split(F.trim("value"), sep)
    rows = spark.read.text(path).where(~F.startswith("value", F.lit(comment)))
    return rows.select(F.try_element_at(parts, F.lit(1)).try_cast("bigint").alias("src"), F.try_element_at(parts, F.lit(2)).try_cast("bigint").alias("dst")).where("src is not null and dst is not null")


def read_adjacency(spark: SparkSession, path: str, sep: str = r"\s+") -> DataFrame:
    """(src, dst) of a text file with a vertex and its neighbours a line."""
    parts = F.split(F.trim("value"), sep)
    rows = spark.read.text(path).select(parts.alias("p")).select(F.get("p", F.lit(0)).try_cast("bigint").alias("src"), F.explode(F.slice("p", 2, 1 << 30)).alias("d"))
    return rows.select("src", F.col("d").try_cast("bigint").alias("dst")).where("src is not null and dst is not null")


def read_kv(spark: SparkSession, path: str) -> DataFrame:
    """(src, dst) of JSON lines {"id": 1, "nbrs": [2, 3]}."""
    rows = spark.read.text(path).select(F.from_json("value", "id bigint, nbrs array<bigint>").alias("x"))
    return rows.select(F.col("x.id").alias("src"), F.explode("x.nbrs").alias("dst")).where("src is not null")


def read_jdbc(spark: SparkSession, url: str, table: str, column: str, lower: int, upper: int, parts: int, **options) -> DataFrame:
    """A table of a relational store, read in parallel ranges of a column."""
    return spark.read.jdbc(url, table, column=column, lowerBound=lower, upperBound=upper, numPartitions=parts, properties=options)


def save_placement(assignment: DataFrame, path: str) -> None:
    """The assignment as Parquet, a folder a bin range, for every later program on the same query."""
    assignment.write.mode("overwrite").parquet(path)


def load_placement(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


def grid(spark: SparkSession, n: int) -> DataFrame:
    """Edges of an n x n grid."""
    v = spark.range(n * n)
    right = v.where(f"id % {n} < {n - 1}").select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"))
    return right.unionAll(v.where(f"id < {n * (n - 1)}").select(F.col("id").alias("src"), (F.col("id") + n).alias("dst")))
