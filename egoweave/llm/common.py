"""What the operators share: the shared folder, size-checked joins and connected components."""

from __future__ import annotations

import atexit
import contextlib
import os
import re
import tempfile
import uuid
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: A side of a join is broadcast only if its rows, counted first, fit in this many bytes.
BROADCAST_BYTES = 24 << 20
#: Texts go to Python workers in Arrow batches of this many bytes (or one row, where that is longer); a smaller setting of the session stays.
BATCH_SETTING, BATCH_BYTES = "spark.sql.execution.arrow.maxBytesPerBatch", 8 << 20
_made: list[tuple[SparkSession, str]] = []


def _bytes(setting: str) -> int:
    """A byte setting as a number; one with a unit other than bytes counts as large."""
    return int(setting.removesuffix("b")) if setting.removesuffix("b").isdigit() else 1 << 62


def ship(spark: SparkSession) -> None:
    """Let Python workers import this package from where the driver has it, and bound the bytes of a batch sent to one."""
    if _bytes(spark.conf.get(BATCH_SETTING)) > BATCH_BYTES:
        spark.conf.set(BATCH_SETTING, str(BATCH_BYTES))
    root = str(Path(__file__).resolve().parents[2])
    env = spark.sparkContext.environment
    have = env.get("PYTHONPATH", "")
    if root not in have.split(os.pathsep):
        env["PYTHONPATH"] = os.pathsep.join(x for x in (root, have) if x)


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or in local mode one of our own where that is unset."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        if not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
            raise RuntimeError("on a cluster spark.checkpoint.dir must name a folder that all machines share")
        found = tempfile.gettempdir() + f"/egoweave-{os.getpid()}"
    return found.rstrip("/")


def new_path(spark: SparkSession, name: str) -> str:
    path = f"{shared_dir(spark)}/egoweave/{name}-{uuid.uuid4().hex}"
    _made.append((spark, path))
    return path


def drop_path(spark: SparkSession, path: str) -> None:
    """Delete a folder that nothing reads any more."""
    with contextlib.suppress(Exception):
        jvm = spark.sparkContext._jvm
        at = jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


@atexit.register
def _clean() -> None:
    for spark, path in _made:
        drop_path(spark, path)


def saved(df: DataFrame, name: str, codec: str = "zstd") -> DataFrame:
    """df written to the shared folder and read again: later reads do not compute it anew, and lost executors lose nothing."""
    spark = df.sparkSession
    path = new_path(spark, name)
    df.write.option("compression", codec).parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._egoweave_path = path
    return out


def small(df: DataFrame, row_bytes: int, limit: int = BROADCAST_BYTES) -> DataFrame:
    """df marked for broadcast if its counted rows fit in limit; else as it is, for a shuffled join. Give a saved df."""
    return F.broadcast(df) if limit and df.count() * row_bytes <= limit else df


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def free(columns: list[str], *wanted: str) -> list[str]:
    """The wanted column names, lengthened where a table already has them (case aside)."""
    taken, out = {c.lower() for c in columns}, []
    for name in wanted:
        while name.lower() in taken:
            name = f"_{name}"
        taken.add(name.lower())
        out.append(name)
    return out


def components(edges: DataFrame, name: str = "components") -> DataFrame:
    """(v, component): the smallest vertex that is reachable over edges (a, b), for every vertex of an edge.

    Alternating star contraction: each pass links what lies above a vertex, then what lies
    at or below it, to its smallest neighbour, until every vertex is tied to its minimum only.
    Minima are partial aggregates and the joins are plain equi-joins that Spark can split, so
    a vertex with very many links does not meet in one task. Self-loops are allowed.
    """
    current = saved(edges.where("a <> b").select(F.least("a", "b").alias("lo"), F.greatest("a", "b").alias("hi")).distinct(), name)
    while True:
        both = current.select(F.col("hi").alias("u"), F.col("lo").alias("n")).union(current.select(F.col("lo").alias("u"), F.col("hi").alias("n")))
        least = both.groupBy("u").agg(F.min("n").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("n > u").join(least, "u").select(F.least("n", "m").alias("lo"), F.greatest("n", "m").alias("hi")).where("lo <> hi").distinct()
        below = large.groupBy(F.col("hi").alias("u")).agg(F.min("lo").alias("m"))
        tied = large.select(F.col("hi").alias("u"), "lo").join(below, "u")
        nxt = saved(tied.select(F.col("m").alias("lo"), F.col("lo").alias("x")).where("lo <> x").select("lo", F.col("x").alias("hi")).union(tied.select(F.col("m").alias("lo"), F.col("u").alias("hi"))).distinct(), name)
        # done when every upper vertex has one lower one and no lower vertex is itself an upper one
        uppers = nxt.groupBy("hi").agg(F.count("*").alias("n"))
        loose = uppers.where("n > 1").limit(1).count() or nxt.select(F.col("lo").alias("hi")).distinct().join(nxt.select("hi"), "hi", "left_semi").limit(1).count()
        drop_path(current.sparkSession, current._egoweave_path)
        current = nxt
        if not loose:
            return current.select(F.col("hi").alias("v"), F.col("lo").alias("component")).union(current.select(F.col("lo").alias("v"), F.col("lo").alias("component")).distinct())
