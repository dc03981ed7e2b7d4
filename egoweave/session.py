"""Session helpers: shipping this package to Python workers, cutting lineage."""

from __future__ import annotations

import atexit
import contextlib
import os
import re
import tempfile
import uuid
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession


def ship(spark: SparkSession) -> SparkSession:
    """Let Python workers import this package from where the driver has it."""
    root = str(Path(__file__).resolve().parents[1])
    env = spark.sparkContext.environment
    have = env.get("PYTHONPATH", "")
    if root not in have.split(os.pathsep):
        env["PYTHONPATH"] = os.pathsep.join(x for x in (root, have) if x)
    return spark


_made: list[tuple[SparkSession, str]] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder that all machines share: spark.checkpoint.dir, or in local mode one of our own where that is unset."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        if not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
            raise RuntimeError("on a cluster spark.checkpoint.dir must name a folder that all machines share")
        found = f"{tempfile.gettempdir()}/egoweave-{os.getpid()}"
    return found.rstrip("/")


def new_folder(spark: SparkSession, name: str) -> str:
    """A folder of its own below the shared one; it goes when the driver ends."""
    path = f"{shared_dir(spark)}/egoweave/{name}-{uuid.uuid4().hex}"
    _made.append((spark, path))
    return path


def drop_folder(spark: SparkSession, path: str) -> None:
    """Delete a folder that nothing reads any more."""
    with contextlib.suppress(Exception):
        at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


@atexit.register
def _clean() -> None:
    for spark, path in _made:
        drop_folder(spark, path)


def cut(df: DataFrame, name: str = "state") -> DataFrame:
    """df written to the shared folder and read again, so that loops keep short plans and lost executors lose nothing."""
    spark = df.sparkSession
    path = new_folder(spark, name)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._egoweave_path = path
    return out


def let_go(df: DataFrame) -> None:
    """Delete what cut() wrote for df; nothing may read df afterwards."""
    drop_folder(df.sparkSession, df._egoweave_path)
