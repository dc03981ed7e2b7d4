"""The methods as functions of SQL: a table function, a scalar Arrow function and a user aggregate."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import Row


class EgoMembers:
    """Table function over arcs (src, dst) partitioned by src: (sg_id, v, hop) of the 1-hop ball of each src."""

    def __init__(self) -> None:
        self.center: int | None = None
        self.near: set[int] = set()

    def eval(self, row: Row) -> Iterator[tuple]:
        self.center = row["src"]
        self.near.add(row["dst"])
        return iter(())

    def terminate(self) -> Iterator[tuple]:
        if self.center is not None:
            yield self.center, self.center, 0
            for v in sorted(self.near - {self.center}):
                yield self.center, v, 1


def test_bit(words: pa.Array, slot: pa.Array) -> pa.Array:
    """Whether the bit of a slot is set in a word of 32."""
    return pc.equal(pc.bit_wise_and(pc.shift_right(words, slot), pa.scalar(1, pa.int64())), pa.scalar(1, pa.int64()))


def geometric_mean(x: pd.Series) -> float:
    """A user aggregate: the geometric mean of the positive values, null where there is none."""
    import numpy as np

    x = x[x > 0]
    return round(float(np.exp(np.log(x).mean())), 6) if len(x) else None


def register(spark: SparkSession) -> None:
    """ego_members, test_bit and geometric_mean for SQL."""
    spark.udtf.register("ego_members", F.udtf(EgoMembers, returnType="sg_id bigint, v bigint, hop int"))
    spark.udf.register("test_bit", F.arrow_udf(test_bit, "boolean"))
    spark.udf.register("geometric_mean", F.pandas_udf(geometric_mean, "double"))
