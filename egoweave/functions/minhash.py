"""Min-hash signatures of vertex sets, by integer arithmetic that any SQL engine repeats."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

# fixed values: multipliers, offsets and modulus of the hash family
A = (1103515245, 1664525013, 1812433253, 1597334677, 2027808485, 1284865837)
B = (1013904223, 777767777, 1540483477, 374761393, 668265263, 1274126177)
P = 2147483647


def coefficients(i: int) -> tuple[int, int]:
    """Multiplier and offset of the i-th function, i from 0; past the fixed ones each follows from the one before."""
    if i < len(A):
        return A[i], B[i]
    a, b = coefficients(i - 1)
    return a * 48271 % P, (b * 69621 + 11) % P


def hashed(i: int, v: str = "v") -> Column:
    """The i-th hash of a vertex id, i from 0."""
    a, b = coefficients(i)
    return F.expr(f"({a} * pmod({v}, {P}) + {b}) % {P}")


def names(n: int = 6) -> list[str]:
    return [f"s{i + 1}" for i in range(n)]


def sketch(members: DataFrame, n: int = 6) -> DataFrame:
    """(sg_id, s1..sn): least hash of each subgraph's vertices under each function; partial minima keep the shuffle light."""
    return members.groupBy("sg_id").agg(*(F.min(hashed(i)).alias(s) for i, s in enumerate(names(n))))


def sketch_order(sketches: DataFrame, buckets: int | None = None) -> DataFrame:
    """(sg_id, rank) from 1 in lexicographic order of the signature, then sg_id.

    Subgraphs are dealt by the quantiles of s1; each range is ranked by itself and moved by the counts of those below.
    """
    cols = [c for c in sketches.columns if c != "sg_id"]
    n = buckets or int(sketches.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = bucket_by_range(sketches, n)
    base = rows.groupBy("bucket").agg(F.count("*").alias("n")).withColumn("base", F.sum("n").over(Window.orderBy("bucket")) - F.col("n"))  # one row a bucket
    rank = F.row_number().over(Window.partitionBy("bucket").orderBy(*cols, "sg_id"))
    return rows.withColumn("r", rank).join(F.broadcast(base.select("bucket", "base")), "bucket").select("sg_id", (F.col("base") + F.col("r")).alias("rank"))


def bucket_by_range(sketches: DataFrame, n: int) -> DataFrame:
    """sketches with bucket 0..n-1: how many of n-1 quantile cut points of s1 lie below s1."""
    if n <= 1:
        return sketches.withColumn("bucket", F.lit(0).cast("bigint"))
    cuts = sketches.agg(F.expr("percentile_approx(s1, array(" + ",".join(f"{i / n!r}D" for i in range(1, n)) + "), 100000)").alias("cuts")).head().cuts or []
    below = sum((F.when(F.col("s1") > F.lit(c), 1).otherwise(0) for c in cuts), F.lit(0))
    return sketches.withColumn("bucket", below.cast("bigint"))


def bucket_by_hash(sketches: DataFrame, n: int, keys: int = 1) -> DataFrame:
    """sketches with bucket 0..n-1 from the first values of the signature: s1 mod n, or a polynomial of several."""
    key = F.col("s1")
    for name in names(keys)[1:]:
        key = (key * 31 + F.col(name)) % P
    return sketches.withColumn("bucket", key % n)


def merge(a: Column, b: Column) -> Column:
    """Signature of a union from two signature arrays."""
    return F.zip_with(a, b, lambda x, y: F.least(x, y))


def similarity(a: Column, b: Column) -> Column:
    """Share of equal places of two signature arrays, an estimate of the Jaccard similarity."""
    same = F.zip_with(a, b, lambda x, y: (x == y).cast("double"))
    return F.aggregate(same, F.lit(0.0), lambda s, x: s + x) / F.size(a)


def as_array(sketches: DataFrame) -> DataFrame:
    return sketches.select("sg_id", F.array(*(c for c in sketches.columns if c.startswith("s") and c != "sg_id")).alias("s"))


def lsh_pairs(sketches: DataFrame, bands: int = 3) -> DataFrame:
    """(a, b) that agree on all places of a band."""
    cols = [c for c in sketches.columns if c != "sg_id"]
    width = len(cols) // bands
    keyed = sketches.select("sg_id", F.posexplode(F.array(*(F.concat_ws(",", *cols[k * width : (k + 1) * width]) for k in range(bands)))).alias("band", "key"))
    x, y = keyed.alias("x"), keyed.alias("y")
    return x.join(y, (F.col("x.band") == F.col("y.band")) & (F.col("x.key") == F.col("y.key")) & (F.col("x.sg_id") < F.col("y.sg_id"))).select(F.col("x.sg_id").alias("a"), F.col("y.sg_id").alias("b")).distinct()


def jaccard(members: DataFrame, pairs: DataFrame) -> DataFrame:
    """(a, b, inter, jaccard) of the vertex sets of pairs (a, b), exactly."""
    size = members.groupBy("sg_id").agg(F.count("*").alias("n"))
    m = members.select("sg_id", "v")
    both = pairs.join(m.withColumnRenamed("sg_id", "a"), "a").join(m.withColumnRenamed("sg_id", "b"), ["b", "v"]).groupBy("a", "b").agg(F.count("*").alias("inter"))
    full = pairs.join(both, ["a", "b"], "left").join(size.toDF("a", "na"), "a").join(size.toDF("b", "nb"), "b")
    inter = F.coalesce("inter", F.lit(0))
    return full.select("a", "b", inter.alias("inter"), (inter / (F.col("na") + F.col("nb") - inter)).alias("jaccard"))
