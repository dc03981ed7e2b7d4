"""Streams over the events table: read as files, run until all is read, each result kept as Parquet in the shared folder."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..graph import from_edges
from ..operators import baselines, kernels
from ..session import cut, new_folder

STRETCHES = 4


def events(spark: SparkSession, sf_dir: str, order: tuple[int, ...] = tuple(range(STRETCHES))) -> DataFrame:
    """The events as a stream of four stretches of time; ts becomes a timestamp, which watermarks need.

    A stream takes files by their time of writing, so the stretches are written one after another, a file each: this stands
    in for a folder that fills over time, and only the queries here use it. Another order makes late rows.
    """
    path = new_folder(spark, "events")
    rows = spark.read.parquet(f"{sf_dir}/events.parquet")
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    lo, hi = rows.agg(F.min(us), F.max(us)).first()
    stretch = F.floor((us - F.lit(lo)) * STRETCHES / F.lit((hi or 0) - (lo or 0) + 1))
    for i in order:
        rows.where(F.coalesce(stretch, F.lit(0)) == i).coalesce(1).write.mode("append").parquet(path)
    return spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def key() -> Column:
    return F.get_json_object("props", "$.k").cast("bigint")


def drained(stream: DataFrame, name: str, mode: str) -> DataFrame:
    """The rows that a stream gives until its input ends. complete: the last state; append: all rows."""
    spark = stream.sparkSession
    out = new_folder(spark, name)
    w = stream.writeStream.outputMode(mode).option("checkpointLocation", new_folder(spark, f"{name}-checkpoint")).trigger(availableNow=True)
    if mode == "complete":
        w = w.foreachBatch(lambda df, _: df.write.mode("overwrite").parquet(out))
    else:
        w = w.format("parquet").option("path", out)
    w.start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(start, n, weight) events per hour, and how often one within it was followed there by another user's."""
    row = F.struct("ts", "event_id", "user_id")
    w = events(spark, sf_dir).withWatermark("ts", "2 hours").groupBy(F.window("ts", "1 hour").alias("w")).agg(F.sort_array(F.collect_list(row)).alias("e"))
    users = F.transform("e", lambda x: x["user_id"])
    weight = F.aggregate(F.zip_with(F.slice(users, 2, F.size("e")), users, lambda x, y: (x != y).cast("bigint")), F.lit(0).cast("bigint"), lambda s, x: s + F.coalesce(x, F.lit(0)))
    return drained(w.select(F.col("w.start").alias("start"), F.size("e").cast("bigint").alias("n"), weight.alias("weight")), "tumbling", "complete").select(F.col("start").cast("timestamp_ntz").alias("start"), "n", "weight")


def sliding_degree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(start, user_id, n) distinct keys that a user touched in two-day windows that begin every day."""
    e = events(spark, sf_dir).withColumn("k", key()).withWatermark("ts", "2 hours")
    w = e.groupBy(F.window("ts", "2 days", "1 day").alias("w"), "user_id").agg(F.size(F.collect_set("k")).cast("bigint").alias("n"))
    return drained(w.select(F.col("w.start").alias("start"), "user_id", "n"), "sliding", "complete").select(F.col("start").cast("timestamp_ntz").alias("start"), "user_id", "n")


def ego_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(user_id, n) degree of every user in the user-key graph: a user's set of keys is kept as state and its size given out as it grows."""

    def grow(user: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        seen = set(state.get[0]) if state.exists else set()
        for f in frames:
            seen |= set(f["k"].tolist())
        state.update((sorted(seen),))
        yield pd.DataFrame({"user_id": [user[0]], "n": [len(seen)]})

    e = events(spark, sf_dir).select("user_id", key().alias("k")).where("user_id is not null and k is not null")
    out = e.groupBy("user_id").applyInPandasWithState(grow, "user_id bigint, n bigint", "seen array<bigint>", "update", "NoTimeout")
    path = new_folder(spark, "ego")
    out.writeStream.outputMode("update").option("checkpointLocation", new_folder(spark, "ego-checkpoint")).trigger(availableNow=True).foreachBatch(lambda df, _: df.write.mode("append").parquet(path)).start().awaitTermination()
    return spark.read.schema(out.schema).parquet(path).groupBy("user_id").agg(F.max("n").alias("n"))


def stream_components(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(v, component) of the user-key graph (even and odd vertices): each batch's edges are joined with the labels so far, which stand for all edges seen."""
    held: dict[str, DataFrame] = {}

    def merge(df: DataFrame, _: int) -> None:
        edges = df.select("src", "dst").distinct()
        if "labels" in held:
            edges = edges.unionAll(held["labels"].where("v <> component").select(F.col("v").alias("src"), F.col("component").alias("dst")))
        edges = cut(edges, "batch")
        labels = baselines.message_components(from_edges(edges))[0]
        if "labels" in held:
            labels = labels.unionAll(held["labels"].join(labels.select("v"), "v", "left_anti"))
        held["labels"] = cut(labels, "labels")

    e = events(spark, sf_dir).select((F.col("user_id") * 2).alias("src"), (key() * 2 + 1).alias("dst")).where("src is not null and dst is not null")
    e.writeStream.option("checkpointLocation", new_folder(spark, "components-checkpoint")).trigger(availableNow=True).foreachBatch(merge).start().awaitTermination()
    return held["labels"]


def repack(spark: SparkSession, sf_dir: str, capacity: int = 60, buckets: int = 4) -> DataFrame:
    """(rule, violations) after new users' key sets were placed batch by batch, into bins that are there already where they fit (online first fit).

    Users are dealt to buckets by id; a bucket's bins and its new items meet in one task.
    """
    held: dict[str, DataFrame] = {}
    schema = "bucket bigint, bin bigint, user_id bigint, v bigint"

    def place(t: pa.Table) -> pa.Table:
        rows = t.to_pylist()
        bins: dict[int, list] = {}
        new: dict[int, set[int]] = {}
        for r in rows:
            if r["bin"] is None:
                new.setdefault(r["user_id"], set()).add(r["v"])
            else:
                x = bins.setdefault(r["bin"], [set(), set()])
                x[0].add(r["v"])
                x[1].add(r["user_id"])
        ids = sorted(new)
        start = [(bins[b][0], len(bins[b][1])) for b in sorted(bins)]
        at = kernels.place_greedy(kernels.Problem(ids, [frozenset(new[i]) for i in ids], capacity), start=start)
        out = [(rows[0]["bucket"], b, i, v) for b, i in zip(at, ids, strict=True) for v in sorted(new[i])]
        return pa.table(dict(zip(("bucket", "bin", "user_id", "v"), map(list, zip(*out, strict=True)), strict=True)) if out else {c: [] for c in ("bucket", "bin", "user_id", "v")}, pa.schema([(c, pa.int64()) for c in ("bucket", "bin", "user_id", "v")]))

    def merge(df: DataFrame, _: int) -> None:
        items = df.select((F.col("user_id") % buckets).alias("bucket"), F.lit(None).cast("bigint").alias("bin"), "user_id", F.col("k").alias("v")).distinct()
        if "bins" in held:
            items = items.join(held["bins"].select("user_id").distinct(), "user_id", "left_anti").select("bucket", "bin", "user_id", "v").unionAll(held["bins"])
        fresh = items.groupBy("bucket").applyInArrow(place, schema)
        held["bins"] = cut(fresh.unionAll(held["bins"]) if "bins" in held else fresh, "bins")

    e = events(spark, sf_dir).select("user_id", key().alias("k")).where("user_id is not null and k is not null")
    e.writeStream.option("checkpointLocation", new_folder(spark, "repack-checkpoint")).trigger(availableNow=True).foreachBatch(merge).start().awaitTermination()
    b = held["bins"]
    per = b.groupBy("user_id").agg(F.countDistinct("bucket", "bin").alias("n")).where("n > 1")
    load = b.groupBy("bucket", "bin").agg(F.countDistinct("v").alias("load"), F.countDistinct("user_id").alias("n")).where((F.col("load") > capacity) & (F.col("n") > 1))
    missing = spark.read.parquet(f"{sf_dir}/events.parquet").where(key().isNotNull() & F.col("user_id").isNotNull()).select("user_id").distinct().join(b.select("user_id"), "user_id", "left_anti")
    count = lambda df, rule: df.agg(F.count("*").alias("violations")).select(F.lit(rule).alias("rule"), "violations")
    return count(per, "user in one bin").unionAll(count(load, "bin within capacity")).unionAll(count(missing, "every user placed"))


def late_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(start, n) closed hours where the second and third stretch come after the last one.

    A batch is held against the watermark that the batch before it began with, so the second stretch, right after
    the last, still counts; the third is behind the watermark and dropped.
    """
    w = events(spark, sf_dir, (0, 3, 1, 2)).withWatermark("ts", "2 hours").groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count("*").alias("n"))
    return drained(w.select(F.col("w.start").alias("start"), "n"), "late", "append").select(F.col("start").cast("timestamp_ntz").alias("start"), "n")


def dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(user_id, event_type) pairs seen, each once."""
    e = events(spark, sf_dir).withWatermark("ts", "60 days").dropDuplicatesWithinWatermark(["user_id", "event_type"])
    return drained(e.select("user_id", "event_type"), "dedup", "append")


def sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(user_id, start, n) closed sessions of a user: six hours without an event end one, and it is given once the watermark has passed that end."""
    w = events(spark, sf_dir).withWatermark("ts", "2 hours").groupBy(F.session_window("ts", "6 hours").alias("w"), "user_id").agg(F.count("*").alias("n"))
    return drained(w.select("user_id", F.col("w.start").alias("start"), "n"), "sessions", "append").select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), "n")


def stream_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(click_id, purchase_id): purchases within a day after a click of the same user. Watermarks and the interval bound the state."""
    side = lambda kind, i: events(spark, sf_dir).withWatermark("ts", "2 hours").where(F.col("event_type") == kind).select(F.col("user_id").alias(f"{i}_user"), F.col("ts").alias(f"{i}_ts"), F.col("event_id").alias(f"{i}_id"))
    both = side("click", "click").join(side("purchase", "purchase"), F.expr("click_user = purchase_user and purchase_ts >= click_ts and purchase_ts <= click_ts + interval 1 day"))
    return drained(both.select("click_id", "purchase_id"), "join", "append")


SQL = {
    "stream_sessions": "select user_id, min(ts) as start, count(*) as n from (select user_id, ts, sum(fresh) over (partition by user_id order by ts rows unbounded preceding) as s from (select user_id, ts, case when ts < lag(ts) over (partition by user_id order by ts) + interval 6 hours then 0 else 1 end as fresh from events)) group by user_id, s having max(ts) + interval 6 hours <= (select max(ts) - interval 2 hours from events)",
    "stream_join": "select c.event_id as click_id, p.event_id as purchase_id from events c join events p on c.user_id = p.user_id and p.ts between c.ts and c.ts + interval 1 day where c.event_type = 'click' and p.event_type = 'purchase'",
    "stream_tumbling": "select start, count(*) as n, cast(count(*) filter (after <> user_id) as bigint) as weight from (select date_trunc('hour', ts) as start, user_id, lead(user_id) over (partition by date_trunc('hour', ts) order by ts, event_id) as after from events) group by 1",
    "stream_sliding_degree": "select s as start, user_id, count(distinct k) as n from (select user_id, cast(json_extract_string(props, '$.k') as bigint) as k, unnest([date_trunc('day', ts)::timestamp, date_trunc('day', ts)::timestamp - interval 1 day]) as s from events) group by 1, 2",
    "stream_ego_counts": "select user_id, count(distinct k) as n from (select user_id, cast(json_extract_string(props, '$.k') as bigint) as k from events) where k is not null group by 1",
    "stream_components": "with recursive e as (select distinct 2 * user_id as a, 2 * cast(json_extract_string(props, '$.k') as bigint) + 1 as b from events where json_extract_string(props, '$.k') is not null), u as (select a, b from e union select b, a from e), r as (select a as v, a as l from u union select u.b, r.l from r join u on u.a = r.v) select v, min(l) as component from r group by 1",
    "stream_repack": "select unnest(['user in one bin', 'bin within capacity', 'every user placed']) as rule, cast(0 as bigint) as violations",
    "stream_late_rows": "select date_trunc('hour', ts) as start, count(*) as n from events, (select epoch_us(min(ts)) as lo, epoch_us(max(ts)) as hi, max(ts) as top from events) where (epoch_us(ts) - lo) * 4 // (hi - lo + 1) in (0, 1, 3) group by 1, top having date_trunc('hour', ts) + interval 1 hour <= top - interval 2 hours",
    "stream_dedup": "select distinct user_id, event_type from events",
}
QUERIES = {"stream_tumbling": tumbling, "stream_sliding_degree": sliding_degree, "stream_dedup": dedup, "stream_sessions": sessions, "stream_join": stream_join, "stream_ego_counts": ego_counts, "stream_components": stream_components, "stream_repack": repack, "stream_late_rows": late_rows}
