"""Samples of subgraphs that outgrow a bin; every choice is a function of ids and a salt."""

from __future__ import annotations

from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.minhash import A, B, P
from ..graph import PropertyGraph
from ..plans.extract import induced_edges
from ..session import cut
from . import closing


def find_oversized(sizes: DataFrame, capacity: int) -> DataFrame:
    return sizes.where(F.col("load") > capacity)


def kept(ratio: float, salt: str = "salt", v: str = "v", c: str = "sg_id") -> str:
    """SQL of the rule by which a vertex stays in a sample; it reads the same in any engine for ids of 0 or more."""
    return f"({v} = {c} or ((({A[0]} * {v}) % {P}) + (({A[1]} * {c}) % {P}) + (({salt} * {B[2]}) % {P})) % {P} % 1000000 < {int(ratio * 1_000_000)})"


def fit(members: DataFrame, capacity: int, salt: int = 1) -> DataFrame:
    """members in which every subgraph over the capacity keeps its centre and, in order of a hash, as many vertices as fit.

    The hash first thins each of them to about a tenth over the capacity, so what is then ordered is bounded by a bin.
    """
    load = members.groupBy("sg_id").agg(F.sum("w").alias("load")).where(F.col("load") > capacity)
    over = members.join(load, "sg_id")
    h = F.expr(f"((({A[0]} * pmod(v, {P})) % {P}) + (({A[1]} * pmod(sg_id, {P})) % {P}) + (({salt} * {B[2]}) % {P})) % {P}")
    over = over.withColumn("h", F.when(F.col("v") == F.col("sg_id"), -1).otherwise(h)).where(F.col("h") < 1.1 * capacity / F.col("load") * P)
    so_far = F.sum("w").over(Window.partitionBy("sg_id").orderBy("h", "v").rowsBetween(Window.unboundedPreceding, 0))
    kept_rows = over.withColumn("so_far", so_far).where((F.col("so_far") <= capacity) | (F.col("v") == F.col("sg_id"))).select(*members.columns)
    return members.join(load.select("sg_id"), "sg_id", "left_anti").select(*members.columns).unionAll(kept_rows)


def node_sample(members: DataFrame, ratio: float, salt: int = 1) -> DataFrame:
    """members with each vertex but the centre kept independently with the given probability."""
    return members.where(kept(ratio, f"cast({salt} as bigint)"))


def _walker(members: DataFrame, g: PropertyGraph, rule: Callable, schema: str) -> DataFrame:
    edges = induced_edges(members, g).select(F.col("sg_id").alias("of"), "src", "dst")
    return members.select("sg_id", "v").groupBy("sg_id").cogroup(edges.groupBy("of")).applyInArrow(rule, schema)


def _near(right: pa.Table, directed: bool) -> dict[int, list[int]]:
    near: dict[int, set[int]] = {}
    for a, b in zip(right.column("src").to_pylist(), right.column("dst").to_pylist(), strict=True):
        near.setdefault(a, set()).add(b)
        if not directed:
            near.setdefault(b, set()).add(a)
    return {v: sorted(x) for v, x in near.items()}


def sampled(members: DataFrame, g: PropertyGraph, sampler: Callable[[int, dict[int, list[int]], list[int]], set[int]]) -> DataFrame:
    """(sg_id, v) that a user's sampler(centre, neighbours, vertices) picks in each subgraph."""
    directed = g.directed

    def rule(key, left: pa.Table, right: pa.Table) -> pa.Table:
        c = key[0].as_py()
        got = sorted(sampler(c, _near(right, directed), left.column("v").to_pylist()))
        return pa.table({"sg_id": pa.array([c] * len(got), pa.int64()), "v": pa.array(got, pa.int64())})

    return _walker(members, g, rule, "sg_id bigint, v bigint")


def walk_sampler(ratio: float, salt: int = 1, restart: int = 150) -> Callable:
    """A seeded walk from the centre until a share of the vertices is seen; it stops after 100 steps a wanted vertex (small components)."""

    def pick(c: int, near: dict[int, list[int]], vs: list[int]) -> set[int]:
        want, x, v, got = max(1, round(ratio * len(vs))), (48271 * (c % P) + salt) % P or 1, c, {c}
        for _ in range(100 * want):
            if len(got) >= want:
                break
            x = 48271 * x % P
            to = near.get(v)
            v = c if x % 1000 < restart or not to else to[x // 1000 % len(to)]
            got.add(v)
        return got

    return pick


def walk_counts(c: int, near: dict[int, list[int]], n: int, ratios: list[float], salt: int = 1, restart: int = 150) -> list[tuple[int, int]]:
    """(vertices without the centre, links among them) that walk_sampler() picks of n vertices by each ratio.

    The walks of a salt are one walk, which stops later for a larger ratio; a link is counted when its second end is seen.
    """
    x, v, got, steps, links = (48271 * (c % P) + salt) % P or 1, c, {c}, 0, 0
    out: dict[int, tuple[int, int]] = {}
    wants = [max(1, round(r * n)) for r in ratios]
    for want in sorted(set(wants)):
        while len(got) < want and steps < 100 * want:
            steps += 1
            x = 48271 * x % P
            to = near.get(v)
            v = c if x % 1000 < restart or not to else to[x // 1000 % len(to)]
            if v not in got:
                links += sum(1 for u in near[v] if u in got) - (c in near[v])
                got.add(v)
        out[want] = len(got) - 1, links
    return [out[want] for want in wants]


def forest_fire_sampler(ratio: float, burn: float = 0.4, salt: int = 1) -> Callable:
    """Burns from the centre to a share of each burning vertex's neighbours until enough vertices have burnt."""

    def pick(c: int, near: dict[int, list[int]], vs: list[int]) -> set[int]:
        want, x, got, todo = max(1, round(ratio * len(vs))), (48271 * (c % P) + salt) % P or 1, {c}, [c]
        while todo and len(got) < want:
            v = todo.pop(0)
            for u in near.get(v, ()):
                x = 48271 * x % P
                if u not in got and x % 1000 < burn * 1000 and len(got) < want:
                    got.add(u)
                    todo.append(u)
        return got

    return pick


def hash_of(salt: int, v: str, c: str = "sg_id") -> str:
    """SQL of the number under a million that kept() compares with a ratio."""
    return f"((({A[0]} * {v}) % {P}) + (({A[1]} * {c}) % {P}) + {salt * B[2] % P}L) % {P} % 1000000"


def links_of(g: PropertyGraph, members: DataFrame) -> DataFrame:
    """(sg_id, src, dst): edges among the neighbours in 1-hop subgraphs, written once."""
    return cut(closing.opposite_edges(g, members.select(F.col("sg_id").alias("id")).distinct()), "links")


def _exact(g: PropertyGraph, members: DataFrame, links: DataFrame) -> DataFrame:
    """(exact_lcc): mean clustering of the centres in the whole graph."""
    ids = members.select("sg_id").distinct()
    degree = g.arcs("both").where("src <> dst").join(ids.withColumnRenamed("sg_id", "src"), "src", "left_semi").groupBy(F.col("src").alias("sg_id")).agg(F.count("*").alias("degree"))
    rows = ids.join(degree, "sg_id", "left").join(links.groupBy("sg_id").agg(F.count("*").alias("links")), "sg_id", "left")
    return relational_lcc(rows.withColumn("degree", F.coalesce("degree", F.lit(0)))).agg(F.round(F.avg("lcc"), 6).alias("exact_lcc"))


def _study(each: DataFrame, exact: DataFrame) -> DataFrame:
    per_run = each.groupBy("ratio", "salt").agg(F.avg("lcc").alias("m"))
    return per_run.groupBy("ratio").agg(F.round(F.avg("m"), 6).alias("mean_lcc"), F.round(F.stddev("m"), 6).alias("std_lcc")).join(F.broadcast(exact))


def lcc_study(g: PropertyGraph, members: DataFrame, ratios: list[float], runs: int = 10, links: DataFrame | None = None) -> DataFrame:
    """(ratio, mean_lcc, std_lcc, exact_lcc): node samples of 1-hop subgraphs, all ratios and runs in one pass.

    A member or link is in a sample where its hash is under the ratio, so samples are counted by sums and not copied; links are links_of().
    """
    links = links_of(g, members) if links is None else links
    salts = range(1, runs + 1)
    cells = [(k, r, s) for k, (r, s) in enumerate((r, s) for r in ratios for s in salts)]
    ends = members.select(F.col("sg_id"), F.col("v").alias("src")).where("src <> sg_id")
    inside = links.join(ends, ["sg_id", "src"], "left_semi").join(ends.withColumnRenamed("src", "dst"), ["sg_id", "dst"], "left_semi")

    def counted(rows: DataFrame, place: Callable[[int], str], name: str) -> DataFrame:
        rows = rows.select("sg_id", *(F.expr(place(s)).alias(f"h{s}") for s in salts))
        return rows.groupBy("sg_id").agg(*(F.sum((F.col(f"h{s}") < int(r * 1_000_000)).cast("bigint")).alias(f"{name}{k}") for k, r, s in cells))

    degree = counted(ends, lambda s: hash_of(s, "src"), "d")
    link = counted(inside, lambda s: f"greatest({hash_of(s, 'src')}, {hash_of(s, 'dst')})", "k")
    rows = members.select("sg_id").distinct().join(degree, "sg_id", "left").join(link, "sg_id", "left")
    cell = (F.struct(F.lit(float(r)).alias("ratio"), F.lit(s).cast("bigint").alias("salt"), F.coalesce(f"d{k}", F.lit(0)).alias("degree"), F.coalesce(f"k{k}", F.lit(0)).alias("links")) for k, r, s in cells)
    each = relational_lcc(rows.select("sg_id", F.explode(F.array(*cell)).alias("c")).select("sg_id", "c.*"))
    return _study(each, _exact(g, members, links))


def walk_lcc_study(g: PropertyGraph, members: DataFrame, ratios: list[float], runs: int = 10, links: DataFrame | None = None) -> DataFrame:
    """(ratio, mean_lcc, std_lcc, exact_lcc) by walk samples of 1-hop subgraphs: a subgraph's walks of all ratios and runs go in one task, its own; links are links_of()."""
    links = links_of(g, members) if links is None else links
    schema = "ratio double, salt bigint, sg_id bigint, lcc double"

    def rule(key, left: pa.Table, right: pa.Table) -> pa.Table:
        c, near, n, out = key[0].as_py(), _near(right, False), left.num_rows, []
        for salt in range(1, runs + 1):
            for r, (d, k) in zip(ratios, walk_counts(c, near, n, ratios, salt), strict=True):
                out.append((r, salt, c, round(2 * k / (d * (d - 1)), 6) if d > 1 else 0.0))
        return pa.table(dict(zip(("ratio", "salt", "sg_id", "lcc"), map(list, zip(*out, strict=True)), strict=True)), pa.schema([("ratio", pa.float64()), ("salt", pa.int64()), ("sg_id", pa.int64()), ("lcc", pa.float64())]))

    spokes = members.where("v <> sg_id").select("sg_id", F.least("sg_id", "v").alias("src"), F.greatest("sg_id", "v").alias("dst"))
    edges = links.select("sg_id", "src", "dst").unionAll(spokes).withColumnRenamed("sg_id", "of")
    each = members.select("sg_id", "v").groupBy("sg_id").cogroup(edges.groupBy("of")).applyInArrow(rule, schema)
    return _study(each, _exact(g, members, links))


def relational_lcc(counts: DataFrame) -> DataFrame:
    d, k = F.col("degree"), F.coalesce("links", F.lit(0))
    return counts.withColumn("lcc", F.when(d > 1, F.round(2 * k / (d * (d - 1)), 6)).otherwise(0.0))
