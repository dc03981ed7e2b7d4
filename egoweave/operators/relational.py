"""The applications as joins: no Python on the executors, spill anywhere."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.minhash import P
from ..graph import PropertyGraph
from ..session import cut


def triangle_list(g: PropertyGraph) -> DataFrame:
    """(a, b, c) once per triangle. Edges point from lower to higher degree, which bounds the wedges by edges**1.5 even with hubs."""
    und = g.arcs("both").where("src < dst")
    deg = g.degrees()
    e = und.join(deg.toDF("src", "ds"), "src").join(deg.toDF("dst", "dd"), "dst")
    low = F.struct("ds", "src") < F.struct("dd", "dst")
    o = e.select(F.when(low, F.col("src")).otherwise(F.col("dst")).alias("a"), F.when(low, F.col("dst")).otherwise(F.col("src")).alias("b"))
    wedge = o.join(o.withColumnRenamed("b", "c"), "a").where("b < c")
    return wedge.join(und.toDF("b", "c"), ["b", "c"]).select("a", "b", "c")


def links(g: PropertyGraph, seed_ids: DataFrame | None = None) -> DataFrame:
    """(sg_id, degree, links): neighbours of each vertex and edges among them (the triangles through it)."""
    corner = triangle_list(g).select(F.explode(F.array("a", "b", "c")).alias("sg_id")).groupBy("sg_id").agg(F.count("*").alias("links"))
    base = g.vertices.select(F.col("id").alias("sg_id")) if seed_ids is None else seed_ids.withColumnRenamed("id", "sg_id")
    return base.join(g.degrees().withColumnRenamed("id", "sg_id"), "sg_id", "left").join(corner, "sg_id", "left").select("sg_id", F.coalesce("degree", F.lit(0)).alias("degree"), F.coalesce("links", F.lit(0)).alias("links"))


def with_lcc(counts: DataFrame) -> DataFrame:
    d = F.col("degree")
    return counts.select("sg_id", "degree", "links", F.when(d > 1, F.round(2 * F.col("links") / (d * (d - 1)), 6)).otherwise(0.0).alias("lcc"))


def lcc(g: PropertyGraph, seed_ids: DataFrame | None = None) -> DataFrame:
    return with_lcc(links(g, seed_ids))


def weak_ties(g: PropertyGraph, seed_ids: DataFrame | None = None) -> DataFrame:
    return links(g, seed_ids).select("sg_id", (F.expr("degree * (degree - 1) div 2") - F.col("links")).alias("n"))


def triangles(g: PropertyGraph, seed_ids: DataFrame | None = None) -> DataFrame:
    return links(g, seed_ids).select("sg_id", F.col("links").alias("n"))


def _zero(g: PropertyGraph, counts: DataFrame) -> DataFrame:
    return g.vertices.select(F.col("id").alias("sg_id")).join(counts, "sg_id", "left").select("sg_id", F.coalesce("n", F.lit(0)).alias("n"))


def feed_forward(g: PropertyGraph) -> DataFrame:
    """(sg_id, n) with sg_id as the source of a->b, b->c, a->c."""
    e = g.edges.select("src", "dst")
    two = e.toDF("a", "b").join(e.toDF("b", "c"), "b").where("a <> c")
    return _zero(g, two.join(e.toDF("a", "c"), ["a", "c"]).groupBy(F.col("a").alias("sg_id")).agg(F.count("*").alias("n")))


def feedback(g: PropertyGraph) -> DataFrame:
    e = g.edges.select("src", "dst")
    two = e.toDF("a", "b").join(e.toDF("b", "c"), "b").where("a <> c")
    return _zero(g, two.join(e.toDF("c", "a"), ["c", "a"]).groupBy(F.col("a").alias("sg_id")).agg(F.count("*").alias("n")))


def biparallel(g: PropertyGraph) -> DataFrame:
    e = g.edges.select("src", "dst")
    paths = e.toDF("a", "b").join(e.toDF("b", "d"), "b").where("a <> d").groupBy("a", "d").agg(F.count("*").alias("m"))
    return _zero(g, paths.groupBy(F.col("a").alias("sg_id")).agg(F.sum(F.expr("m * (m - 1) div 2")).alias("n")))


def ppr(members: DataFrame, induced: DataFrame, directed: bool, damping: float = 0.85, rounds: int = 10) -> DataFrame:
    """(sg_id, v, score) by power iteration in (sg_id, v) space."""
    arcs = induced.select("sg_id", "src", "dst")
    if not directed:
        arcs = arcs.unionAll(arcs.select("sg_id", F.col("dst").alias("src"), F.col("src").alias("dst")))
    out = arcs.groupBy("sg_id", "src").agg(F.count("*").alias("n"))
    arcs = cut(arcs.join(out, ["sg_id", "src"]).select("sg_id", F.col("src").alias("v"), "dst", "n"), "arcs")
    ids = members.select("sg_id", "v")
    home = ids.where("v = sg_id").select("sg_id", "v", F.lit(1 - damping).alias("x"))
    score = ids.select("sg_id", "v", (F.col("v") == F.col("sg_id")).cast("double").alias("s"))
    for r in range(rounds):
        # a vertex without an edge inside sends all it has to the centre; the state is read once a round
        sent = score.join(arcs, ["sg_id", "v"], "left").select("sg_id", F.coalesce("dst", "sg_id").alias("v"), (F.lit(damping) * F.col("s") / F.coalesce("n", F.lit(1))).alias("x"))
        gained = sent.unionAll(home).groupBy("sg_id", "v").agg(F.sum("x").alias("s"))
        score = cut(gained, "score") if r % 4 == 3 else gained
    score = ids.join(score, ["sg_id", "v"], "left").select("sg_id", "v", F.coalesce("s", F.lit(0.0)).alias("s"))
    return score.select("sg_id", "v", F.round("s", 6).alias("score"))


def ppr_walks(members: DataFrame, induced: DataFrame, directed: bool, n_walks: int = 200, steps: int = 20, salt: int = 7) -> DataFrame:
    """(sg_id, v, score) by seeded walkers, one join per step (a superstep per step, as a vertex-centric system would)."""
    arcs = induced.select("sg_id", "src", "dst")
    if not directed:
        arcs = arcs.unionAll(arcs.select("sg_id", F.col("dst").alias("src"), F.col("src").alias("dst")))
    nbrs = cut(arcs.groupBy("sg_id", F.col("src").alias("v")).agg(F.sort_array(F.collect_list("dst")).alias("to")), "nbrs")
    at = members.where("v = sg_id").select("sg_id", F.explode(F.sequence(F.lit(0), F.lit(n_walks - 1))).alias("r"), "v", F.array().cast("array<bigint>").alias("path"))
    x0 = F.expr(f"(48271 * pmod(sg_id, {P}) + 69621L * r + {salt}) % {P}")
    at = at.select("sg_id", "v", "path", F.when(x0 == 0, 1).otherwise(x0).alias("x"))
    for step in range(steps):
        at = at.withColumn("x", F.expr(f"48271 * x % {P}")).join(nbrs, ["sg_id", "v"], "left")
        home = (F.col("x") % 1000 < 150) | F.col("to").isNull()
        at = at.select("sg_id", F.when(home, F.col("sg_id")).otherwise(F.expr("get(to, cast((x div 1000) % size(to) as int))")).alias("v"), "path", "x").withColumn("path", F.array_append("path", F.col("v")))
        at = cut(at, "walkers") if step % 5 == 4 else at
    seen = at.select("sg_id", F.explode("path").alias("v")).groupBy("sg_id", "v").agg(F.count("*").alias("n"))
    return seen.select("sg_id", "v", F.round(F.col("n") / (n_walks * steps), 6).alias("score"))


def link_prediction(scores: DataFrame, g: PropertyGraph, top_k: int = 5) -> DataFrame:
    known = g.arcs("out").toDF("sg_id", "v")
    rest = scores.where("v <> sg_id").join(known, ["sg_id", "v"], "left_anti")
    rank = F.row_number().over(Window.partitionBy("sg_id").orderBy(F.desc("score"), "v"))
    return rest.withColumn("rank", rank).where(F.col("rank") <= top_k).select("sg_id", "v", "score", "rank")


def ego_betweenness(g: PropertyGraph, seed_ids: DataFrame) -> DataFrame:
    """Sum over unlinked pairs of neighbours of one over the two-step ways between them inside the subgraph."""
    arcs = g.arcs("both")
    near = seed_ids.toDF("sg_id").join(arcs.toDF("sg_id", "v"), "sg_id")
    inside = near.unionAll(seed_ids.select(F.col("id").alias("sg_id"), F.col("id").alias("v")))
    pairs = near.toDF("sg_id", "x").join(near.toDF("sg_id", "y"), "sg_id").where("x < y").join(arcs.toDF("x", "y"), ["x", "y"], "left_anti")
    ways = pairs.join(arcs.toDF("x", "z"), "x").join(arcs.toDF("z", "y"), ["z", "y"]).join(inside.toDF("sg_id", "z"), ["sg_id", "z"], "left_semi")
    each = ways.groupBy("sg_id", "x", "y").agg(F.count("*").alias("k"))
    total = each.groupBy("sg_id").agg(F.round(F.sum(1 / F.col("k")), 6).alias("betweenness"))
    return seed_ids.toDF("sg_id").join(total, "sg_id", "left").select("sg_id", F.coalesce("betweenness", F.lit(0.0)).alias("betweenness"))


def brokerage(g: PropertyGraph, seed_ids: DataFrame) -> DataFrame:
    """(sg_id, effective_size, efficiency)."""
    d, k = F.col("degree"), F.col("links")
    size = F.when(d > 0, d - 2 * k / d).otherwise(0.0)
    return links(g, seed_ids).select("sg_id", F.round(size, 6).alias("effective_size"), F.when(d > 0, F.round(size / d, 6)).otherwise(0.0).alias("efficiency"))


def constraint(g: PropertyGraph, seed_ids: DataFrame) -> DataFrame:
    """(sg_id, constraint): how much a centre's ties lead back to its own neighbours. Each neighbour j counts (share spent on j
    directly, plus through every neighbour q that knows j)^2; q spreads its ties over the centre and its neighbours inside."""
    arcs = g.arcs("both").where("src <> dst")
    near = seed_ids.toDF("sg_id").join(arcs.toDF("sg_id", "v"), "sg_id")
    inside = near.toDF("sg_id", "q").join(arcs.toDF("q", "j"), "q").join(near.toDF("sg_id", "j"), ["sg_id", "j"]).select("sg_id", "q", "j")
    ties = inside.groupBy("sg_id", "q").agg(F.count("*").alias("k"))
    by_way = inside.join(ties, ["sg_id", "q"]).groupBy("sg_id", "j").agg(F.sum(1 / (1 + F.col("k"))).alias("x"))
    d = near.groupBy("sg_id").agg(F.count("*").alias("d"))
    each = near.withColumnRenamed("v", "j").join(d, "sg_id").join(by_way, ["sg_id", "j"], "left").select("sg_id", ((1 + F.coalesce("x", F.lit(0.0))) / F.col("d")).alias("p"))
    total = each.groupBy("sg_id").agg(F.round(F.sum(F.col("p") * F.col("p")), 6).alias("c"))
    return seed_ids.toDF("sg_id").join(total, "sg_id", "left").select("sg_id", F.coalesce("c", F.lit(0.0)).alias("constraint_"))


def density(members: DataFrame, induced: DataFrame, directed: bool = False) -> DataFrame:
    """(sg_id, n_vertices, n_edges, density): edges over the pairs of vertices."""
    n = members.groupBy("sg_id").agg(F.count("*").alias("n_vertices")).join(induced.groupBy("sg_id").agg(F.count("*").alias("n_edges")), "sg_id", "left")
    e, v = F.coalesce("n_edges", F.lit(0)), F.col("n_vertices")
    return n.select("sg_id", "n_vertices", e.alias("n_edges"), F.when(v > 1, F.round((1 if directed else 2) * e / (v * (v - 1)), 6)).otherwise(0.0).alias("density"))


def ego_features(members: DataFrame, induced: DataFrame) -> DataFrame:
    n = members.groupBy("sg_id").agg(F.count("*").alias("n_vertices"))
    e = induced.groupBy("sg_id").agg(F.count("*").alias("n_edges"), F.sum("weight").alias("weight"))
    z = lambda c: F.coalesce(c, F.lit(0))
    return n.join(e, "sg_id", "left").select("sg_id", "n_vertices", z("n_edges").alias("n_edges"), z("weight").alias("weight"), F.when(z("n_edges") > 0, F.round(F.col("weight") / F.col("n_edges"), 6)).otherwise(0.0).alias("mean_weight"))


def pattern_counts(g: PropertyGraph, pattern: list[tuple[int, int]]) -> DataFrame:
    """(sg_id, n): occurrences of an undirected pattern with node 0 at sg_id, a join an edge; each set of mapped edges once."""
    arcs = g.arcs("both")
    rows, bound = g.vertices.select(F.col("id").alias("n0")), {0}
    todo = list(pattern)
    while todo:
        a, b = next(e for e in todo if e[0] in bound or e[1] in bound)
        todo.remove((a, b))
        if a in bound and b in bound:
            rows = rows.join(arcs.toDF(f"n{a}", f"n{b}"), [f"n{a}", f"n{b}"], "left_semi")
            continue
        old, new = (a, b) if a in bound else (b, a)
        rows = rows.join(arcs.toDF(f"n{old}", f"n{new}"), f"n{old}")
        for x in bound:
            rows = rows.where(f"n{x} <> n{new}")
        bound.add(new)
    edges = F.sort_array(F.array(*(F.struct(F.least(f"n{a}", f"n{b}").alias("a"), F.greatest(f"n{a}", f"n{b}").alias("b")) for a, b in pattern)))
    return _zero(g, rows.select(F.col("n0").alias("sg_id"), edges.alias("e")).distinct().groupBy("sg_id").agg(F.count("*").alias("n")))


def pair_scores(g: PropertyGraph, pairs: DataFrame) -> DataFrame:
    """(a, b, common, jaccard, adamic_adar) of the neighbour sets of pairs."""
    arcs, deg = g.arcs("both"), g.degrees()
    common = pairs.join(arcs.toDF("a", "z"), "a").join(arcs.toDF("b", "z"), ["b", "z"]).join(deg.toDF("z", "dz"), "z")
    both = common.groupBy("a", "b").agg(F.count("*").alias("common"), F.sum(1 / F.log("dz")).alias("aa"))
    full = pairs.join(both, ["a", "b"], "left").join(deg.toDF("a", "da"), "a").join(deg.toDF("b", "db"), "b")
    c = F.coalesce("common", F.lit(0))
    return full.select("a", "b", c.alias("common"), F.round(c / (F.col("da") + F.col("db") - c), 6).alias("jaccard"), F.round(F.coalesce("aa", F.lit(0.0)), 6).alias("adamic_adar"))


def cascade(steps: DataFrame, hours: int = 24, k: int = 2) -> DataFrame:
    """(seed, reached, hop): users reached along steps (ts, src, dst) of ascending time, each step within so many hours of the one before."""
    now = steps.select(F.col("src").alias("seed"), F.col("dst").alias("at"), "ts", F.lit(1).alias("hop"))
    out = now
    for hop in range(2, k + 1):
        s = steps.toDF("ts2", "at", "dst2")
        now = now.drop("hop").join(s, "at").where((F.col("ts2") > F.col("ts")) & (F.col("ts2") <= F.col("ts") + F.expr(f"interval {hours} hours")))
        now = now.groupBy("seed", F.col("dst2").alias("at")).agg(F.min("ts2").alias("ts")).withColumn("hop", F.lit(hop))
        out = out.unionByName(now.select("seed", "at", "ts", "hop"))
    return out.where("seed <> at").groupBy("seed", F.col("at").alias("reached")).agg(F.min("hop").cast("bigint").alias("hop"))
