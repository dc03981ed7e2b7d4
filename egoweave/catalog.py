"""The registered queries of the engine, each with an independent SQL formulation where there is one."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import metrics, workloads
from .functions import bitmaps, minhash, surfaces
from .functions.minhash import A, B, P, coefficients
from .graph import PropertyGraph
from .operators import baselines, engine, iterate, kernels, packing, programs, relational, resolution, sampling
from .plans import extract
from .session import cut, ship
from .sources import graphs, gridsource
from .spec import AttributeSpec, ExecOptions, ListSpec, NeighborhoodSpec, PackOptions, PairSpec, parse_spec

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}

SEED_RULE = "p_size > 45"
CAPACITY, MAX_ITEMS = 90, 12


def query(name: str, sql: str | None = None):
    def keep(fn):
        def call(spark: SparkSession, sf_dir: str) -> DataFrame:
            return fn(ship(spark), sf_dir)

        QUERIES[name] = call
        if sql:
            SQL[name] = sql
        return fn

    return keep


# ---------------------------------------------------------------- SQL building blocks

_PAIRS = "select distinct a.l_partkey as src, b.l_partkey as dst from lineitem a join lineitem b on a.l_orderkey = b.l_orderkey and a.l_partkey < b.l_partkey"
RET = f"ret as ({_PAIRS} where a.l_returnflag = 'R' and b.l_returnflag = 'R'), arc as (select src, dst from ret union all select dst, src from ret)"
SEED = f"seed as (select p_partkey as id from part where {SEED_RULE} and p_partkey in (select src from arc))"
MEM = "mem as (select id as sg_id, id as v, 0 as hop from seed union all select id, dst, 1 from seed join arc on id = src)"
MEM2 = MEM + ", mem2 as (select sg_id, v, min(hop) as hop from (select * from mem union all select m.sg_id, a.dst, 2 from mem m join arc a on a.src = m.v) group by 1, 2)"
DEG = "deg as (select src as id, count(*) as degree from arc group by 1)"
TRI = "tri as (select x.src as a, x.dst as b, y.dst as c from ret x join ret y on x.dst = y.src join ret z on z.src = x.src and z.dst = y.dst), cor as (select id as sg_id, count(*) as links from (select a as id from tri union all select b from tri union all select c from tri) group by 1)"
SIGN = "sig as (select sg_id, " + ", ".join(f"min(({A[i]} * (v % {P}) + {B[i]}) % {P}) as s{i + 1}" for i in range(6)) + " from mem group by 1)"
NEXT = "nxt as (select distinct src, dst from (select l_partkey as src, lead(l_partkey) over (partition by l_orderkey order by l_linenumber, l_partkey, l_suppkey) as dst from lineitem) where dst is not null and src <> dst)"
HAND = "hand as (select src, dst, count(*) as weight from (select user_id as src, lead(user_id) over (order by ts, event_id) as dst from events) where dst is not null and src <> dst group by 1, 2)"
KIND = "kin as (select r.src, r.dst from ret r join part a on a.p_partkey = r.src join part b on b.p_partkey = r.dst where a.p_brand = b.p_brand and a.p_type = b.p_type)"


def W(*parts: str, recursive: bool = False) -> str:
    return ("with recursive " if recursive else "with ") + ", ".join(parts) + " "


# ---------------------------------------------------------------- shared inputs


def part_graph(spark: SparkSession, d: str) -> PropertyGraph:
    """The returned graph with part attributes on its vertices; its edges are written once, as several readers follow."""
    return graphs.with_parts(spark, d, graphs.kept(graphs.returned(spark, d)))


def default_members(spark: SparkSession, d: str, k: int = 1, g: PropertyGraph | None = None) -> DataFrame:
    return extract.khop_members(g or part_graph(spark, d), NeighborhoodSpec(SEED_RULE, k)).withColumn("w", F.lit(1).cast("bigint"))


def plan(spark: SparkSession, d: str, order: str = "sketch", **kw) -> tuple[PropertyGraph, DataFrame, DataFrame]:
    """Graph, weighted members and assignment of the default query, each written once, as several readers follow."""
    g = part_graph(spark, d)
    members = cut(default_members(spark, d, g=g), "members")
    placed = packing.pack(members, PackOptions(capacity=kw.pop("capacity", CAPACITY), max_items=kw.pop("max_items", MAX_ITEMS), order=order, **kw))
    return g, members, cut(packing.numbered(placed), "assignment")


# ---------------------------------------------------------------- graphs

for _name, _sql in {
    "graph_returned_edges": W(RET) + "select src, dst from ret",
    "graph_copurchase_edges": _PAIRS,
    "graph_nextline_edges": W(NEXT) + "select src, dst from nxt",
    "graph_handoff_edges": W(HAND) + "select src, dst, weight from hand",
    "graph_supplier_part_edges": "select distinct 2 * l_partkey as src, 2 * l_suppkey + 1 as dst from lineitem",
    "graph_customer_part_edges": "select distinct 2 * o_custkey as src, 2 * l_partkey + 1 as dst from lineitem join orders on l_orderkey = o_orderkey",
    "graph_customer_supplier_edges": "select distinct 2 * o_custkey as src, 2 * l_suppkey + 1 as dst from lineitem join orders on l_orderkey = o_orderkey",
    "graph_customer_order_edges": "select distinct 2 * o_custkey as src, 2 * o_orderkey + 1 as dst from orders",
    "graph_user_key_edges": "select distinct 2 * user_id as src, 2 * cast(json_extract_string(props, '$.k') as bigint) + 1 as dst from events where json_extract_string(props, '$.k') is not null",
    "graph_same_kind_edges": W(RET, KIND) + "select src, dst from kin",
}.items():
    _of = {"graph_nextline_edges": "next_line", "graph_same_kind_edges": "returned_same_kind"}.get(_name, _name[6:-6])
    query(_name, _sql)(lambda s, d, of=_of: graphs.GRAPHS[of](s, d).edges)


@query("graph_host_links", "select distinct regexp_extract(url, '^[a-z]+://([^/?#]*)', 1) as host, unnest(regexp_extract_all(html, 'href=\"(/[^\"]*)\"', 1)) as target from pages")
def _(s, d):
    return graphs.host_links(s, d)


@query("graph_doc_shared_lines", "with l as (select distinct doc_id, line from (select doc_id, unnest(string_split(text, chr(10))) as line from documents) where length(line) >= 40) select distinct a.doc_id as src, b.doc_id as dst from l a join l b on a.line = b.line and a.doc_id < b.doc_id")
def _(s, d):
    return graphs.shared_lines(s, d).edges


@query("graph_embedding_neighbors", "select a.vec_id as src, b.vec_id as dst from embeddings a join embeddings b on a.vec_id < b.vec_id where list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda x: x[1]::double * x[2]::double)) > 0.3")
def _(s, d):
    return graphs.similar_vectors(s, d).edges


@query("graph_adjacency_lists", W(RET) + "select src as id, count(*) as degree, list_sort(list(dst)) as nbrs from arc group by 1")
def _(s, d):
    return graphs.returned(s, d).adjacency()


@query("graph_degree_table", W(RET, DEG) + "select id, degree from deg")
def _(s, d):
    return graphs.returned(s, d).degrees()


@query("graph_stats_row", W(RET, DEG, TRI) + "select count(*) as n_vertices, (select count(*) from ret) as n_edges, round(avg(degree), 6) as mean_degree, round(avg(case when degree > 1 then 2.0 * coalesce(links, 0) / (degree * (degree - 1)) else 0 end), 6) as mean_lcc, (select count(*) from tri) as n_triangles from deg left join cor on id = sg_id")
def _(s, d):
    return metrics.dataset_stats(graphs.returned(s, d))


_BA = """with recursive ids as (select id, row_number() over (order by id) - 1 as r from (select distinct s_suppkey as id from supplier where s_suppkey is not null)), st as (select 1::bigint as v, 0::bigint as j, (1 * 48271 + 11)::bigint as x, []::bigint[] as ends, []::bigint[] as picked, []::struct(a bigint, b bigint)[] as edges
 union all select case when j + 1 < least(4, v) then v else v + 1 end, case when j + 1 < least(4, v) then j + 1 else 0 end, nx,
  case when j + 1 < least(4, v) then ends else list_concat(ends, flatten(list_transform(list_sort(list_distinct(list_append(picked, u))), lambda w: [w, v]))) end,
  case when j + 1 < least(4, v) then list_append(picked, u) else [] end,
  case when j + 1 < least(4, v) then edges else list_concat(edges, list_transform(list_distinct(list_append(picked, u)), lambda w: {'a': w, 'b': v})) end
 from (select *, case when not list_contains(picked, t) then t else nx % v end as u from (select *, case when len(ends) > 0 then ends[1 + nx % len(ends)] else 0 end as t from (select *, x * 48271 % 2147483647 as nx from st where v < (select count(*) from ids)))))
select distinct x.id as src, y.id as dst from (select unnest(edges) as e from st where v = (select count(*) from ids)) join ids x on x.r = least(e.a, e.b) join ids y on y.r = greatest(e.a, e.b)"""


@query("graph_ba_edges", _BA)
def _(s, d):
    return graphs.attached(graphs.table(s, d, "supplier").select(F.col("s_suppkey").alias("id")), 4, 1).edges


# ---------------------------------------------------------------- extraction

_MEM_SQL = W(RET, SEED, MEM)


@query("extract_hop1_members", _MEM_SQL + "select sg_id, v, hop from mem")
def _(s, d):
    return extract.khop_members(part_graph(s, d), NeighborhoodSpec(SEED_RULE))


@query("extract_hop2_members", W(RET, SEED, MEM2) + "select sg_id, v, hop from mem2")
def _(s, d):
    return extract.khop_members(part_graph(s, d), NeighborhoodSpec(SEED_RULE, 2))


@query("extract_hop3_members", W(RET, SEED, MEM2) + ", mem3 as (select sg_id, v, min(hop) as hop from (select * from mem2 union all select m.sg_id, a.dst, 3 from mem2 m join arc a on a.src = m.v) group by 1, 2) select sg_id, v, hop from mem3")
def _(s, d):
    return extract.khop_members(part_graph(s, d), NeighborhoodSpec(SEED_RULE, 3))


_RULED = NeighborhoodSpec(SEED_RULE, 2, v_pred="p_retailprice > 950")
_PASS = "pas as (select p_partkey as v from part where p_retailprice > 950)"


@query("extract_prefilter", W(RET, SEED, _PASS) + ", h1 as (select id as sg_id, dst as v from seed join arc on id = src where dst in (select v from pas)), r as (select id as sg_id, id as v, 0 as hop from seed union all select sg_id, v, 1 from h1 union all select sg_id, dst, 2 from h1 join arc on src = v where dst in (select v from pas)) select sg_id, v, min(hop) as hop from r group by 1, 2")
def _(s, d):
    return extract.khop_members(part_graph(s, d), _RULED)


@query("extract_postfilter", W(RET, SEED, MEM2, _PASS) + "select sg_id, v, hop from mem2 where v = sg_id or v in (select v from pas)")
def _(s, d):
    from dataclasses import replace

    return extract.khop_members(part_graph(s, d), replace(_RULED, filter_mode="post"))


_PASS_MORE = "pas as (select p_partkey as v from part where p_retailprice > 930)"


@query("extract_drop_center", W(RET, SEED, _PASS_MORE) + ", sd as (select id from seed where id in (select v from pas)) select id as sg_id, id as v, 0 as hop from sd union all select id, dst, 1 from sd join arc on id = src where dst in (select v from pas)")
def _(s, d):
    return extract.khop_members(part_graph(s, d), NeighborhoodSpec(SEED_RULE, 1, v_pred="p_retailprice > 930", keep_center=False))


@query("extract_edge_rule", W(HAND) + ", sd as (select user_id as id from events group by 1 having count(*) > 60 and user_id in (select src from hand union select dst from hand)) select id as sg_id, id as v, 0 as hop from sd union all select id, dst, 1 from sd join hand on id = src where weight > 2")
def _(s, d):
    g = graphs.handoff(s, d)
    n = graphs.table(s, d, "events").groupBy(F.col("user_id").alias("id")).agg(F.count("*").alias("n"))
    return extract.khop_members(PropertyGraph(g.vertices.join(n, "id"), g.edges, True), NeighborhoodSpec("n > 60", 1, e_pred="weight > 2"))


@query("extract_induced_edges", _MEM_SQL + "select a.sg_id, src, dst from mem a join ret on a.v = src join mem b on b.sg_id = a.sg_id and b.v = dst")
def _(s, d):
    return extract.induced_edges(default_members(s, d), part_graph(s, d))


@query("extract_weights", W(RET, DEG) + "select id, 1 + degree as w from deg")
def _(s, d):
    return extract.vertex_weights(graphs.returned(s, d), "degree")


@query("extract_sizes", W(RET, DEG, SEED, MEM) + "select sg_id, count(*) as n_vertices, cast(sum(1 + degree) as bigint) as load from mem join deg on id = v group by 1")
def _(s, d):
    g = part_graph(s, d)
    return extract.subgraph_sizes(extract.attach_weights(default_members(s, d).drop("w"), extract.vertex_weights(g, "degree")))


@query("extract_attribute_groups", "select p_brand as sg_id, p_partkey as v, 0 as hop from part where p_brand is not null")
def _(s, d):
    p = graphs.table(s, d, "part").withColumnRenamed("p_partkey", "id")
    return extract.attribute_members(PropertyGraph(p, p.select(F.col("id").alias("src"), F.col("id").alias("dst"))), AttributeSpec("p_brand"))


@query("extract_sample_seeds", W(RET) + f"select id from (select distinct src as id from arc) order by ({A[0]} * (id % {P}) + {B[0]}) % {P}, id limit 25")
def _(s, d):
    return extract.sample_seeds(graphs.returned(s, d), 25)


_PAIRSQL = "prs as (select src as a, dst as b from ret), ball as (select src as c, dst as v from arc union select src, src from arc)"


def _pair_spec(s, d, op):
    g = graphs.kept(graphs.returned(s, d))
    return extract.pair_members(g, PairSpec(extract.edge_pairs(g), 1, op))


@query("extract_pair_union", W(RET, _PAIRSQL) + "select a, b, v from prs join ball on c = a union select a, b, v from prs join ball on c = b")
def _(s, d):
    return _pair_spec(s, d, "union")


@query("extract_pair_intersection", W(RET, _PAIRSQL) + "select a, b, x.v from prs join ball x on x.c = a join ball y on y.c = b and y.v = x.v")
def _(s, d):
    return _pair_spec(s, d, "intersection")


@query("extract_directed_in", W(NEXT) + ", ids as (select src as id from nxt union select dst from nxt), sd as (select p_partkey as id from part where p_size > 45 and p_partkey in (select id from ids)) select id as sg_id, id as v, 0 as hop from sd union all select id, src, 1 from sd join nxt on dst = id")
def _(s, d):
    g = graphs.next_line(s, d)
    part = graphs.table(s, d, "part").withColumnRenamed("p_partkey", "id").join(g.vertices, "id", "left_semi")
    return extract.khop_members(PropertyGraph(part, g.edges, True), NeighborhoodSpec(SEED_RULE, 1, direction="in"))


@query("extract_both_strategies_agree", "select cast(0 as bigint) as differences")
def _(s, d):
    g, spec = part_graph(s, d), NeighborhoodSpec(SEED_RULE, 2)
    a, b = extract.khop_members(g, spec), extract.local_members(g, spec)
    return a.exceptAll(b).unionAll(b.exceptAll(a)).agg(F.count("*").alias("differences"))


@query("extract_chosen_strategy", W(RET, SEED, MEM2) + "select sg_id, v, hop from mem2")
def _(s, d):
    """Members by the strategy that the counted sizes call for."""
    return extract.members(part_graph(s, d), NeighborhoodSpec(SEED_RULE, 2))


@query("extract_projected", _MEM_SQL + "select sg_id, v, hop, p_brand, p_size from mem join part on p_partkey = v")
def _(s, d):
    return extract.project(default_members(s, d).drop("w"), part_graph(s, d), NeighborhoodSpec(attrs_v=("p_brand", "p_size")))[0]


@query("extract_by_rule_text", _MEM_SQL + "select sg_id, v, hop from mem")
def _(s, d):
    return extract.khop_members(part_graph(s, d), parse_spec(f"seed {SEED_RULE}; hops 1; direction out"))


@query("extract_byte_weights", W(RET, DEG) + "select id, 16 + 8 + octet_length(encode(p_brand)) + degree * 8 as w from deg join part on p_partkey = id")
def _(s, d):
    return extract.vertex_weights(part_graph(s, d), "bytes", ("p_brand", "p_retailprice"))


@query("extract_vertex_lists", "select distinct o_custkey as sg_id, l_partkey as v, 0 as hop from orders join lineitem on o_orderkey = l_orderkey")
def _(s, d):
    rows = graphs.table(s, d, "orders").join(graphs.table(s, d, "lineitem"), F.expr("o_orderkey = l_orderkey"))
    return extract.list_members(ListSpec(rows.select(F.col("o_custkey").alias("sg_id"), F.col("l_partkey").alias("v"))))


@query("extract_stage1_fanout_count", W(RET) + "select count(*) + (select count(distinct src) from arc) as n from arc")
def _(s, d):
    g = graphs.returned(s, d)
    return extract.hop_join(g.vertices.select(F.col("id").alias("sg_id"), F.col("id").alias("v")), g.arcs()).unionAll(g.vertices.select("id", "id")).agg(F.count("*").alias("n"))


@query("extract_edge_membership", _MEM_SQL + "select src, dst, list_sort(list(a.sg_id)) as sgs from mem a join ret on a.v = src join mem b on b.sg_id = a.sg_id and b.v = dst group by 1, 2")
def _(s, d):
    return extract.edge_membership(default_members(s, d), part_graph(s, d))


# ---------------------------------------------------------------- signatures

_SIG_SQL = W(RET, SEED, MEM, SIGN)


@query("sketch_signatures", _SIG_SQL + "select * from sig")
def _(s, d):
    return minhash.sketch(default_members(s, d))


@query("sketch_order_ranks", _SIG_SQL + "select sg_id, row_number() over (order by s1, s2, s3, s4, s5, s6, sg_id) as rank from sig")
def _(s, d):
    return minhash.sketch_order(minhash.sketch(default_members(s, d)))


@query("sketch_bucket_sizes", _SIG_SQL + "select s1 % 6 as bucket, count(*) as n from sig group by 1")
def _(s, d):
    return minhash.bucket_by_hash(minhash.sketch(default_members(s, d)), 6).groupBy("bucket").agg(F.count("*").alias("n"))


def _sign(n: int) -> str:
    return "sig as (select sg_id, " + ", ".join(f"min(({a} * (v % {P}) + {b}) % {P}) as s{i + 1}" for i, (a, b) in enumerate(map(coefficients, range(n)))) + " from mem group by 1)"


@query("sketch_ten_hashes", W(RET, SEED, MEM, _sign(10)) + "select * from sig")
def _(s, d):
    return minhash.sketch(default_members(s, d), 10)


@query("sketch_buckets_of_four_values", _SIG_SQL + f"select ((((s1 * 31 + s2) % {P}) * 31 + s3) % {P} * 31 + s4) % {P} % 6 as bucket, count(*) as n from sig group by 1")
def _(s, d):
    return minhash.bucket_by_hash(minhash.sketch(default_members(s, d)), 6, 4).groupBy("bucket").agg(F.count("*").alias("n"))


@query("sketch_merge_check", "select cast(0 as bigint) as differences")
def _(s, d):
    m = default_members(s, d)
    a = minhash.as_array(minhash.sketch(m)).withColumn("g", F.expr("sg_id div 100"))
    merged = a.groupBy("g").agg(F.collect_list("s").alias("x")).select("g", F.aggregate(F.slice("x", 2, 1 << 20), F.get("x", F.lit(0)), minhash.merge).alias("s"))
    direct = minhash.as_array(minhash.sketch(m.select(F.expr("sg_id div 100").alias("sg_id"), "v"))).toDF("g", "t")
    return merged.join(direct, "g", "full").where("s is null or t is null or s <> t").agg(F.count("*").alias("differences"))


_EQ = " + ".join(f"(a.s{i}=b.s{i})::int" for i in range(1, 7))
_LSH = "lsh as (select a.sg_id as a, b.sg_id as b, round((" + _EQ + ") / 6.0, 6) as estimate from sig a join sig b on a.sg_id < b.sg_id and ((a.s1=b.s1 and a.s2=b.s2) or (a.s3=b.s3 and a.s4=b.s4) or (a.s5=b.s5 and a.s6=b.s6)))"


@query("lsh_candidate_pairs", _SIG_SQL + ", " + _LSH + " select a, b from lsh")
def _(s, d):
    return minhash.lsh_pairs(minhash.sketch(default_members(s, d)), 3)


_INTER = "it as (select a.sg_id as a, b.sg_id as b, count(*) as n from mem a join mem b on a.v = b.v and a.sg_id < b.sg_id group by 1, 2), sz as (select sg_id, count(*) as n from mem group by 1)"


@query("sketch_similarity_vs_exact", _SIG_SQL + ", " + _LSH + ", " + _INTER + " select l.a, l.b, estimate, round(coalesce(it.n, 0) / (x.n + y.n - coalesce(it.n, 0)), 6) as exact from lsh l join sz x on x.sg_id = l.a join sz y on y.sg_id = l.b left join it on it.a = l.a and it.b = l.b")
def _(s, d):
    m = default_members(s, d)
    sk = minhash.sketch(m)
    pairs = minhash.lsh_pairs(sk, 3)
    arr = minhash.as_array(sk)
    est = pairs.join(arr.toDF("a", "sa"), "a").join(arr.toDF("b", "sb"), "b").select("a", "b", F.round(minhash.similarity(F.col("sa"), F.col("sb")), 6).alias("estimate"))
    return est.join(minhash.jaccard(m, pairs), ["a", "b"]).select("a", "b", "estimate", F.round("jaccard", 6).alias("exact"))


@query("jaccard_neighbor_pairs", _SIG_SQL + ", " + _INTER + ", rk as (select sg_id, row_number() over (order by s1, s2, s3, s4, s5, s6, sg_id) as r from sig) select p.sg_id as a, q.sg_id as b, coalesce(it.n, 0) as inter, round(coalesce(it.n, 0) / (x.n + y.n - coalesce(it.n, 0)), 6) as jaccard from rk p join rk q on q.r = p.r + 1 join sz x on x.sg_id = p.sg_id join sz y on y.sg_id = q.sg_id left join it on it.a = least(p.sg_id, q.sg_id) and it.b = greatest(p.sg_id, q.sg_id)")
def _(s, d):
    m = default_members(s, d)
    rk = minhash.sketch_order(minhash.sketch(m))
    pairs = rk.toDF("a", "r").join(rk.select(F.col("sg_id").alias("b"), (F.col("rank") - 1).alias("r")), "r").select("a", "b")
    return minhash.jaccard(m, pairs).withColumn("jaccard", F.round("jaccard", 6))


# ---------------------------------------------------------------- packing


def _greedy_sql(order: str, cap: int = CAPACITY, items: int | None = MAX_ITEMS, overlap: bool = True, bucket: str = "0", out: str = "select c as sg_id, b as bin_id from st where c >= 0") -> str:
    """Greedy placement as a recursion over the ranked subgraphs with a list of open bins as state."""
    size = "len(list_distinct(list_concat(x.vs, nx.vs)))" if overlap else "len(x.vs) + len(nx.vs)"
    grown = "list_distinct(list_concat(x.vs, o.vs))" if overlap else "list_concat(x.vs, o.vs)"
    few = f"x.n < {items} and " if items else ""
    return W(RET, SEED, MEM, SIGN, recursive=True) + f""", o as (select row_number() over (partition by {bucket} order by {order}) as i, {bucket} as k, sg_id as c, vs from sig join (select sg_id, list(v) as vs, count(*) as load from mem group by 1) using (sg_id)),
st as (select distinct 0::bigint as i, k, []::struct(vs bigint[], n int)[] as bins, -1::bigint as c, -1::bigint as b from o
 union all select o.i, o.k, case when j is null then list_append(bins, {{'vs': o.vs, 'n': 1}}) else list_transform(bins, lambda x, m: case when m = j then {{'vs': {grown}, 'n': x.n + 1}} else x end) end, o.c, coalesce(j, len(bins) + 1)
 from (select st.i, st.k, st.bins, list_position(list_transform(st.bins, lambda x: {few}{size} <= {cap}), true) as j from st join o nx on nx.i = st.i + 1 and nx.k = st.k) z join o on o.i = z.i + 1 and o.k = z.k) """ + out


_SKETCH = "s1, s2, s3, s4, s5, s6, sg_id"
for _name, _order, _sort, _kw in (
    ("pack_arrival", "arrival", "sg_id", {}),
    ("pack_size_desc", "size_desc", "load desc, sg_id", {}),
    ("pack_sketch_order", "sketch", _SKETCH, {}),
    ("pack_no_overlap", "arrival", "sg_id", {"overlap": False}),
    ("pack_item_cap", "arrival", "sg_id", {"max_items": 3}),
):
    query(_name, _greedy_sql(_sort, items=_kw.get("max_items", MAX_ITEMS), overlap=_kw.get("overlap", True)))(lambda s, d, o=_order, kw=_kw: plan(s, d, o, **kw)[2].select("sg_id", "bin_id"))


@query("pack_sketch_distributed", _greedy_sql(_SKETCH, bucket="s1 % 6", out="select k as bucket, c as sg_id, b as local from st where c >= 0"))
def _(s, d):
    return packing.pack(default_members(s, d), PackOptions(CAPACITY, MAX_ITEMS, n_buckets=6)).select("bucket", "sg_id", "local")


_ZEROS = "select unnest(['subgraph in one bin', 'bin within capacity', 'items within cap', 'one owner']) as rule, cast(0 as bigint) as violations"


@query("pack_merge_underfilled_audit", _ZEROS)
def _(s, d):
    opts = PackOptions(300, None, n_buckets=6)
    m = cut(default_members(s, d), "members")
    a = cut(packing.numbered(packing.pack(m, opts)), "assignment")
    return packing.audit(m, cut(packing.merge_underfilled(m, a, opts), "merged"), 300)


for _name, _alg in (("pack_agglomerative_audit", "agglomerative"), ("pack_kmeans_audit", "kmeans")):
    query(_name, _ZEROS)(lambda s, d, a=_alg: packing.audit(*plan(s, d, algorithm=a)[1:], CAPACITY, MAX_ITEMS))


def _grow_audit(s, d, opts, parts=packing.balanced_parts):
    g, m = part_graph(s, d), cut(default_members(s, d), "members")
    grown = packing.pack_partition_grow(g, m, 40, opts, cut(parts(g, 40), "parts"))
    return packing.audit(m, cut(grown, "grown"), CAPACITY, MAX_ITEMS)


@query("pack_partition_grow_audit", _ZEROS)
def _(s, d):
    return _grow_audit(s, d, PackOptions(CAPACITY, MAX_ITEMS))


@query("pack_partition_grow_buckets_audit", _ZEROS)
def _(s, d):
    """The audit where grown parts are placed in several buckets."""
    return _grow_audit(s, d, PackOptions(CAPACITY, MAX_ITEMS, n_buckets=6))


@query("pack_grown_parts_audit", _ZEROS)
def _(s, d):
    """The audit where disjoint parts are grown directly from start vertices."""
    return _grow_audit(s, d, PackOptions(CAPACITY, MAX_ITEMS), packing.grow_parts)


@query("pack_sampled_oversized", "select cast(0 as bigint) as over, (select count(*) from (" + W(RET, SEED) + "select id from seed)) as n_sg")
def _(s, d):
    """Subgraphs over a capacity of 20 are sampled down to it, so no bin is over."""
    kept = cut(sampling.fit(cut(default_members(s, d), "members"), 20), "sampled")
    a = packing.numbered(packing.pack(kept, PackOptions(20, None)))
    return packing.bins(kept, a).agg(F.sum((F.col("load") > 20).cast("bigint")).alias("over"), F.sum("n_sg").alias("n_sg"))


#: Distances of all pairs within the window in signature order that one bin can take, as whole numbers of millionths.
_NEAR = "rk as (select sg_id, row_number() over (order by s1, s2, s3, s4, s5, s6, sg_id) as r from sig), pr as (select a.r as i, b.r as j, a.sg_id as x, b.sg_id as y from rk a join rk b on b.r > a.r and b.r <= a.r + 8), sh as (select x, y, count(*) as n from pr join mem m on m.sg_id = x join mem q on q.sg_id = y and q.v = m.v group by 1, 2), sz as (select sg_id, count(*) as n from mem group by 1), ds as (select i, j, pr.x, pr.y, coalesce(sh.n, 0) as n, p.n + q.n - coalesce(sh.n, 0) as u from pr left join sh on sh.x = pr.x and sh.y = pr.y join sz p on p.sg_id = pr.x join sz q on q.sg_id = pr.y)"


@query("pack_one_agglomerative_round", W(RET, SEED, MEM, SIGN, recursive=True) + f", {_NEAR}, ok as (select * from ds where u <= {CAPACITY} and 1 - n::double / u < 0.9), gr as (select i, list({{'d': 1 - n::double / u, 'j': j}} order by 1 - n::double / u, j) as c from ok group by 1), nn as (select max(r) as n from rk), st as (select 0::bigint as i, []::bigint[] as taken, []::struct(a bigint, b bigint)[] as won union all select st.i + 1, case when pick is null then taken else list_append(taken, pick) end, case when pick is null then won else list_append(won, {{'a': st.i + 1, 'b': pick}}) end from (select st.*, case when list_contains(st.taken, st.i + 1) then null else list_filter(gr.c, lambda e: not list_contains(st.taken, e.j))[1].j end as pick from st left join gr on gr.i = st.i + 1) st, nn where st.i < nn.n), fin as (select unnest(won) as e from st, nn where i = nn.n) select p.sg_id as first, q.sg_id as joined from fin join rk p on p.r = e.a join rk q on q.r = e.b")
def _(s, d):
    """One pass of the agglomerative packer over all subgraphs in signature order: who joins whom, window 8, distance under 0.9."""
    return packing.merge_round(default_members(s, d), CAPACITY, 8, 0.9)


@query("pack_kmeans_first_pass", W(RET, SEED, MEM) + f", k as (select cast(ceil(count(*) / {CAPACITY}.0) as bigint) as k from mem), h as (select id, row_number() over (order by ({A[0]} * (id % {P}) + {B[0]}) % {P}, id) as r from seed) select id as sg_id, r - 1 as cluster from h, k where r <= k")
def _(s, d):
    """The start sets of the k-means packer, one a cluster, k from summed sizes and capacity; the rest of the pass is held against its objective in tests."""
    return packing.kmeans_starts(default_members(s, d), CAPACITY)


@query("pack_bin_loads", _greedy_sql(_SKETCH, out=", asg as (select c as sg_id, b as bin_id from st where c >= 0) select bin_id, count(distinct v) as load, count(distinct sg_id) as n_sg, count(distinct v) as n_vertices from asg join mem using (sg_id) group by 1"))
def _(s, d):
    _, m, a = plan(s, d)
    return packing.bins(m, a)


@query("pack_overlap_saving", _greedy_sql(_SKETCH, out=", asg as (select c as sg_id, b as bin_id from st where c >= 0), u as (select bin_id, count(distinct v) as load, count(*) as total from asg join mem using (sg_id) group by 1) select count(*) as n_bins, cast(sum(total) as bigint) as total_size, cast(sum(load) as bigint) as total_load, round(sum(total) / sum(load), 6) as saving from u"))
def _(s, d):
    _, m, a = plan(s, d)
    total = m.agg(F.count("*").alias("total_size"))
    load = packing.bins(m, a).agg(F.count("*").alias("n_bins"), F.sum("load").alias("total_load"))
    return load.join(total).select("n_bins", "total_size", "total_load", F.round(F.col("total_size") / F.col("total_load"), 6).alias("saving"))  # one row each


@query("pack_placement_ghosts", _greedy_sql(_SKETCH, out=", asg as (select c as sg_id, b as bin_id from st where c >= 0), pl as (select bin_id, v, max((v = sg_id)::int) as own from asg join mem using (sg_id) group by 1, 2) select bin_id, cast(sum(own) as bigint) as n_owned, cast(sum(1 - own) as bigint) as n_ghost from pl group by 1"))
def _(s, d):
    _, m, a = plan(s, d)
    return iterate.ghosts(packing.placement(m, a))


@query("pack_lower_bound", _MEM_SQL + f"select cast(ceil(count(distinct v) / {CAPACITY}.0) as bigint) as by_union, cast(ceil(count(distinct sg_id) / {MAX_ITEMS}.0) as bigint) as by_items from mem")
def _(s, d):
    return default_members(s, d).agg(F.ceil(F.countDistinct("v") / CAPACITY).alias("by_union"), F.ceil(F.countDistinct("sg_id") / MAX_ITEMS).alias("by_items"))


@query("pack_exact_tiny")
def _(s, d):
    """All subgraphs with the proven bounds of the number of bins; lower < upper where the search was not ended."""
    return packing.numbered(packing.pack(default_members(s, d), PackOptions(60, 4, algorithm="exact"))).select("sg_id", "bin_id", "lower", "upper")


def _cells_sql(cells: list[tuple[str, str, int, int | None]], out: str, n_hashes: int = 6) -> str:
    """Greedy placement of many cells at once, (seed rule, order, capacity, item cap) each: st has k, the number of the cell, c and b."""
    base = f"base as (select sig.*, vs, load, p_size from sig join (select sg_id, list(v) as vs, count(*) as load from mem group by 1) using (sg_id) join part on p_partkey = sg_id)"
    o = " union all ".join(f"select row_number() over (order by {order}) as i, {k} as k, sg_id as c, vs, {cap} as cap, {items or 1 << 30} as lim from base where {rule}" for k, (rule, order, cap, items) in enumerate(cells))
    return W(RET, SEED, MEM, _sign(n_hashes), recursive=True) + f""", {base}, o as ({o}),
st as (select distinct 0::bigint as i, k, []::struct(vs bigint[], n int)[] as bins, -1::bigint as c, -1::bigint as b from o
 union all select o.i, o.k, case when j is null then list_append(bins, {{'vs': o.vs, 'n': 1}}) else list_transform(bins, lambda x, m: case when m = j then {{'vs': list_distinct(list_concat(x.vs, o.vs)), 'n': x.n + 1}} else x end) end, o.c, coalesce(j, len(bins) + 1)
 from (select st.i, st.k, st.bins, list_position(list_transform(st.bins, lambda x: x.n < nx.lim and len(list_distinct(list_concat(x.vs, nx.vs))) <= nx.cap), true) as j from st join o nx on nx.i = st.i + 1 and nx.k = st.k) z join o on o.i = z.i + 1 and o.k = z.k) """ + out


_BY_ORDER = {"arrival": "sg_id", "size_desc": "load desc, sg_id", "sketch": _SKETCH}
_NAMES = lambda names: "(values " + ", ".join(f"({k}, " + ", ".join(f"'{x}'" if isinstance(x, str) else str(x) for x in n) + ")" for k, n in enumerate(names)) + ")"


@query("pack_quality_by_order", _cells_sql([("true", o, CAPACITY, MAX_ITEMS) for o in _BY_ORDER.values()], f", u as (select k, b, count(distinct v) as load from st join mem on sg_id = c where c >= 0 group by 1, 2) select name as order_name, count(*) as n_bins, cast(sum(load) as bigint) as total_load, round(avg(load / {CAPACITY}.0), 6) as mean_fill from u join {_NAMES([(n,) for n in _BY_ORDER])} t(k, name) using (k) group by 1"))
def _(s, d):
    out = None
    m = cut(default_members(s, d), "members")
    for order in ("arrival", "size_desc", "sketch"):
        a = cut(packing.numbered(packing.pack(m, PackOptions(CAPACITY, MAX_ITEMS, order))), "assignment")
        row = packing.bins(m, a).agg(F.count("*").alias("n_bins"), F.sum("load").alias("total_load"), F.round(F.avg(F.col("load") / CAPACITY), 6).alias("mean_fill")).select(F.lit(order).alias("order_name"), "n_bins", "total_load", "mean_fill")
        out = row if out is None else out.unionAll(row)
    return out


# ---------------------------------------------------------------- samples


@query("sample_oversized", W(RET, SEED, MEM) + "select sg_id, count(*) as n_vertices, count(*) as load from mem group by 1 having count(*) > 20")
def _(s, d):
    return sampling.find_oversized(extract.subgraph_sizes(default_members(s, d)), 20)


def _stays(ratio: float, salt: str) -> str:
    """The rule of node samples for SQL, written apart from the code that samples."""
    terms = f"({A[0]} * v) % {P} + ({A[1]} * sg_id) % {P} + ({salt} * {B[2]}) % {P}"
    return f"(v = sg_id or mod(mod({terms}, {P}), 1000000) < {ratio} * 1000000)"


@query("sample_nodes_members", _MEM_SQL + f"select sg_id, v, hop from mem where {_stays(0.4, '1')}")
def _(s, d):
    return sampling.node_sample(default_members(s, d), 0.4).select("sg_id", "v", "hop")


_RATIOS = [0.2, 0.4, 0.6, 0.8]
_KEEP = " or ".join(f"(ratio = {r} and {_stays(r, 'salt')})" for r in _RATIOS)


@query("sample_nodes_lcc_study", W(RET, DEG, SEED, MEM, TRI) + f", grid as (select unnest({_RATIOS})::double as ratio), runs as (select unnest(range(1, 11)) as salt), sm as (select ratio, salt, sg_id, v from mem, grid, runs where {_KEEP}), dg as (select ratio, salt, sg_id, count(*) - 1 as d from sm group by 1, 2, 3), lk as (select x.ratio, x.salt, x.sg_id, count(*) as k from sm x join ret on src = x.v join sm y on y.v = dst and y.ratio = x.ratio and y.salt = x.salt and y.sg_id = x.sg_id where x.v <> x.sg_id and y.v <> x.sg_id group by 1, 2, 3), each as (select ratio, salt, avg(case when d > 1 then round(2.0 * coalesce(k, 0) / (d * (d - 1)), 6) else 0 end) as m from dg left join lk using (ratio, salt, sg_id) group by 1, 2), ex as (select round(avg(case when degree > 1 then round(2.0 * coalesce(links, 0) / (degree * (degree - 1)), 6) else 0 end), 6) as exact_lcc from seed join deg using (id) left join cor on cor.sg_id = id) select ratio, round(avg(m), 6) as mean_lcc, round(stddev(m), 6) as std_lcc, exact_lcc from each, ex group by ratio, exact_lcc")
def _(s, d):
    return sampling.lcc_study(part_graph(s, d), default_members(s, d), _RATIOS)


#: A walk a subgraph until half of its vertices are seen; its state is the list of those seen.
_WALKED = f", ie as (select a.sg_id, r.src, r.dst from mem a join ret r on a.v = r.src join mem b on b.sg_id = a.sg_id and b.v = r.dst), ib as (select sg_id, src, dst from ie union all select sg_id, dst, src from ie), nb as (select sg_id, src as v, list_sort(list(dst)) as tos from ib group by 1, 2), wt as (select sg_id, greatest(1, cast(round_even(0.5 * count(*), 0) as int)) as want from mem group by 1), wk as (select 0 as t, sg_id, sg_id as v, case when (48271 * sg_id + 1) % {P} = 0 then 1 else (48271 * sg_id + 1) % {P} end as x, [sg_id] as got, want from wt union all select t + 1, sg_id, nv, x, case when list_contains(got, nv) then got else list_append(got, nv) end, want from (select t, w.sg_id, case when 48271 * x % {P} % 1000 < 150 or tos is null then w.sg_id else tos[1 + (48271 * x % {P} // 1000) % len(tos)] end as nv, 48271 * x % {P} as x, got, want from wk w left join nb on nb.sg_id = w.sg_id and nb.v = w.v where len(got) < want and t < 100 * want)) select sg_id, unnest(got) as v from (select sg_id, arg_max(got, t) as got from wk group by 1)"


@query("sample_walk_members", W(RET, SEED, MEM, recursive=True) + _WALKED)
def _(s, d):
    return sampling.sampled(default_members(s, d), part_graph(s, d), sampling.walk_sampler(0.5))


@query("sample_forest_fire_members")
def _(s, d):
    return sampling.sampled(default_members(s, d), part_graph(s, d), sampling.forest_fire_sampler(0.5))


# ---------------------------------------------------------------- engine


@query("bin_load_rows", _greedy_sql(_SKETCH, out=", asg as (select c as sg_id, b as bin_id from st where c >= 0), bv as (select distinct bin_id, v from asg join mem using (sg_id)) select x.bin_id, count(*) as n_edges from bv x join ret on src = x.v join bv y on y.v = dst and y.bin_id = x.bin_id group by 1"))
def _(s, d):
    g, m, a = plan(s, d)
    return engine.materialize_bins(g, m, a)[1].groupBy("bin_id").agg(F.count("*").alias("n_edges"))


@query("bin_bitmap_words", _greedy_sql(_SKETCH, out=", asg as (select c as sg_id, b as bin_id, row_number() over (partition by b order by i) - 1 as slot from st where c >= 0) select bin_id, v, slot // 32 as word, bit_or(1::bigint << (slot % 32)) as bits from asg join mem using (sg_id) group by 1, 2, 3"))
def _(s, d):
    _, m, a = plan(s, d)
    return bitmaps.slot_bitmap(m, a)


@query("bin_shared_vertices", _greedy_sql(_SKETCH, out=", asg as (select c as sg_id, b as bin_id from st where c >= 0) select bin_id, v, count(*) as n from asg join mem using (sg_id) group by 1, 2 having count(*) > 1"))
def _(s, d):
    _, m, a = plan(s, d)
    return bitmaps.slot_bitmap(m, a).groupBy("bin_id", "v").agg(F.sum(F.bit_count("bits")).cast("bigint").alias("n")).where("n > 1")


_SEEN = _MEM_SQL + ", n as (select sg_id, count(*) as n_vertices from mem group by 1), e as (select a.sg_id, count(*) as n_edges from mem a join ret on a.v = src join mem b on b.sg_id = a.sg_id and b.v = dst group by 1) select sg_id, n_vertices, coalesce(n_edges, 0) as n_edges from n left join e using (sg_id)"


@query("bin_visible_elements", _SEEN)
def _(s, d):
    return engine.run(*plan(s, d), programs.visible())


@query("engine_modes_agree", "select cast(8 as bigint) as modes, cast(0 as bigint) as differences")
def _(s, d):
    g, m, a = plan(s, d)
    out = None
    for k, o in enumerate((ExecOptions(), ExecOptions("batched", 3), ExecOptions("single"), ExecOptions("replicate"), ExecOptions(bitmap="sparse"), ExecOptions(bitmap="growable"), ExecOptions(threads=4), ExecOptions(sequential=True))):
        rows = engine.run(g, m, a, programs.lcc(), o).withColumn("mode", F.lit(k))
        out = rows if out is None else out.unionAll(rows)
    same = out.groupBy("sg_id", "degree", "links", "lcc").agg(F.countDistinct("mode").alias("n"))
    return same.agg(F.max("n").alias("modes"), F.sum((F.col("n") != 8).cast("bigint")).alias("differences"))


# ---------------------------------------------------------------- applications

_LCC = "round(case when degree > 1 then 2.0 * coalesce(links, 0) / (degree * (degree - 1)) else 0 end, 6) as lcc"
_SEEDED = W(RET, DEG, SEED, TRI)
_ALL_LCC = W(RET, DEG, TRI) + f"select id as sg_id, degree, coalesce(links, 0) as links, {_LCC} from deg left join cor on cor.sg_id = id"


@query("app_lcc", _SEEDED + f"select id as sg_id, degree, coalesce(links, 0) as links, {_LCC} from seed join deg using (id) left join cor on cor.sg_id = id")
def app_lcc(s, d):
    return engine.run(*plan(s, d), programs.lcc())


@query("app_lcc_relational", _ALL_LCC)
def _(s, d):
    return relational.lcc(graphs.returned(s, d))


@query("app_triangles", W(RET, DEG, TRI) + "select id as sg_id, coalesce(links, 0) as n from deg left join cor on cor.sg_id = id")
def _(s, d):
    return relational.triangles(graphs.returned(s, d))


@query("app_triangles_engine", _SEEDED + "select id as sg_id, coalesce(links, 0) as n from seed left join cor on cor.sg_id = id")
def _(s, d):
    return engine.run(*plan(s, d), programs.triangles())


_WEAK = "select id as sg_id, degree * (degree - 1) // 2 - coalesce(links, 0) as n from deg left join cor on cor.sg_id = id"


@query("app_weak_ties", W(RET, DEG, TRI) + _WEAK)
def _(s, d):
    return relational.weak_ties(graphs.returned(s, d))


@query("app_weak_ties_engine", _SEEDED + "select id as sg_id, degree * (degree - 1) // 2 - coalesce(links, 0) as n from seed join deg using (id) left join cor on cor.sg_id = id")
def _(s, d):
    return engine.run(*plan(s, d), programs.weak_ties())


_IDS = "ids as (select src as id from nxt union select dst from nxt)"
_FFL = "select a.src as sg_id, count(*) as n from nxt a join nxt b on a.dst = b.src join nxt c on c.src = a.src and c.dst = b.dst group by 1"
_FBL = "select a.src as sg_id, count(*) as n from nxt a join nxt b on a.dst = b.src join nxt c on c.src = b.dst and c.dst = a.src group by 1"
_BIP = "select a as sg_id, cast(sum(m * (m - 1) // 2) as bigint) as n from (select x.src as a, y.dst as d, count(*) as m from nxt x join nxt y on x.dst = y.src where x.src <> y.dst group by 1, 2) group by 1"
for _name, _fn, _sql in (("app_motif_feed_forward", relational.feed_forward, _FFL), ("app_motif_feedback", relational.feedback, _FBL), ("app_motif_biparallel", relational.biparallel, _BIP)):
    query(_name, W(NEXT, _IDS) + f"select id as sg_id, coalesce(n, 0) as n from ids left join ({_sql}) on sg_id = id")(lambda s, d, f=_fn: f(graphs.next_line(s, d)))


def _directed_plan(s, d, k, direction):
    g = graphs.next_line(s, d)
    part = graphs.table(s, d, "part").withColumnRenamed("p_partkey", "id").join(g.vertices, "id", "left_semi")
    g = PropertyGraph(part, g.edges, True)
    m = cut(extract.khop_members(g, NeighborhoodSpec(SEED_RULE, k, direction=direction)).withColumn("w", F.lit(1).cast("bigint")), "members")
    return g, m, cut(packing.numbered(packing.pack(m, PackOptions(1500, None))), "assignment")


_NSEED = "sd as (select p_partkey as id from part where p_size > 45 and p_partkey in (select id from ids))"
for _kind, _k, _sql in (("feed_forward", 1, _FFL), ("feedback", 2, _FBL), ("biparallel", 2, _BIP)):
    query(f"app_motif_{_kind}_engine", W(NEXT, _IDS, _NSEED) + f"select id as sg_id, coalesce(n, 0) as n from sd left join ({_sql}) on sg_id = id")(lambda s, d, kind=_kind, k=_k: engine.run(*_directed_plan(s, d, k, "out"), programs.motif(kind)))


def _ppr_sql(tail: str) -> str:
    """Ten rounds over the induced subgraphs of two hops; every vertex has an out-edge there, as the graph is undirected."""
    ia = "ia as (select x.sg_id, a.src, a.dst from mem2 x join arc a on a.src = x.v join mem2 y on y.sg_id = x.sg_id and y.v = a.dst), od as (select sg_id, src, count(*) as k from ia group by 1, 2)"
    return W(RET, PSEED, MEM2, recursive=True) + f", {ia}, step as (select 0 as t, sg_id, v, case when v = sg_id then 1.0::double else 0.0::double end as s from mem2 union all select t + 1, sg_id, v, sum(x) from (select st.t, ia.sg_id, ia.dst as v, 0.85 * st.s / od.k as x from step st join ia on ia.sg_id = st.sg_id and ia.src = st.v join od on od.sg_id = ia.sg_id and od.src = ia.src union all select t, sg_id, v, case when v = sg_id then 0.15 else 0 end from step) where t < 10 group by t, sg_id, v), fin as (select sg_id, v, round(s, 6) as score from step where t = 10) " + tail


#: One seed in fifty, as the two-hop experiments take a small share of the vertices.
PSEED = "seed as (select p_partkey as id from part where p_size = 50 and p_partkey in (select src from arc))"
PPR_RULE = "p_size = 50"


def _ppr_inputs(s, d):
    g = part_graph(s, d)
    m = extract.khop_members(g, NeighborhoodSpec(PPR_RULE, 2))
    return g, m


@query("app_ppr_power", _ppr_sql("select sg_id, v, score from fin"))
def _(s, d):
    g, m = _ppr_inputs(s, d)
    return relational.ppr(m, extract.induced_edges(m, g), False)


@query("app_ppr_engine", _ppr_sql("select sg_id, v, score from fin"))
def _(s, d):
    g, m = _ppr_inputs(s, d)
    m = cut(m.withColumn("w", F.lit(1).cast("bigint")), "members")
    return engine.run(g, m, cut(packing.numbered(packing.pack(m, PackOptions(600))), "assignment"), programs.ppr())


#: Walkers with the integer generator of the walks: 200 a seed, 20 steps, restart where the last three digits are under 150.
_WALKS = f", wa as (select x.sg_id, a.src, a.dst from mem2 x join arc a on a.src = x.v join mem2 y on y.sg_id = x.sg_id and y.v = a.dst), nb as (select sg_id, src as v, list_sort(list(dst)) as tos from wa group by 1, 2), wk as (select 0 as t, id as sg_id, r, id as v, case when (48271 * id + 69621 * r + 7) % {P} = 0 then 1 else (48271 * id + 69621 * r + 7) % {P} end as x from seed, (select unnest(range(200)) as r) union all select t + 1, w.sg_id, r, case when 48271 * x % {P} % 1000 < 150 or tos is null then w.sg_id else tos[1 + (48271 * x % {P} // 1000) % len(tos)] end, 48271 * x % {P} from wk w left join nb on nb.sg_id = w.sg_id and nb.v = w.v where t < 20) select sg_id, v, round(count(*) / 4000, 6) as score from wk where t > 0 group by 1, 2"


@query("app_ppr_walks", W(RET, PSEED, MEM2, recursive=True) + _WALKS)
def _(s, d):
    g, m = _ppr_inputs(s, d)
    return relational.ppr_walks(m, extract.induced_edges(m, g), False)


@query("app_link_prediction", _ppr_sql("select sg_id, v, score, row_number() over (partition by sg_id order by score desc, v)::int as rank from fin where v <> sg_id and not exists (select 1 from arc where src = sg_id and dst = v) qualify row_number() over (partition by sg_id order by score desc, v) <= 5"))
def _(s, d):
    g, m = _ppr_inputs(s, d)
    return relational.link_prediction(relational.ppr(m, extract.induced_edges(m, g), False), g)


_ALTER = "al as (select sg_id, v from mem where v <> sg_id), ae as (select x.sg_id, a.src, a.dst from al x join arc a on a.src = x.v join al y on y.sg_id = x.sg_id and y.v = a.dst)"


@query("app_circles_components", W(RET, SEED, MEM, recursive=True) + f", {_ALTER}, reach as (select sg_id, v, v as l from al union select r.sg_id, ae.dst, r.l from reach r join ae on ae.sg_id = r.sg_id and ae.src = r.v) select sg_id, v, min(l) as circle from reach group by 1, 2")
def _(s, d):
    return engine.run(*plan(s, d), programs.circles())


for _method in ("votes", "modularity"):
    query(f"app_circles_{_method}")(lambda s, d, m=_method: engine.run(*plan(s, d), programs.circles(m)))

_BETW = W(RET, SEED, MEM) + ", al as (select sg_id, v from mem where v <> sg_id), pr as (select x.sg_id, x.v as a, y.v as b from al x join al y on y.sg_id = x.sg_id and x.v < y.v where not exists (select 1 from ret where src = x.v and dst = y.v)), wy as (select pr.sg_id, a, b, count(*) as k from pr join arc p on p.src = a join arc q on q.src = p.dst and q.dst = b join mem m on m.sg_id = pr.sg_id and m.v = p.dst group by 1, 2, 3) select id as sg_id, coalesce(round(sum(1.0 / k), 6), 0) as betweenness from seed left join wy on sg_id = id group by 1"


@query("app_ego_betweenness", _BETW)
def _(s, d):
    g = part_graph(s, d)
    return relational.ego_betweenness(g, g.vertices.where(SEED_RULE).select("id"))


@query("app_ego_betweenness_engine", _BETW)
def _(s, d):
    return engine.run(*plan(s, d), programs.ego_betweenness())


@query("app_brokerage", _SEEDED + "select id as sg_id, round(degree - 2.0 * coalesce(links, 0) / degree, 6) as effective_size, round((degree - 2.0 * coalesce(links, 0) / degree) / degree, 6) as efficiency from seed join deg using (id) left join cor on cor.sg_id = id")
def _(s, d):
    g = part_graph(s, d)
    return relational.brokerage(g, g.vertices.where(SEED_RULE).select("id"))


_CONSTRAINT = ", nb as (select id as sg_id, dst as j from seed join arc on src = id), ins as (select x.sg_id, x.j as q, a.dst as j from nb x join arc a on a.src = x.j join nb y on y.sg_id = x.sg_id and y.j = a.dst), tk as (select sg_id, q, count(*) as k from ins group by 1, 2), wy as (select sg_id, j, sum(1.0::double / (1 + k)) as x from ins join tk using (sg_id, q) group by 1, 2), dg as (select sg_id, count(*) as d from nb group by 1), cs as (select sg_id, round(sum(p * p), 6) as constraint_ from (select sg_id, (1 + coalesce(x, 0)) / d as p from nb join dg using (sg_id) left join wy using (sg_id, j)) group by 1)"


@query("app_constraint", W(RET, SEED) + _CONSTRAINT + " select sg_id, constraint_ from cs")
def _(s, d):
    g = part_graph(s, d)
    return relational.constraint(g, g.vertices.where(SEED_RULE).select("id"))


@query("app_brokerage_engine", _SEEDED + _CONSTRAINT + " select id as sg_id, round(degree - 2.0 * coalesce(links, 0) / degree, 6) as effective_size, round((degree - 2.0 * coalesce(links, 0) / degree) / degree, 6) as efficiency, constraint_ from seed join deg using (id) left join cor on cor.sg_id = id join cs on cs.sg_id = id")
def _(s, d):
    return engine.run(*plan(s, d), programs.brokerage())


@query("app_density", _MEM_SQL + ", n as (select sg_id, count(*) as n_vertices from mem group by 1), e as (select a.sg_id, count(*) as n_edges from mem a join ret on a.v = src join mem b on b.sg_id = a.sg_id and b.v = dst group by 1) select sg_id, n_vertices, coalesce(n_edges, 0) as n_edges, round(case when n_vertices > 1 then 2.0 * coalesce(n_edges, 0) / (n_vertices * (n_vertices - 1)) else 0 end, 6) as density from n left join e using (sg_id)")
def _(s, d):
    m = default_members(s, d)
    return relational.density(m, extract.induced_edges(m, part_graph(s, d)))


@query("app_ego_features", W(HAND) + ", ids as (select src as v from hand union select dst from hand), mem as (select v as sg_id, v from ids union select src, dst from hand), n as (select sg_id, count(*) as n_vertices from mem group by 1), e as (select x.sg_id, count(*) as n_edges, cast(sum(weight) as bigint) as weight from mem x join hand on src = x.v join mem y on y.sg_id = x.sg_id and y.v = dst group by 1) select sg_id, n_vertices, coalesce(n_edges, 0) as n_edges, coalesce(weight, 0) as weight, coalesce(round(weight / n_edges, 6), 0) as mean_weight from n left join e using (sg_id)")
def _(s, d):
    g = graphs.handoff(s, d)
    m = extract.khop_members(g, NeighborhoodSpec())
    return relational.ego_features(m, extract.induced_edges(m, g))


_VX = "vx as (select distinct src as id from arc)"
for _name, _pat, _sql in (
    ("app_pattern_path3", [(0, 1), (1, 2)], "select a.src as sg_id, count(*) as n from arc a join arc b on a.dst = b.src and b.dst <> a.src group by 1"),
    ("app_pattern_star", [(0, 1), (0, 2), (0, 3)], "select src as sg_id, count(*) * (count(*) - 1) * (count(*) - 2) // 6 as n from arc group by 1 having count(*) > 2"),
    ("app_pattern_triangle", [(0, 1), (1, 2), (0, 2)], "select sg_id, links as n from cor"),
    ("app_pattern_diamond", [(0, 1), (0, 2), (1, 2), (1, 3), (2, 3)], "select a.src as sg_id, count(*) as n from arc a join arc b on b.src = a.src and a.dst < b.dst join ret e on e.src = a.dst and e.dst = b.dst join arc f on f.src = a.dst and f.dst <> a.src join arc h on h.src = b.dst and h.dst = f.dst group by 1"),
):
    query(_name, W(RET, TRI, _VX) + f"select id as sg_id, coalesce(n, 0) as n from vx left join ({_sql}) on sg_id = id")(lambda s, d, p=_pat: relational.pattern_counts(graphs.returned(s, d), p))

@query("app_pattern_match_engine", _SEEDED + "select id as sg_id, coalesce(links, 0) as n from seed left join cor on cor.sg_id = id")
def _(s, d):
    """The black-box matcher on triangles around the centre."""
    return engine.run(*plan(s, d), programs.match([(0, 1), (1, 2), (0, 2)]))


_DOC = "l as (select distinct doc_id, line from (select doc_id, unnest(string_split(text, chr(10))) as line from documents) where length(line) >= 40), de as (select distinct a.doc_id as src, b.doc_id as dst from l a join l b on a.line = b.line and a.doc_id < b.doc_id), da as (select src, dst from de union all select dst, src from de), dd as (select src as id, count(*) as k from da group by 1)"


@query("app_pair_resolution", W(_DOC) + ", cm as (select e.src as a, e.dst as b, count(*) as common, sum(1 / ln(k)) as aa from de e join da x on x.src = e.src join da y on y.src = e.dst and y.dst = x.dst join dd on dd.id = x.dst group by 1, 2) select e.src as a, e.dst as b, coalesce(common, 0) as common, round(coalesce(common, 0) / (p.k + q.k - coalesce(common, 0)), 6) as jaccard, round(coalesce(aa, 0), 6) as adamic_adar from de e left join cm on cm.a = e.src and cm.b = e.dst join dd p on p.id = e.src join dd q on q.id = e.dst")
def _(s, d):
    return resolution.keyed_pair_scores(graphs.document_lines(s, d))


@query("app_cascade_reach", "with st as (select ts, user_id as src, lead(user_id) over (order by ts, event_id) as dst from events), ok as (select * from st where dst is not null and src <> dst), two as (select a.src as seed, b.dst as reached, 2 as hop from ok a join ok b on b.src = a.dst and b.ts > a.ts and b.ts <= a.ts + interval 24 hours) select seed, reached, cast(min(hop) as bigint) as hop from (select src as seed, dst as reached, 1 as hop from ok union all select * from two) where seed <> reached group by 1, 2")
def _(s, d):
    e = graphs.table(s, d, "events").select("ts", "event_id", "user_id", F.to_date("ts").alias("day"))
    from pyspark.sql import Window

    within = e.select("ts", F.col("user_id").alias("src"), F.lead("user_id").over(Window.partitionBy("day").orderBy("ts", "event_id")).alias("dst"))
    ends = e.groupBy("day").agg(F.min_by("user_id", F.struct("ts", "event_id")).alias("first"), F.max_by(F.struct("ts", "user_id"), F.struct("ts", "event_id")).alias("last"))
    across = ends.select("last.ts", F.col("last.user_id").alias("src"), F.lead("first").over(Window.orderBy("day")).alias("dst"))  # one row a day
    return relational.cascade(within.unionAll(across).where("dst is not null and src <> dst"), 24, 2)


@query("sql_ego_members", W(RET) + "select src as sg_id, src as v, 0 as hop from arc group by 1 union all select src, dst, 1 from arc")
def _(s, d):
    """One-hop subgraphs by the table function, in SQL."""
    surfaces.register(s)
    return s.sql("select * from ego_members(table({arcs}) partition by src)", arcs=graphs.returned(s, d).arcs())


@query("sql_bit_members", _greedy_sql(_SKETCH, out="select b as bin_id, count(*) as n from st join mem on sg_id = c where c >= 0 group by 1"))
def _(s, d):
    """Memberships a bin, counted by testing every bit of the bitmap words with the scalar function."""
    surfaces.register(s)
    _, m, a = plan(s, d)
    return s.sql("select bin_id, sum(cast(test_bit(bits, slot) as bigint)) as n from (select bin_id, bits, explode(sequence(0L, 31L)) as slot from {words}) group by bin_id", words=bitmaps.slot_bitmap(m, a))


@query("sql_geometric_mean", _SEEDED + "select degree, round(exp(avg(ln(2.0 * links / (degree * (degree - 1))))), 6) as mean from seed join deg using (id) join cor on cor.sg_id = id where degree > 1 and links > 0 group by 1")
def _(s, d):
    """A user aggregate over results: the geometric mean of positive clustering by degree."""
    surfaces.register(s)
    g = part_graph(s, d)
    links = relational.links(g, g.vertices.where(SEED_RULE).select("id")).where("degree > 1 and links > 0")
    return s.sql("select degree, geometric_mean(2.0D * links / (degree * (degree - 1))) as mean from {r} group by degree", r=links)


@query("engine_user_aggregate", _SEEDED + "select count(*) as n, cast(sum(links) as bigint) as links, max(degree) as most from (select degree, coalesce(links, 0) as links from seed join deg using (id) left join cor on cor.sg_id = id)")
def _(s, d):
    """A user's aggregator over program results, states built where the results are."""
    top = engine.Aggregator("n bigint, links bigint, most bigint", lambda: (0, 0, 0), lambda x, r: (x[0] + 1, x[1] + r["links"], max(x[2], r["degree"])), lambda x, y: (x[0] + y[0], x[1] + y[1], max(x[2], y[2])), lambda x: x)
    return engine.aggregate(engine.run(*plan(s, d), programs.lcc()), top)


@query("engine_pandas_program", _SEEN.replace("select sg_id, n_vertices, coalesce(n_edges, 0) as n_edges", "select sg_id, n_vertices, coalesce(n_edges, 0) as n_edges"))
def _(s, d):
    """A program over pandas frames of a subgraph's vertices and edges."""
    import pandas as pd

    m = default_members(s, d)
    return engine.run_pandas(m, extract.induced_edges(m, part_graph(s, d)), lambda c, v, e: pd.DataFrame({"sg_id": [c], "n_vertices": [len(v)], "n_edges": [len(e)]}), "sg_id bigint, n_vertices bigint, n_edges bigint")


@query("graph_grid_source", "with p as (select distinct p_partkey as id from part where p_partkey is not null), n as (select ceil(sqrt(max(id) + 1))::bigint as n from p) select id as src, id + 1 as dst from p, n where id % n < n - 1 and id + 1 in (select id from p) union all select id, id + n from p, n where id + n in (select id from p)")
def _(s, d):
    """Parts in the cells of the least square grid that holds their keys, and the grid's edges between cells that hold one."""
    gridsource.register(s)
    part = graphs.table(s, d, "part").select(F.col("p_partkey").alias("id")).where("id is not null").distinct()
    most = part.agg(F.max("id").alias("most")).head().most
    n = 0 if most is None else math.isqrt(most) + 1
    grid = s.read.format("grid_graph").option("n", n).option("parts", max(4, n * n // 100_000)).load()
    return grid.join(part.toDF("src"), "src", "left_semi").join(part.toDF("dst"), "dst", "left_semi").select("src", "dst")


# ---------------------------------------------------------------- iteration

_REACH = W(RET, KIND, recursive=True) + ", ka as (select src, dst from kin union select dst, src from kin), reach as (select src as v, src as l from ka union select ka.dst, r.l from reach r join ka on ka.src = r.v) select v, min(l) as component from reach group by 1"


def _kind_bins(s, d, n):
    g = graphs.returned_same_kind(s, d)
    return g, packing.pack_hash(g.vertices.select(F.col("id").alias("sg_id")), n).toDF("v", "bin_id")


@query("iter_components", _REACH)
def _(s, d):
    return iterate.components(*_kind_bins(s, d, 5))[0]


@query("iter_components_local_fix", _REACH)
def _(s, d):
    return iterate.components(*_kind_bins(s, d, 10), local_fix=True)[0]


@query("iter_components_per_subgraph", W(RET, SEED, MEM) + "select sg_id, v, min(sg_id) over (partition by sg_id) * 0 + (select min(m.v) from mem m where m.sg_id = mem.sg_id) as component from mem")
def _(s, d):
    return engine.run(*plan(s, d), programs.local_components())


@query("iter_pagerank", W(HAND, recursive=True) + ", ids as (select src as v from hand union select dst from hand), n as (select count(*)::double as n from ids), od as (select src, count(*) as k from hand group by 1), step as (select 0 as t, v, 1.0 / n as s from ids, n union all select t + 1, v, (select 0.15 / n from n) + 0.85 * (sum(x) + max(lost) / (select n from n)) from (select st.t, h.dst as v, st.s / od.k as x, 0.0::double as lost from step st join hand h on h.src = st.v join od on od.src = st.v union all select st.t, st.v, 0.0, (select coalesce(sum(z.s), 0) from step z where z.v not in (select src from od)) from step st) where t < 10 group by t, v) select v, round(s, 9) as score from step where t = 10")
def _(s, d):
    return iterate.pagerank(graphs.handoff(s, d))


@query("iter_pagerank_bins", W(HAND, recursive=True) + SQL["iter_pagerank"].split(", ids as", 1)[1].join([", ids as", ""]))
def _(s, d):
    """The same by a superstep program over bins and ghosts."""
    g = graphs.handoff(s, d)
    return iterate.pagerank_bins(g, packing.pack_hash(g.vertices.select(F.col("id").alias("sg_id")), 10).toDF("v", "bin_id"))


@query("iter_ghost_counts", W(RET, KIND) + f", ids as (select src as v from kin union select dst from kin), bn as (select v, ({A[0]} * (v % {P}) + {B[0]}) % {P} % 5 + 1 as bin_id from ids), ka as (select src, dst from kin union select dst, src from kin) select b.bin_id, count(distinct src) as n_ghost from ka join bn b on b.v = dst join bn c on c.v = src and c.bin_id <> b.bin_id group by 1")
def _(s, d):
    g, bins = _kind_bins(s, d, 5)
    rows = g.arcs("both").join(bins.toDF("dst", "bin_id"), "dst").join(bins.toDF("src", "home"), "src").where("bin_id <> home")
    return rows.groupBy("bin_id").agg(F.countDistinct("src").alias("n_ghost"))


# ---------------------------------------------------------------- baselines

_TRI_ALL = W(RET, DEG, TRI) + "select id as sg_id, coalesce(links, 0) as n from deg left join cor on cor.sg_id = id"
_MODELS = {
    "bsp": (baselines.bsp_links, baselines.bsp_motif, baselines.gathered_ppr, lambda g: baselines.message_components(g)[0]),
    "gas": (baselines.gas_links, baselines.gas_motif, baselines.gas_ppr, baselines.gas_components),
    "triplet": (baselines.triplet_links, baselines.triplet_motif, baselines.triplet_ppr, baselines.triplet_components),
}
for _model, (_links, _motif, _walk, _parts) in _MODELS.items():
    for _app, _sql in (("lcc", _ALL_LCC), ("triangles", _TRI_ALL), ("weak_ties", W(RET, DEG, TRI) + _WEAK)):
        query(f"base_{_model}_{_app}", _sql)(lambda s, d, f=_links, a=_app: workloads.of_links(a, f(graphs.returned(s, d))))
    for _app, _kind, _sql in (("ffl", "feed_forward", _FFL), ("feedback", "feedback", _FBL), ("biparallel", "biparallel", _BIP)):
        query(f"base_{_model}_{_app}", W(NEXT, _IDS) + f"select id as sg_id, coalesce(n, 0) as n from ids left join ({_sql}) on sg_id = id")(lambda s, d, f=_motif, k=_kind: f(graphs.next_line(s, d), k))
    query(f"base_{_model}_components", _REACH)(lambda s, d, f=_parts: f(graphs.returned_same_kind(s, d)))
    query(f"base_{_model}_pagerank", SQL["iter_pagerank"])(lambda s, d, m=_model: baselines.rank(graphs.handoff(s, d), m))

    @query(f"base_{_model}_ppr", _ppr_sql("select sg_id, v, score from fin"))
    def _(s, d, f=_walk):
        g = part_graph(s, d)
        return f(g, g.vertices.where(PPR_RULE).select("id"))


@query("base_bsp_ffl_lists", W(NEXT, _IDS) + f"select id as sg_id, coalesce(n, 0) as n from ids left join ({_FFL}) on sg_id = id")
def _(s, d):
    """Feed-forward loops by sending out-lists against the in-edges only."""
    return baselines.bsp_feed_forward(graphs.next_line(s, d))


@query("base_gas_replication", W(RET) + ", cp as (select src % 4 * 4 + dst % 4 as p, src as v from arc union select src % 4 * 4 + dst % 4, dst from arc) select count(distinct v) as n_vertices, count(*) as n_mirrors, round(count(*) / count(distinct v), 6) as replication from cp")
def _(s, d):
    return baselines.gas_replication(graphs.returned(s, d))


@query("base_triplet_message_rows", W(RET, DEG) + "select 'message list entries' as model, cast(sum(degree * degree) as bigint) as n from deg union all select 'triplet array entries', cast(sum(degree * degree) as bigint) from deg union all select 'arcs', count(*) from arc")
def _(s, d):
    return baselines.triplet_message_rows(graphs.returned(s, d))


@query("base_hash_bins", W(RET, SEED) + f"select id as sg_id, ({A[0]} * (id % {P}) + {B[0]}) % {P} % 35 + 1 as bin_id from seed")
def _(s, d):
    return packing.pack_hash(part_graph(s, d).vertices.where(SEED_RULE).select(F.col("id").alias("sg_id")), 35)


# ---------------------------------------------------------------- measures


@query("measure_bin_distribution", _greedy_sql(_SKETCH, out=", n as (select b, count(*) as n from st where c >= 0 group by 1) select round(quantile_cont(n, 0.0), 6) as low, round(quantile_cont(n, 0.25), 6) as q1, round(quantile_cont(n, 0.5), 6) as median, round(quantile_cont(n, 0.75), 6) as q3, round(quantile_cont(n, 1.0), 6) as high from n"))
def _(s, d):
    return metrics.bin_distribution(plan(s, d)[2])


@query("measure_replication", _greedy_sql(_SKETCH, out=", u as (select distinct b, v from st join mem on sg_id = c where c >= 0) select count(*) as copies, count(distinct v) as vertices, round(count(*) / count(distinct v), 6) as replication from u"))
def _(s, d):
    _, m, a = plan(s, d)
    return metrics.replication(m, a)


@query("measure_bin_fill", _greedy_sql(_SKETCH, out=f", u as (select b, count(distinct v) as load from st join mem on sg_id = c where c >= 0 group by 1) select round(avg(load / {CAPACITY}.0), 6) as mean_fill, round(max(load) / avg(load), 6) as imbalance from u"))
def _(s, d):
    _, m, a = plan(s, d)
    return metrics.bin_fill(m, a, CAPACITY)


@query("measure_bitmap_bytes")
def _(s, d):
    """Measured bytes of one vertex and the hash form's model, at the widths and numbers of set bits that vertices have in the default query's wide bins."""
    _, m, a = plan(s, d, capacity=2000, max_items=None)
    return bitmaps.measured_bytes(m, a)


# ---------------------------------------------------------------- experiments

_SIZED = [(name, o, rule) for name, rule in workloads.RULES.items() for o in workloads.ORDERS]
_SIZED_SQL = [(rule, _BY_ORDER[o], CAPACITY, MAX_ITEMS) for _, o, rule in _SIZED]
_SIZED_NAMES = f"{_NAMES([x[:2] for x in _SIZED])} t(k, instance, packer)"


@query("work_bins_by_order", _cells_sql(_SIZED_SQL, f"select instance, packer, count(*) as n_sg, max(b) as n_bins from st join {_SIZED_NAMES} using (k) where c >= 0 group by 1, 2"))
def _(s, d):
    placed = workloads.packed_grid(workloads.sized_items(s, d, workloads.RULES), [workloads.cell(o) for o in workloads.ORDERS], False)
    return workloads.bin_counts(placed).select("instance", "packer", "n_sg", "n_bins")


@query("work_distribution_by_order", _cells_sql(_SIZED_SQL, f", n as (select k, b, count(*) as n from st where c >= 0 group by 1, 2) select instance, packer, " + ", ".join(f"round(quantile_cont(n, {q}), 6) as {name}" for q, name in ((0.0, "low"), (0.25, "q1"), (0.5, "median"), (0.75, "q3"), (1.0, "high"))) + f" from n join {_SIZED_NAMES} using (k) group by 1, 2"))
def _(s, d):
    return workloads.distribution_by_order(s, d)


_HASHED = (1, 2, 4, 6, 8)


@query("work_hash_counts", _cells_sql([("true", ", ".join(f"s{i + 1}" for i in range(n)) + ", sg_id", CAPACITY, MAX_ITEMS) for n in _HASHED], f"select n_hashes::int as n_hashes, max(b) as n_bins from st join {_NAMES([(n,) for n in _HASHED])} t(k, n_hashes) using (k) where c >= 0 group by 1", 8))
def _(s, d):
    placed = workloads.packed_grid(workloads.sized_items(s, d, {"some": SEED_RULE}), [workloads.cell("sketch", n_hashes=n) for n in _HASHED], False)
    return workloads.bin_counts(placed).select("n_hashes", "n_bins")


_BUCKETED = (1, 2, 4, 6, 8, 16)


@query("work_bins_by_buckets", _cells_sql([(f"s1 % {n} = {b}", _SKETCH, CAPACITY, MAX_ITEMS) for n in _BUCKETED for b in range(n)], f", m as (select k, max(b) as bins from st where c >= 0 group by 1) select n_buckets::int as n_buckets, cast(sum(bins) as bigint) as n_bins from m join {_NAMES([(n,) for n in _BUCKETED for b in range(n)])} t(k, n_buckets) using (k) group by 1"))
def _(s, d):
    placed = workloads.packed_grid(workloads.sized_items(s, d, {"some": SEED_RULE}), [workloads.cell("sketch", n_buckets=n) for n in _BUCKETED], False)
    return workloads.bin_counts(placed).select("n_buckets", "n_bins")


_CAPS = (None, 16, 6)


@query("work_item_caps_bins", _cells_sql([("true", _SKETCH, 300, c) for c in _CAPS], f"select cap2::int as max_items, max(b) as n_bins from st join (values (0, null), (1, 16), (2, 6)) t(k, cap2) using (k) where c >= 0 group by 1"))
def _(s, d):
    placed = workloads.packed_grid(workloads.sized_items(s, d, {"some": SEED_RULE}), [workloads.cell("sketch", 300, c) for c in _CAPS], False)
    return workloads.bin_counts(placed).select("max_items", "n_bins")


_STATS_SQL = "select '{0}' as graph, (select count(*) from deg) as n_vertices, (select count(*) from ret) as n_edges, round(avg(degree), 6) as mean_degree, round(avg(case when degree > 1 then 2.0 * coalesce(links, 0) / (degree * (degree - 1)) else 0 end), 6) as mean_lcc, (select count(*) from tri) as n_triangles from deg left join cor on id = sg_id"
_SWEEP = "d0 as (select id as v from deg order by degree desc, id limit 1), b1 as (select v, 0 as h from d0 union select a.dst, h + 1 from b1 join arc a on a.src = b1.v where h < 24), l1 as (select v, min(h) as h from b1 group by 1), d1 as (select v from l1 order by h desc, v limit 1), b2 as (select v, 0 as h from d1 union select a.dst, h + 1 from b2 join arc a on a.src = b2.v where h < 24), l2 as (select v, min(h) as h from b2 group by 1)"


@query("work_dataset_row", W(RET, DEG, TRI, _SWEEP, recursive=True) + _STATS_SQL.format("returned").replace(" from deg left join", ", (select max(h) from (select h from l1 union all select h from l2)) as diameter from deg left join"))
def _(s, d):
    return workloads.dataset_table(s, d, ("returned",)).withColumn("diameter", F.col("diameter").cast("int"))


for _name, _fn in {
    "work_dataset_table": workloads.dataset_table,
    "work_order_costs": workloads.orders_by_size,
    "work_heuristics": workloads.heuristics,
    "work_attachment_packers": workloads.attachment_packers,
    "work_planning_costs": workloads.central_or_distributed,
    "work_hash_and_threshold_sweeps": workloads.hash_and_threshold_sweeps,
    "work_item_caps": workloads.item_caps,
    "work_modes_and_bitmaps": workloads.modes_and_bitmaps,
    "work_batch_sizes": workloads.batch_sizes,
    "work_stages": workloads.stages,
    "work_end_to_end": workloads.end_to_end,
    "work_large_graph": workloads.large_graph,
    "work_superstep_times": workloads.superstep_times,
    "work_components_by_model": workloads.components_by_model,
    "work_sampled_clustering": workloads.sampled_clustering,
    "work_cut_curve": workloads.cut_curve,
    "work_cut_curve_grown": lambda s, d: workloads.cut_curve(s, d, grown=True),
    **{f"work_block_{app}": lambda s, d, a=app, n=names: workloads.model_grid(s, d, a, n) for app, names in workloads.BLOCKS.items()},
    "work_improvement": lambda s, d: workloads.improvement(workloads.all_blocks(s, d)),
}.items():
    query(_name)(_fn)


# ---------------------------------------------------------------- surrounding operators

from .operators.relops import OPS  # noqa: E402

for _name, _sql, _fn in OPS:
    query(_name, _sql)(lambda s, d, f=_fn: f(lambda t: graphs.table(s, d, t)))


# ---------------------------------------------------------------- streams

from .streaming import streams  # noqa: E402

for _name, _fn in streams.QUERIES.items():
    query(_name, streams.SQL[_name])(_fn)
