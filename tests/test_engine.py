import pytest
from pyspark.sql import functions as F

from egoweave.graph import PropertyGraph, dense_ids, from_edges
from egoweave.operators import baselines, engine, iterate, packing, programs, relational, sampling
from egoweave.plans import extract
from egoweave.plans.extract import edge_membership, induced_edges, khop_members, list_members, local_members
from egoweave.spec import ExecOptions, ListSpec, NeighborhoodSpec, PackOptions

K = [(1, 2), (1, 3), (1, 4), (2, 3), (3, 4), (4, 5)]
D = [(1, 2), (2, 3), (1, 3), (3, 4), (4, 1), (2, 4)]


def graph(spark, edges, directed=False):
    return from_edges(spark.createDataFrame(edges, "src bigint, dst bigint"), directed)


def rows(df, *cols):
    return sorted(tuple(r) for r in df.select(*cols).collect())


def placed(members, capacity=100):
    m = members.withColumn("w", F.lit(1).cast("bigint"))
    return m, packing.numbered(packing.pack(m, PackOptions(capacity, None)))


def test_clustering_in_every_form(spark):
    g = graph(spark, K)
    want = [(1, 3, 2, 0.666667), (2, 2, 1, 1.0), (3, 3, 2, 0.666667), (4, 3, 1, 0.333333), (5, 1, 0, 0.0)]
    cols = ("sg_id", "degree", "links", "lcc")
    m, a = placed(khop_members(g, NeighborhoodSpec()), 4)
    for o in (ExecOptions(), ExecOptions("single"), ExecOptions("replicate")):
        assert rows(engine.run(g, m, a, programs.lcc(), o), *cols) == want
    assert rows(relational.lcc(g), *cols) == want
    for f in (baselines.bsp_links, baselines.gas_links, baselines.triplet_links):
        assert rows(relational.with_lcc(f(g)), *cols) == want
    assert rows(engine.run(g, m, a, programs.weak_ties()), "sg_id", "n") == [(1, 1), (2, 0), (3, 1), (4, 2), (5, 0)]
    assert rows(engine.run(g, m, a, programs.ego_betweenness()), "sg_id", "betweenness") == [(1, 0.5), (2, 0.0), (3, 0.5), (4, 2.0), (5, 0.0)]


def test_motifs(spark):
    g = graph(spark, D, True)
    assert sum(n for _, n in rows(relational.feed_forward(g), "sg_id", "n")) == 2
    assert sum(n for _, n in rows(relational.feedback(g), "sg_id", "n")) == 6
    assert sum(n for _, n in rows(relational.biparallel(g), "sg_id", "n")) == 1


def test_pagerank_with_dangling_vertex(spark):
    g = graph(spark, [(1, 2), (2, 1), (1, 3)], True)
    m = khop_members(g, NeighborhoodSpec(k=2), spark.createDataFrame([(1,)], "id bigint"))
    e = induced_edges(m, g)
    assert rows(relational.ppr(m, e, True, rounds=1), "v", "score") == [(1, 0.15), (2, 0.425), (3, 0.425)]
    assert rows(relational.ppr(m, e, True, rounds=2), "v", "score") == [(1, 0.8725), (2, 0.06375), (3, 0.06375)]


def test_baselines_of_every_model(spark):
    g = graph(spark, [*D, (5, 1), (2, 5), (6, 7), (7, 6), (5, 4)], True)
    for motif, f in (("feed_forward", relational.feed_forward), ("feedback", relational.feedback), ("biparallel", relational.biparallel)):
        want = rows(f(g), "sg_id", "n")
        assert any(n for _, n in want)
        for run in (baselines.bsp_motif, baselines.gas_motif, baselines.triplet_motif):
            assert rows(run(g, motif), "sg_id", "n") == want
    assert rows(baselines.triplet_components(g), "v", "component") == [(1, 1), (2, 1), (3, 1), (4, 1), (5, 1), (6, 6), (7, 6)]
    p = graph(spark, [(1, 2), (2, 3), (3, 4), (4, 5), (2, 1)], True)
    ids = spark.createDataFrame([(1,), (4,)], "id bigint")
    m = khop_members(p, NeighborhoodSpec(k=2), ids)
    want = rows(relational.ppr(m, induced_edges(m, p), True, rounds=3), "sg_id", "v", "score")
    for run in (baselines.gathered_ppr, baselines.gas_ppr, baselines.triplet_ppr):
        assert rows(run(p, ids, rounds=3), "sg_id", "v", "score") == want
    want = rows(iterate.pagerank(p, rounds=2), "v", "score")
    for model in ("bsp", "gas", "triplet"):
        assert [(v, round(x, 7)) for v, x in rows(baselines.rank(p, model, rounds=2), "v", "score")] == [(v, round(x, 7)) for v, x in want]


def test_query_example_in_three_readings(spark):
    v = spark.createDataFrame([(1, 20), (2, 30), (3, 40), (4, 17), (5, 26)], "id bigint, age int")
    e = spark.createDataFrame([(1, 2, 6), (1, 3, 4), (2, 3, 9), (3, 5, 7), (4, 5, 8)], "src bigint, dst bigint, weight bigint")
    g = PropertyGraph(v, e)
    spec = dict(seed_pred="age > 18", v_pred="age > 25", e_pred="weight > 5")
    sets = lambda s: {c: sorted(v for x, v in rows(khop_members(g, s), "sg_id", "v") if x == c) for c, in rows(khop_members(g, s).select("sg_id").distinct(), "sg_id")}
    assert sets(NeighborhoodSpec(**spec)) == {1: [1, 2], 2: [2, 3], 3: [2, 3, 5], 5: [3, 5]}
    assert sets(NeighborhoodSpec(**spec, keep_center=False)) == {2: [2, 3], 3: [2, 3, 5], 5: [3, 5]}
    assert sets(NeighborhoodSpec(**spec, filter_mode="post")) == {1: [1, 2, 3], 2: [2, 3], 3: [2, 3, 5], 5: [3, 5]}
    assert rows(local_members(g, NeighborhoodSpec(**spec)), "sg_id", "v") == rows(khop_members(g, NeighborhoodSpec(**spec)), "sg_id", "v")


def test_components_over_two_bins(spark):
    g = graph(spark, [(1, 2), (2, 3), (3, 4)])
    bins = spark.createDataFrame([(1, 1), (2, 1), (3, 2), (4, 2)], "v bigint, bin_id bigint")
    state, rounds, metrics = iterate.components(g, bins)
    assert rows(state, "v", "component") == [(1, 1), (2, 1), (3, 1), (4, 1)] and rounds == 4
    state, fewer, _ = iterate.components(g, bins, local_fix=True)
    assert rows(state, "v", "component") == [(1, 1), (2, 1), (3, 1), (4, 1)] and fewer < rounds


def test_components_run_until_no_label_changes(spark):
    g = graph(spark, [(i, i + 1) for i in range(1, 9)])
    bins = g.vertices.select(F.col("id").alias("v"), (F.col("id") % 2).alias("bin_id"))
    for run in (lambda: iterate.components(g, bins, max_steps=2), lambda: baselines.message_components(g, 2), lambda: baselines.gas_components(g, max_rounds=2)):
        with pytest.raises(RuntimeError):
            run()
    chain = graph(spark, [(i, i + 1) for i in range(1, 54)]).edges.coalesce(1)
    state, rounds = baselines.message_components(PropertyGraph(spark.range(1, 55).coalesce(1), chain))
    assert {c for _, c in rows(state, "v", "component")} == {1} and rounds == 54


def test_programs_see_only_their_subgraph(spark):
    g = graph(spark, K)
    m, a = placed(khop_members(g, NeighborhoodSpec()))
    seen = rows(engine.run(g, m, a, programs.visible()), "sg_id", "n_vertices", "n_edges")
    assert seen == [(1, 4, 5), (2, 3, 3), (3, 4, 5), (4, 4, 4), (5, 2, 1)]

    def write(view):
        with pytest.raises(PermissionError):
            view.set_state(view.center + 1, 0)
        view.set_state(view.center, 1)
        return [(view.center,)]

    assert len(rows(engine.run(g, m, a, engine.Program("sg_id bigint", write)), "sg_id")) == 5


def test_exact_packing_takes_all_and_shows_its_bounds(spark):
    from egoweave import catalog

    d = "/root/testdata/sf0.001"
    got = rows(catalog.QUERIES["pack_exact_tiny"](spark, d), "sg_id", "bin_id", "lower", "upper")
    assert [x[0] for x in got] == [x for x, in rows(catalog.default_members(spark, d).select("sg_id").distinct(), "sg_id")] and len(got) > 8
    (lower, upper), = {x[2:] for x in got}
    assert lower <= upper == len({x[1] for x in got})
    m = spark.createDataFrame([(i, 10 * i + j, 1) for i, n in enumerate((4, 4, 3, 3, 3, 3)) for j in range(n)], "sg_id bigint, v bigint, w bigint")
    unended = rows(packing.numbered(packing.pack(m, PackOptions(10, None, algorithm="exact"), nodes=0)).select("lower", "upper").distinct(), "lower", "upper")
    ended = rows(packing.numbered(packing.pack(m, PackOptions(10, None, algorithm="exact"), nodes=10**7)).select("lower", "upper").distinct(), "lower", "upper")
    assert unended == [(2, 3)] and ended == [(2, 2)]


def test_audit_finds_faults(spark):
    m = spark.createDataFrame([(1, 1, 1), (1, 2, 1), (2, 3, 1), (2, 4, 1)], "sg_id bigint, v bigint, w bigint")
    bad = spark.createDataFrame([(1, 1), (2, 1)], "sg_id bigint, bin_id bigint")
    found = dict(rows(packing.audit(m, bad, 3, 1), "rule", "violations"))
    assert found["bin within capacity"] == 1 and found["items within cap"] == 1 and found["subgraph in one bin"] == 0


def test_isolated_seed_loops_and_duplicates(spark):
    e = spark.createDataFrame([(1, 2), (1, 2), (2, 2)], "src bigint, dst bigint").distinct()
    g = PropertyGraph(spark.createDataFrame([(1,), (2,), (9,)], "id bigint"), e)
    assert (9, 9, 0) in rows(khop_members(g, NeighborhoodSpec()), "sg_id", "v", "hop")
    assert rows(relational.lcc(g), "sg_id", "lcc") == [(1, 0.0), (2, 0.0), (9, 0.0)]
    given = spark.createDataFrame([(1, 5), (1, 5), (None, 2)], "sg_id bigint, v bigint")
    assert rows(list_members(ListSpec(given)), "sg_id", "v") == [(1, 5)]
    assert edge_membership(khop_members(g, NeighborhoodSpec()), g).count() == 2


def test_samplers_keep_the_centre(spark):
    g = graph(spark, K)
    m = khop_members(g, NeighborhoodSpec())
    kept = rows(sampling.node_sample(m, 0.3), "sg_id", "v")
    assert all((c, c) in kept for c in range(1, 6))
    walk = rows(sampling.sampled(m, g, sampling.walk_sampler(0.5)), "sg_id", "v")
    assert all((c, c) in walk for c in range(1, 6)) and set(walk) <= set(rows(m, "sg_id", "v"))


def test_dense_ids(spark):
    ids = [i for _, i in rows(dense_ids(spark.createDataFrame([("a",), ("b",), ("a",), ("z",)], "k string"), "k"), "key", "id")]
    assert sorted(ids) == [0, 1, 2]


def test_plans_push_filters_and_stay_in_the_engine(spark):
    from egoweave import catalog

    text = catalog.QUERIES["app_lcc_relational"](spark, "/root/testdata/sf0.001")._jdf.queryExecution().toString()
    assert "CartesianProduct" not in text and "Arrow" not in text and "PushedFilters: [IsNotNull(l_returnflag), EqualTo(l_returnflag,R)" in text


def test_grown_parts_in_several_buckets_stay_in_bounds(spark):
    """Bins of different buckets never share a number."""
    members = spark.createDataFrame([(i, 8 * i + j, 1) for i in range(40) for j in range(8)], "sg_id bigint, v bigint, w bigint")
    g = from_edges(members.where("v % 8 > 0").selectExpr("v - 1 as src", "v as dst").distinct())
    for buckets in (1, 4):
        for parts in (packing.balanced_parts, packing.grow_parts):
            a = packing.pack_partition_grow(g, members, 10, PackOptions(40, None, n_buckets=buckets), parts(g, 10))
            assert {n for _, n in rows(packing.audit(members, a, 40), "rule", "violations")} == {0}


def test_parts_cover_every_vertex_once_and_are_balanced(spark):
    g = graph(spark, [(i, i + 1) for i in range(59)] + [(i, i + 7) for i in range(50)])
    for parts in (packing.balanced_parts(g, 5), packing.grow_parts(g, 5)):
        got = rows(parts, "v", "part")
        assert sorted(v for v, _ in got) == list(range(60)) and len({p for _, p in got}) <= 5
    n, cut_edges, largest = rows(packing.cut_edges(g, packing.grow_parts(g, 5)), "n_parts", "n_cut", "largest")[0]
    assert 0 < cut_edges < 109 and largest <= 60


def test_samples_of_oversized_subgraphs_fit(spark):
    m = spark.createDataFrame([(1, v, 1 + v % 3) for v in range(1, 200)] + [(2, v, 1) for v in range(2, 9)], "sg_id bigint, v bigint, w bigint")
    got = rows(sampling.fit(m, 30), "sg_id", "v", "w")
    assert sum(w for c, _, w in got if c == 1) <= 30 and (1, 1, 2) in got and [v for c, v, _ in got if c == 2] == list(range(2, 9))
    assert rows(sampling.fit(m, 30), "sg_id", "v", "w") == got and sum(w for c, _, w in got if c == 1) > 15


def test_leftovers_merge_by_rounds(spark, monkeypatch):
    members = spark.createDataFrame([(i, 100 * (i % 6) + i, 1) for i in range(60)], "sg_id bigint, v bigint, w bigint")
    start = members.selectExpr("sg_id", "sg_id + 1 as bin_id")
    monkeypatch.setattr(packing, "TASK_BINS", 8)
    a = packing.merge_underfilled(members, start, PackOptions(20, None))
    assert {n for _, n in rows(packing.audit(members, a, 20), "rule", "violations")} == {0} and a.select("bin_id").distinct().count() < 12


def test_strategy_follows_the_size(spark):
    g, spec = graph(spark, K), NeighborhoodSpec(k=2)
    assert extract.choose_strategy(g, spec) == "local" and extract.choose_strategy(g, spec, 100) == "distributed"
    assert rows(extract.members(g, spec), "sg_id", "v", "hop") == rows(extract.members(g, spec, 100), "sg_id", "v", "hop")


def test_a_user_program_in_supersteps(spark):
    """Breadth-first distances from vertex 1, stopped by the program's own aggregate."""
    import numpy as np

    def step(b):
        new = b.cur.copy()
        np.minimum.at(new, b.dst, b.cur[b.src] + 1)
        return new

    g = graph(spark, [(1, 2), (2, 3), (3, 4), (4, 5), (2, 5), (6, 7)])
    bins = g.vertices.select(F.col("id").alias("v"), (F.col("id") % 3).alias("bin_id"))
    far = F.sum((F.col("cur") >= 100).cast("bigint")).alias("far")
    program = iterate.Iterative(lambda n: F.when(F.col("v") == 1, 0).otherwise(100), step, aggregates=(far,), stop=lambda row, r: row.far == 2)
    run = iterate.supersteps(g, bins, program)
    assert rows(run.state.where("v < 6"), "v", "cur") == [(1, 0), (2, 1), (3, 2), (4, 3), (5, 2)] and run.rounds == 3
    assert len(run.metrics) == 3 and all(len(m) == 6 for m in run.metrics)
    every = iterate.supersteps(g, bins, iterate.min_label(), changed_only=False)
    assert rows(every.state, "v", "cur") == [(1, 1), (2, 1), (3, 1), (4, 1), (5, 1), (6, 6), (7, 6)]


def test_readers(spark, tmp_path):
    from egoweave.sources import readers

    (tmp_path / "edges.txt").write_text("# comment\n1 2\n2\t3\nbad line\n\n")
    (tmp_path / "adj.txt").write_text("1 2 3\n4\n")
    (tmp_path / "kv.json").write_text('{"id": 1, "nbrs": [2, 3]}\n{"nbrs": [1]}\n')
    assert rows(readers.read_edge_list(spark, f"{tmp_path}/edges.txt"), "src", "dst") == [(1, 2), (2, 3)]
    assert rows(readers.read_adjacency(spark, f"{tmp_path}/adj.txt"), "src", "dst") == [(1, 2), (1, 3)]
    assert rows(readers.read_kv(spark, f"{tmp_path}/kv.json"), "src", "dst") == [(1, 2), (1, 3)]
    a = spark.createDataFrame([(1, 2)], "sg_id bigint, bin_id bigint")
    readers.save_placement(a, f"{tmp_path}/a")
    assert rows(readers.load_placement(spark, f"{tmp_path}/a"), "sg_id", "bin_id") == [(1, 2)]
    assert len(rows(readers.grid(spark, 4), "src", "dst")) == 24


def test_measures(spark):
    from egoweave import metrics, workloads

    got = metrics.measured(spark, lambda: spark.range(1000).groupBy((F.col("id") % 7).alias("k")).count().count())
    assert got["status"] == "ok" and got["result"] == 7 and got["seconds"] > 0 and got["shuffle_records"] > 0
    assert metrics.measured(spark, lambda: 1 / 0)["status"] == "DNC"
    assert rows(metrics.diameter(graph(spark, [(i, i + 1) for i in range(9)])), "diameter") == [(9,)]
    assert metrics.gap(6, 4, 5) == (1.2, 1.5)
    few = workloads.attachment_packers(spark, count=2, packers=("sketch", "exact"))
    assert all(r.lower <= r.upper <= r.n_bins for r in few.where("packer = 'exact'").collect())
    assert {r.packer for r in workloads.gaps(few).collect()} == {"sketch", "exact"}
    factors = workloads.improvement(spark.createDataFrame([("a", "g", "engine", "ok", 2.0), ("a", "g", "bsp", "ok", 5.0), ("a", "g", "gas", "OOM", None)], "app string, graph string, model string, status string, node_seconds double"))
    assert rows(factors.where("factor is not null"), "model", "factor") == [("bsp", 2.5)]
    assert len(workloads.attachment_instances()) == 64 and max(n * m for n, m, _ in workloads.attachment_instances()) == 20000


def test_a_cluster_needs_a_shared_folder(spark, monkeypatch):
    from types import SimpleNamespace

    from egoweave import session

    far = SimpleNamespace(conf=SimpleNamespace(get=lambda *a: None), sparkContext=SimpleNamespace(master="spark://host:7077"))
    with pytest.raises(RuntimeError):
        session.shared_dir(far)
