import random

import duckdb
from hypothesis import given, settings
from hypothesis import strategies as st

from egoweave.functions.bitmaps import CLASSES, SparseBitmap, choose_bitmap
from egoweave.operators import kernels as k
from egoweave.operators import programs
from egoweave.spec import parse_spec


def problem(sets, capacity=4, **kw):
    return k.Problem(list(range(1, len(sets) + 1)), [frozenset(s) for s in sets], capacity, **kw)


def test_literal_packing():
    a = [{1, 2, 3}, {6, 7, 8}, {2, 3, 4}, {7, 8, 9}]
    assert k.place_greedy(problem(a)) == [1, 2, 1, 2]
    assert max(k.place_greedy(problem(a, overlap=False))) == 4
    assert max(k.place_greedy(problem(a, max_items=1))) == 4
    b = [{1, 2}, {3, 4}, {1, 2, 5}, {3, 4, 6}]
    assert max(k.place_greedy(problem(b))) == 3
    order = sorted(b, key=len, reverse=True)
    assert max(k.place_greedy(problem(order))) == 2
    assert k.exact(problem(b))[:2] == (2, 2)


def brute(sets, capacity, max_items):
    best = len(sets)

    def go(i, bins):
        nonlocal best
        if len(bins) >= best:
            return
        if i == len(sets):
            best = len(bins)
            return
        for j, (u, n) in enumerate(bins):
            if len(u | sets[i]) <= capacity and n < max_items:
                go(i + 1, [*bins[:j], (u | sets[i], n + 1), *bins[j + 1 :]])
        go(i + 1, [*bins, (sets[i], 1)])

    go(0, [])
    return best


@settings(max_examples=40, deadline=None)
@given(st.lists(st.frozensets(st.integers(0, 9), min_size=1, max_size=4), min_size=1, max_size=7), st.integers(4, 7), st.integers(1, 4))
def test_packers_keep_bounds(sets, capacity, items):
    p = problem(sets, capacity, max_items=items)
    exact = k.exact(p)
    assert exact[0] == exact[1] == brute(p.sets, capacity, items)
    for bins in (k.place_greedy(p), k.agglomerate(p), k.kmeans(p), exact[2]):
        assert len(bins) == len(sets)
        for b in set(bins):
            held = [s for s, x in zip(p.sets, bins, strict=True) if x == b]
            assert len(held) <= items and len(frozenset().union(*held)) <= capacity
        assert max(bins) >= exact[0] >= k.lower_bound(p)


def test_kmeans_objective_falls():
    r = random.Random(3)
    p = problem([frozenset(r.sample(range(60), 8)) for _ in range(80)], 30)
    trace = []
    k.kmeans(p, trace=trace)
    assert trace == sorted(trace, reverse=True)


def test_signature_of_union_is_minimum():
    a, b = frozenset(range(5)), frozenset(range(3, 99))
    assert k.signature(a | b) == tuple(map(min, k.signature(a), k.signature(b)))


def test_bitmaps_agree():
    r = random.Random(1)
    maps = [cls(5, 200) for cls in CLASSES.values()]
    on = {(r.randrange(5), r.randrange(200)) for _ in range(120)}
    for v, bit in on:
        for m in maps:
            m.set(v, bit)
    assert all(m.get(v, b) == ((v, b) in on) for m in maps for v in range(5) for b in range(200))
    assert SparseBitmap.model_bytes(2) == 142 and choose_bitmap(1, 3252) == "sparse" and choose_bitmap(800, 3252) == "words"


def test_rule_text():
    s = parse_spec("seed p_size > 45; hops 2; edge weight > 5; keep_center false")
    assert (s.seed_pred, s.k, s.e_pred, s.keep_center) == ("p_size > 45", 2, "weight > 5", False)


def test_rounding_as_sql():
    con = duckdb.connect()
    for x in (117 / 128, 113 / 128, -117 / 128, 0.0, -0.0, 1 / 3, 0.1 + 0.2, 14.625):
        want = con.execute("select round(?::double, 6)", [x]).fetchone()[0]
        assert programs.rounded(x) == want and str(programs.rounded(x)) != "-0.0"
