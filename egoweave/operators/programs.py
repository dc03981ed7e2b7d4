"""User programs on a SubgraphView."""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator
from itertools import combinations

from ..functions.minhash import P
from .engine import Program, SubgraphView


def rounded(x: float, digits: int = 6) -> float:
    """x with ties away from zero, as SQL rounds; Python's round takes them to the even digit."""
    step = 10**digits
    return math.copysign(math.floor(abs(x) * step + 0.5) / step, x) + 0.0


def _links(view: SubgraphView) -> tuple[int, int]:
    """Neighbours of the centre and edges among them, in either direction."""
    near = sorted(set(view.out(view.center)) - {view.center})
    inside = set(near)
    pairs = {(min(a, b), max(a, b)) for a in near for b in view.out(a) if b in inside and a != b}
    return len(near), len(pairs)


def lcc(undefined: str = "zero") -> Program:
    """Share of the pairs of neighbours that are linked; without a pair 0.0, or null."""

    def fn(view: SubgraphView) -> Iterator[tuple]:
        d, links = _links(view)
        yield view.center, d, links, rounded(2 * links / (d * (d - 1))) if d > 1 else (None if undefined == "null" else 0.0)

    return Program("sg_id bigint, degree bigint, links bigint, lcc double", fn)


def triangles() -> Program:
    return Program("sg_id bigint, n bigint", lambda view: [(view.center, _links(view)[1])])


def weak_ties() -> Program:
    def fn(view: SubgraphView) -> Iterator[tuple]:
        d, links = _links(view)
        yield view.center, d * (d - 1) // 2 - links

    return Program("sg_id bigint, n bigint", fn)


def _feed_forward(view: SubgraphView, role: str) -> int:
    if role == "source":
        a = view.center
        to = set(view.out(a)) - {a}
        return sum(1 for b in to for c in view.out(b) if c in to and c != b)
    return sum(1 for a in view.vertices() for b in view.out(a) for c in view.out(b) if len({a, b, c}) == 3 and view.center in (a, b, c) and view.has_edge(a, c))


def _feedback(view: SubgraphView, role: str) -> int:
    a = view.center
    return sum(1 for b in view.out(a) for c in view.out(b) if len({a, b, c}) == 3 and view.has_edge(c, a))


def _biparallel(view: SubgraphView, role: str) -> int:
    a = view.center
    paths = Counter(d for b in view.out(a) if b != a for d in view.out(b) if d not in (a, b))
    return sum(m * (m - 1) // 2 for m in paths.values())


def motif(kind: str, role: str = "source") -> Program:
    count = {"feed_forward": _feed_forward, "feedback": _feedback, "biparallel": _biparallel}[kind]
    return Program("sg_id bigint, n bigint", lambda view: [(view.center, count(view, role))])


def power(view: SubgraphView, damping: float, rounds: int) -> dict[int, float]:
    c, ids = view.center, view.vertices()
    score = dict.fromkeys(ids, 0.0)
    score[c] = 1.0
    for _ in range(rounds):
        new = dict.fromkeys(ids, 0.0)
        new[c] = 1 - damping
        for u, x in score.items():
            to = view.out(u)
            if not to:
                new[c] += damping * x
            for v in to:
                new[v] += damping * x / len(to)
        score = new
    return score


def walks(view: SubgraphView, n: int, steps: int, salt: int) -> dict[int, float]:
    """Visits of seeded walkers; one in 1000/150 steps, and every step without an edge, goes back to the centre."""
    c, visits = view.center, Counter()
    for r in range(n):
        x, v = (48271 * (c % P) + 69621 * r + salt) % P or 1, c
        for _ in range(steps):
            x = 48271 * x % P
            to = view.out(v)
            v = c if x % 1000 < 150 or not to else to[x // 1000 % len(to)]
            visits[v] += 1
    total = sum(visits.values())
    return {v: k / total for v, k in visits.items()}


def ppr(damping: float = 0.85, rounds: int = 10, method: str = "power", n_walks: int = 200, steps: int = 20, salt: int = 7) -> Program:
    def fn(view: SubgraphView) -> Iterator[tuple]:
        score = power(view, damping, rounds) if method == "power" else walks(view, n_walks, steps, salt)
        for v, s in sorted(score.items()):
            yield view.center, v, rounded(s)

    return Program("sg_id bigint, v bigint, score double", fn)


def link_prediction(top_k: int = 5, damping: float = 0.85, rounds: int = 10) -> Program:
    def fn(view: SubgraphView) -> Iterator[tuple]:
        known = {view.center, *view.out(view.center)}
        ranked = sorted(((-rounded(s), v) for v, s in power(view, damping, rounds).items() if v not in known))[:top_k]
        for k, (s, v) in enumerate(ranked, 1):
            yield view.center, v, -s + 0.0, k

    return Program("sg_id bigint, v bigint, score double, rank int", fn)


def _spread(near: list[int], out, rounds: int | None) -> dict[int, int]:
    label = {v: v for v in near}
    while rounds is None or rounds > 0:
        new = {v: min([label[v], *(label[u] for u in out(v) if u in label)]) for v in near}
        if new == label:
            break
        label = new
        if rounds is not None:
            rounds -= 1
    return label


def circles(method: str = "components", rounds: int = 10) -> Program:
    """Groups among the neighbours, the centre taken out: components, label votes, or merges that raise modularity."""

    def fn(view: SubgraphView) -> Iterator[tuple]:
        near = sorted(set(view.vertices()) - {view.center})
        inside = set(near)
        out = lambda v: [u for u in set(view.out(v)) | set(view.in_(v)) if u in inside]
        if method == "components":
            label = _spread(near, out, None)
        elif method == "votes":
            label = {v: v for v in near}
            for _ in range(rounds):
                old = dict(label)
                for v in near:
                    votes = Counter(label[u] for u in out(v))
                    if votes:
                        label[v] = min(votes, key=lambda k: (-votes[k], k))
                if label == old:
                    break
        else:
            label = {v: v for v in near}
            m2 = sum(len(out(v)) for v in near) or 1
            while True:
                between, degree = Counter(), Counter()
                for v in near:
                    degree[label[v]] += len(out(v))
                    for u in out(v):
                        if label[v] < label[u]:
                            between[label[v], label[u]] += 1
                gains = [(2 * (e / m2 - degree[a] * degree[b] / m2**2), -a, -b) for (a, b), e in between.items()]
                if not gains or max(gains)[0] <= 1e-12:
                    break
                _, a, b = max(gains)
                label = {v: -a if x == -b else x for v, x in label.items()}
        for v in near:
            yield view.center, v, label[v]

    return Program("sg_id bigint, v bigint, circle bigint", fn)


def ego_betweenness() -> Program:
    def fn(view: SubgraphView) -> Iterator[tuple]:
        c = view.center
        near = sorted(set(view.out(c)) - {c})
        total = sum(1 / sum(1 for z in view.out(x) if view.has_edge(z, y)) for x, y in combinations(near, 2) if not view.has_edge(x, y))
        yield c, rounded(total)

    return Program("sg_id bigint, betweenness double", fn)


def brokerage() -> Program:
    """Effective size, efficiency and constraint of the centre's neighbourhood."""

    def fn(view: SubgraphView) -> Iterator[tuple]:
        c = view.center
        d, links = _links(view)
        near = sorted(set(view.out(c)) - {c})
        inside = set(near)
        share = 1 / d if d else 0.0
        constraint = 0.0
        for j in near:
            direct = share
            for q in near:
                if q != j and view.has_edge(q, j):
                    # q spreads its ties over the centre and its neighbours inside
                    direct += share / (1 + sum(1 for x in view.out(q) if x in inside))
            constraint += direct**2
        size = d - 2 * links / d if d else 0.0
        yield c, rounded(size), rounded(size / d) if d else 0.0, rounded(constraint)

    return Program("sg_id bigint, effective_size double, efficiency double, constraint_ double", fn)


def ego_features() -> Program:
    """Vertices, edges, total weight and mean weight of a subgraph."""

    def fn(view: SubgraphView) -> Iterator[tuple]:
        ids = view.vertices()
        edges = [(u, v) for u in ids for v in view.out(u) if view.directed or u < v]
        w = sum(view.weight(u, v) for u, v in edges)
        yield view.center, len(ids), len(edges), w, rounded(w / len(edges)) if edges else 0.0

    return Program("sg_id bigint, n_vertices bigint, n_edges bigint, weight bigint, mean_weight double", fn)


def local_components() -> Program:
    def fn(view: SubgraphView) -> Iterator[tuple]:
        ids = view.vertices()
        label = _spread(ids, lambda v: [*view.out(v), *view.in_(v)], None)
        for v in ids:
            yield view.center, v, label[v]

    return Program("sg_id bigint, v bigint, component bigint", fn)


def visible() -> Program:
    """What the program can see, counted: the leak test."""

    def fn(view: SubgraphView) -> Iterator[tuple]:
        ids = view.vertices()
        yield view.center, len(ids), sum(1 for u in ids for v in view.out(u) if view.directed or u < v)

    return Program("sg_id bigint, n_vertices bigint, n_edges bigint", fn)


def match(pattern: list[tuple[int, int]], directed: bool = False) -> Program:
    """Occurrences of a small pattern with its node 0 at the centre; each set of mapped edges once. Backtracking over at most five nodes."""
    nodes = sorted({x for e in pattern for x in e})
    if len(nodes) > 5 or nodes[0] != 0:
        raise ValueError("patterns have nodes 0.. up to five")

    def fn(view: SubgraphView) -> Iterator[tuple]:
        found: set = set()

        def go(at: dict[int, int]) -> None:
            if len(at) == len(nodes):
                found.add(frozenset((at[a], at[b]) if directed else (min(at[a], at[b]), max(at[a], at[b])) for a, b in pattern))
                return
            x = next(n for n in nodes if n not in at and any((a in at) != (b in at) and n in (a, b) for a, b in pattern))
            a, b = next(e for e in pattern if x in e and (e[0] in at) != (e[1] in at))
            options = view.out(at[a]) if b == x else view.in_(at[b])
            for v in options:
                if v not in at.values() and all(view.has_edge(at.get(p, v), at.get(q, v)) for p, q in pattern if x in (p, q) and (p in at or p == x) and (q in at or q == x)):
                    go({**at, x: v})

        go({0: view.center})
        yield view.center, len(found)

    return Program("sg_id bigint, n bigint", fn)
