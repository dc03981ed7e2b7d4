"""Packing of weighted vertex sets into bins that are charged for the union: the sequential parts, run inside one task per bucket."""

from __future__ import annotations

import contextlib
import gc
import math
import sys
import time
from collections import Counter, defaultdict
from collections.abc import Iterable, Iterator, Sequence
from dataclasses import dataclass, field
from itertools import chain

import numpy as np

from ..functions.minhash import A, B, P, coefficients

Set = frozenset


@dataclass
class Problem:
    """Items in the order in which they are to be placed; weights default to one a vertex."""

    ids: list[int]
    sets: list[Set]
    capacity: int
    max_items: int | None = None
    weights: dict[int, int] = field(default_factory=dict)
    overlap: bool = True

    def weight(self, s) -> int:
        return len(s) if not self.weights else sum(self.weights[v] for v in s)

    def limit(self) -> float:
        return math.inf if self.max_items is None else self.max_items


@contextlib.contextmanager
def uncollected() -> Iterator[None]:
    """No searches for cycles: a kernel makes none, and its many sets and lists would be walked again and again."""
    was = gc.isenabled()
    gc.disable()
    try:
        yield
    finally:
        if was:
            gc.enable()


def signature(s: Set, n: int = 6) -> tuple[int, ...]:
    return tuple(min((a * (v % P) + b) % P for v in s) for a, b in map(coefficients, range(n))) if s else (P,) * n


def signatures(sets: Sequence[Set], n: int = 6) -> list[tuple[int, ...]]:
    """signature() of many sets at once."""
    full = [s for s in sets if s]
    flat = np.fromiter((v for s in full for v in s), np.int64) % P
    starts = np.cumsum([0, *map(len, full)])[:-1]
    got = iter(list(zip(*(np.minimum.reduceat((a * flat + b) % P, starts).tolist() for a, b in map(coefficients, range(n))), strict=True)) if full else [])
    return [next(got) if s else (P,) * n for s in sets]


class FirstFit:
    """Places in order, each with two numbers: a tree of their minima finds the first place from a given one where both are small enough.

    A node has WIDE children, looked through as slices, so that a path is few steps and makes few objects.
    """

    BITS = 5
    WIDE = 1 << BITS

    def __init__(self, places: Iterable[tuple[float, float]] = ()):
        places = list(places)
        #: lists of the first and of the second number, the places at 0 and the root's children last
        self.levels = [tuple([x[side] for x in places] for side in (0, 1))]
        self._grow()

    def _grow(self) -> None:
        while len(self.levels[-1][0]) > self.WIDE:
            last = self.levels[-1]
            self.levels.append(tuple([min(x[i : i + self.WIDE]) for i in range(0, len(x), self.WIDE)] for x in last))

    def put(self, i: int, one: float, two: float) -> None:
        """Set the numbers of place i, which is there or the next."""
        levels, bits, wide = self.levels, self.BITS, self.WIDE
        for side, x in ((0, one), (1, two)):
            at = i
            for k, level in enumerate(levels):
                row = level[side]
                if at == len(row):
                    old = math.inf
                    row.append(x)
                else:
                    old = row[at]
                    row[at] = x
                if k + 1 == len(levels):
                    break
                at >>= bits
                above = levels[k + 1][side]
                if at < len(above):
                    low = above[at]
                    if x > low:
                        if old > low:
                            break
                        x = min(row[at * wide : at * wide + wide])
                    if x == low:
                        break
        if len(levels[-1][0]) > wide:
            self._grow()

    def first(self, one: float, two: float, start: int = 0) -> int | None:
        """The first place from start on whose numbers are at most these."""
        levels, bits, wide = self.levels, self.BITS, self.WIDE
        k, i = (0, start) if start else (len(levels) - 1, 0)
        while k < len(levels):
            a, b = levels[k]
            end = (i & -wide) + wide
            for j, x in enumerate(a[i:end]):
                if x <= one and b[i + j] <= two:
                    if not k:
                        return i + j
                    k, i = k - 1, i + j << bits
                    break
            else:  # on with the parent's next sibling
                k, i = k + 1, (i >> bits) + 1
        return None


def place_greedy(p: Problem, counts: Sequence[int] | None = None, start: Sequence[tuple[set[int], int]] = ()) -> list[int]:
    """Bin of each item, from 1: the first bin, in order of opening, whose union and number of items stay in bounds.

    Overlaps come from an index vertex -> bins that can still take an item; the first bin that has room without an overlap comes
    from a tree, so an item costs its vertices' postings and a path rather than a test a bin. Bins only fill up, so the tree may
    hold what a bin had before, and the first bin for a size never moves back. Vertices of one bin share a posting, and bins hold
    the sets themselves, so few objects are made. counts gives how many subgraphs an item stands for; start has the bins that are
    open already, as (vertices, items).
    """
    load, held, most = [], [], p.limit()
    inside: list[list[Set]] = []
    alone: list[tuple[int]] = []
    where: dict[int, tuple[int] | list[int]] = {}
    indexed = where.keys()
    free, since = FirstFit(), {}
    out = []

    def open_bin() -> int:
        b = len(load)
        load.append(0)
        held.append(0)
        inside.append([])
        alone.append((b,))
        return b

    def room(size: int, n: int) -> int | None:
        """The first bin with room for so much weight and so many items."""
        one, two, key = p.capacity - size, most - n, (size, n) if counts else size
        b = since.get(key, 0)
        while b is not None and b < len(load) and (load[b] > one or held[b] > two):
            b = free.first(one, two, b)
            if b is not None and (load[b] > one or held[b] > two):
                free.put(b, load[b], held[b])
        since[key] = len(load) if b is None else b
        return b if b is not None and b < len(load) else None

    def keep(b: int, s, known: set[int], size: int, n: int) -> None:
        """Bin b has s too, some of it indexed already; a bin that no item can join any more leaves the index."""
        first = not held[b]
        load[b] += size
        held[b] += n
        if first:
            free.put(b, load[b], held[b])
        if held[b] + 1 > most:
            for v in set().union(*inside[b]):
                if len(where[v]) > 1:
                    where[v].remove(b)
                else:
                    del where[v]
            inside[b] = []
            load[b] = math.inf
        elif p.overlap:
            inside[b].append(s)
            for v in known:
                at = where[v]
                if at.__class__ is tuple:
                    if at[0] != b:
                        where[v] = [at[0], b]
                elif first or b not in at:
                    at.append(b)
            for v in s:
                if v not in where:
                    where[v] = alone[b]

    for s, n in start:
        keep(open_bin(), s, indexed & s, p.weight(s), n)
    for k, s in enumerate(p.sets):
        n = counts[k] if counts else 1
        size = p.weight(s)
        known = indexed & s if p.overlap else ()
        shared = shared_weights(p, known, where) if known else {}
        chosen = room(size, n)
        for b, x in shared.items():
            if (chosen is None or b < chosen) and load[b] + size - x <= p.capacity and held[b] + n <= most:
                chosen = b
        if chosen is None:
            chosen = open_bin()
        keep(chosen, s, known, size - shared.get(chosen, 0), n)
        out.append(chosen + 1)
    return out


def regroup(p: Problem, groups: list[list[int]]) -> list[int]:
    """Bins of the items when whole groups are placed greedily, largest union first; a group over the bounds falls back to its items."""
    parts: list[list[int]] = []
    for g in groups:
        union = Set().union(*(p.sets[i] for i in g))
        parts += [g] if p.weight(union) <= p.capacity and len(g) <= p.limit() else [[i] for i in g]
    unions = [Set().union(*(p.sets[i] for i in g)) for g in parts]
    order = sorted(range(len(parts)), key=lambda j: (-p.weight(unions[j]), p.ids[parts[j][0]]))
    placed = place_greedy(Problem([0] * len(order), [unions[j] for j in order], p.capacity, p.max_items, p.weights), [len(parts[j]) for j in order])
    out = [0] * len(p.sets)
    for j, b in zip(order, placed, strict=True):
        for i in parts[j]:
            out[i] = b
    return out


@dataclass
class Cluster:
    items: list[int]
    union: Set
    sign: tuple[int, ...]


def pick_threshold(distances: list[float], percentile: float = 10) -> float:
    """The distance below which so many percent of the sampled pairs lie."""
    ranked = sorted(distances)
    return ranked[min(len(ranked) - 1, max(0, math.ceil(percentile / 100 * len(ranked)) - 1))]


def pair_distance(p: Problem, a: Cluster, b: Cluster) -> float | None:
    """Weighted Jaccard distance, or None where the two may not share a bin."""
    union = a.union | b.union
    total = p.weight(union)
    if total > p.capacity or len(a.items) + len(b.items) > p.limit():
        return None
    return 1 - p.weight(a.union & b.union) / total


class Partners:
    """Which clusters share a vertex and may share a bin, with their distance, kept from pass to pass: only what merged is counted again.

    More than PAIRS pairs a member are not held; merge_pass then counts anew.
    """

    PAIRS = 4

    def __init__(self, p: Problem):
        self.p, self.most, self.pairs = p, self.PAIRS * sum(map(len, p.sets)), 0
        self.near: dict[int, dict[int, float]] = {}
        self.held: dict[int, tuple[Cluster, int]] = {}
        self.where: dict[int, list[int]] = defaultdict(list)

    def follow(self, clusters: list[Cluster]) -> bool:
        """Take up these clusters; False where they have too many partners to hold."""
        if self.pairs <= self.most:
            now = set(map(id, clusters))
            for k in [k for k in self.held if k not in now]:
                for v in self.held.pop(k)[0].union:
                    self.where[v].remove(k)
                gone = self.near.pop(k)
                self.pairs -= len(gone)
                for j in gone:
                    del self.near[j][k]
            for c in clusters:
                if id(c) not in self.held:
                    self._add(c)
                    if self.pairs > self.most:
                        self.near, self.held, self.where = {}, {}, {}
                        break
        return self.pairs <= self.most

    def _add(self, c: Cluster) -> None:
        k, load = id(c), self.p.weight(c.union)
        near: dict[int, float] = {}
        for j, x in shared_weights(self.p, c.union, self.where).items():
            other, size = self.held[j]
            total = load + size - x
            if total <= self.p.capacity and len(c.items) + len(other.items) <= self.p.limit():
                near[j] = self.near[j][k] = 1 - x / total
        self.pairs += len(near)
        self.near[k], self.held[k] = near, (c, load)
        for v in c.union:
            self.where[v].append(k)


def merge_pass(p: Problem, clusters: list[Cluster], window: int, threshold: float, strict: bool = True, partners: Partners | None = None) -> tuple[list[Cluster], int]:
    """One pass from left to right: each cluster joins its closest free follower within the window if that is near enough.

    In a wide window the followers that share a vertex come from partners, or from an index vertex -> places, and the first one
    without a common vertex, whose distance is 1, from a tree over loads and items.
    """
    n = len(clusters)
    taken, out, merged = [False] * n, [], 0
    wide, apart = window > 16, threshold > 1 or not strict and threshold >= 1
    load, held, most = [p.weight(c.union) for c in clusters], [len(c.items) for c in clusters], p.limit()
    known = wide and partners is not None and partners.follow(clusters)
    if known:
        at = {id(c): i for i, c in enumerate(clusters)}
    elif wide:
        where: dict[int, list[int]] = defaultdict(list)
        for i in range(n - 1, -1, -1):  # the nearest follower last
            for v in clusters[i].union:
                where[v].append(i)
    if wide:
        free = FirstFit(zip(load, held, strict=True) if apart else ())
    for i, a in enumerate(clusters):
        if wide and apart:
            free.put(i, math.inf, math.inf)
        if wide and not known:
            for v in a.union:
                while where[v] and (where[v][-1] <= i or taken[where[v][-1]]):
                    where[v].pop()
        if taken[i]:
            continue
        best = None
        if known:
            for k, d in partners.near[id(a)].items():
                j = at[k]
                if i < j <= i + window and not taken[j] and (d < threshold or not strict and d <= threshold) and (best is None or (d, j) < best):
                    best = (d, j)
        elif wide:
            shared: dict[int, int] = {}
            for v in a.union:
                x = p.weights[v] if p.weights else 1
                for j in reversed(where[v]):
                    if j > i + window:
                        break
                    if not taken[j]:
                        shared[j] = shared.get(j, 0) + x
            for j, x in shared.items():
                total = load[i] + load[j] - x
                if total <= p.capacity and held[i] + held[j] <= most:
                    d = 1 - x / total
                    if (d < threshold or not strict and d <= threshold) and (best is None or (d, j) < best):
                        best = (d, j)
        else:
            for j in range(i + 1, min(i + window, n - 1) + 1):
                if taken[j] or load[j] > p.capacity or held[i] + held[j] > most:
                    continue
                if a.union.isdisjoint(clusters[j].union):
                    if not apart or best is not None or load[i] + load[j] > p.capacity:
                        continue
                    d = 1.0
                else:
                    x = p.weight(a.union & clusters[j].union)
                    total = load[i] + load[j] - x
                    if total > p.capacity:
                        continue
                    d = 1 - x / total
                if (d < threshold or not strict and d <= threshold) and (best is None or d < best[0]):
                    best = (d, j)
        if wide and apart and (best is None or best[0] >= 1):
            j = free.first(p.capacity - load[i], most - held[i], i + 1)
            if j is not None and j <= i + window and (best is None or (1.0, j) < best):
                best = (1.0, j)
        if best:
            b = clusters[best[1]]
            taken[best[1]] = True
            if wide and apart:
                free.put(best[1], math.inf, math.inf)
            merged += 1
            a = Cluster(a.items + b.items, a.union | b.union, tuple(map(min, a.sign, b.sign)))
        out.append(a)
    return sorted(out, key=lambda c: (c.sign, p.ids[c.items[0]])), merged


#: Pairs whose draws are made at once.
DRAWS = 1 << 18


def sampled_pairs(n: int, window: int, share: float, state: int) -> tuple[np.ndarray, np.ndarray, int]:
    """(i, j, state): the pairs of n places within the window that a congruential generator picks, from 100 pairs on, else all of them; no pair list is held."""
    each = np.minimum(window, n - 1 - np.arange(n))
    ends = np.cumsum(each)
    count = int(ends[-1])
    if count * share >= 1 and count >= 100:
        power = np.ones(1, np.int64)
        while len(power) < min(count, DRAWS):
            power = np.concatenate([power, power * pow(48271, len(power), P) % P])
        hits = []
        for lo in range(0, count, len(power)):
            drawn = state * 48271 % P * power[: count - lo] % P
            hits.append(np.flatnonzero(drawn < share * P) + lo)
            state = int(drawn[-1])
        at = np.concatenate(hits)
        at = at if len(at) else np.arange(100)
    else:
        at = np.arange(count)
    i = np.searchsorted(ends, at, "right")
    return i, i + 1 + at - (ends[i] - each[i]), state


#: Pairs that one step of a filter looks at.
STEP = 1 << 16


def may_fit(p: Problem, clusters: list[Cluster], first: np.ndarray, second: np.ndarray) -> np.ndarray:
    """Which pairs of clusters are not ruled out by bit sketches: a bit that only one of two sets has is a vertex that only it has."""
    size = np.array([len(c.union) for c in clusters])
    words = 1 << max(2, (int(size.max(initial=1)) // 16).bit_length())
    words = min(words, 64)
    flat = np.fromiter((v for c in clusters for v in c.union), np.int64, int(size.sum()))
    bit = ((flat % P * A[0] + B[0]) % P) % (64 * words)
    sketch = np.zeros((len(clusters), words), np.uint64)
    np.bitwise_or.at(sketch, (np.repeat(np.arange(len(clusters)), size), bit // 64), np.uint64(1) << (bit % 64).astype(np.uint64))
    out = np.empty(len(first), bool)
    for lo in range(0, len(first), STEP):
        i, j = first[lo : lo + STEP], second[lo : lo + STEP]
        only = np.bitwise_count(sketch[i] & ~sketch[j]).sum(axis=1, dtype=np.int64)
        out[lo : lo + STEP] = only + size[j] <= p.capacity
    return out


def sampled_distances(p: Problem, clusters: list[Cluster], first: np.ndarray, second: np.ndarray) -> list[float]:
    """pair_distance of the pairs that may share a bin; what loads, items and sketches alone rule out is not compared."""
    load, held = np.array([p.weight(c.union) for c in clusters]), np.array([len(c.items) for c in clusters])
    may = (np.maximum(load[first], load[second]) <= p.capacity) & (held[first] + held[second] <= p.limit())
    first, second = first[may], second[may]
    fits = load[first] + load[second] <= p.capacity
    if not p.weights and len(first) > len(clusters):
        may = fits.copy()
        may[~fits] = may_fit(p, clusters, first[~fits], second[~fits])
        first, second, fits = first[may], second[may], fits[may]
    out = []
    for i, j, fit in zip(first.tolist(), second.tolist(), fits.tolist(), strict=True):
        if clusters[i].union.isdisjoint(clusters[j].union):
            if fit:
                out.append(1.0)
        elif (d := pair_distance(p, clusters[i], clusters[j])) is not None:
            out.append(d)
    return out


def agglomerate(p: Problem, window: int = 8, percentile: float = 10, share: float = 0.01, stop: str = "no_pair", n_hashes: int = 6) -> list[int]:
    """Bins by repeated merging of near clusters in signature order.

    The threshold is a percentile over a share of the pairs within the window (all of them when they are under 100). When over
    half of the sampled pairs cannot share a bin, the window grows by half. A pass without a merge first
    accepts distances equal to the threshold, then widens the window, and ends when no feasible pair is left
    (stop="first_empty": at once).
    """
    clusters = sorted((Cluster([i], s, x) for i, (s, x) in enumerate(zip(p.sets, signatures(p.sets, n_hashes), strict=True))), key=lambda c: (c.sign, p.ids[c.items[0]]))
    state, partners = 1, Partners(p)
    while len(clusters) > 1:
        first, second, state = sampled_pairs(len(clusters), window, share, state)
        known = sampled_distances(p, clusters, first, second)
        merged = 0
        if known:
            threshold = pick_threshold(known, percentile)
            clusters, merged = merge_pass(p, clusters, window, threshold, True, partners)
            if not merged and stop != "first_empty":
                clusters, merged = merge_pass(p, clusters, window, threshold, False, partners)
        if not merged:
            if stop == "first_empty":
                break
            if window >= len(clusters) - 1:
                clusters, merged = merge_pass(p, clusters, window, math.inf, True, partners)
                if not merged:
                    break
            window = math.ceil(1.5 * window)
        elif len(known) * 2 < len(first):
            window = math.ceil(1.5 * window)
    return regroup_kept(p, [c.items for c in clusters])


def regroup_kept(p: Problem, groups: list[list[int]]) -> list[int]:
    """Each group is a bin."""
    out = [0] * len(p.sets)
    for b, g in enumerate(groups, 1):
        for i in g:
            out[i] = b
    return out


class MultiUnion:
    """Vertices of the sets in a cluster with how many sets hold each."""

    def __init__(self):
        self.times: Counter[int] = Counter()
        self.load = 0

    def add(self, p: Problem, s: Set) -> None:
        for v in s:
            if not self.times[v]:
                self.load += p.weights.get(v, 1) if p.weights else 1
            self.times[v] += 1

    def remove(self, p: Problem, s: Set) -> None:
        for v in s:
            self.times[v] -= 1
            if not self.times[v]:
                del self.times[v]
                self.load -= p.weights.get(v, 1) if p.weights else 1


def overlap_gain(p: Problem, s: Set, c: MultiUnion) -> float:
    """Weight shared with the cluster, or minus infinity where the union is over capacity."""
    shared = p.weight([v for v in s if v in c.times])
    return shared if c.load + p.weight(s) - shared <= p.capacity else -math.inf


def estimate_k(p: Problem, scale: float = 1.0) -> int:
    return max(1, math.ceil(scale * sum(map(p.weight, p.sets)) / p.capacity))


def index_of(clusters: list[MultiUnion]) -> dict[int, set[int]]:
    """vertex -> clusters that hold it."""
    where: dict[int, set[int]] = defaultdict(set)
    for j, c in enumerate(clusters):
        for v in c.times:
            where[v].add(j)
    return where


def shared_weights(p: Problem, s: Set, where: dict) -> dict[int, int]:
    """Weight that s shares with each cluster that holds a vertex of it."""
    if not p.weights:
        return Counter(chain.from_iterable(filter(None, map(where.get, s))))
    shared: dict[int, int] = {}
    for v in s:
        for j in where.get(v, ()):
            shared[j] = shared.get(j, 0) + p.weights[v]
    return shared


def first_assignment(p: Problem, k: int) -> tuple[list[int], list[MultiUnion]]:
    """Cluster of each item, -1 for none, from k start sets of smallest (hash of id, id): the cluster that shares most and has room.

    Clusters that share come from an index; the first that has room without sharing comes from a tree.
    """
    order = sorted(range(len(p.sets)), key=lambda i: ((A[0] * (p.ids[i] % P) + B[0]) % P, p.ids[i]))[:k]
    clusters = [MultiUnion() for _ in order]
    at = [-1] * len(p.sets)
    for c, i in enumerate(order):
        clusters[c].add(p, p.sets[i])
        at[i] = c
    where, free = index_of(clusters), FirstFit((c.load, 0) for c in clusters)
    for i in sorted(range(len(p.sets)), key=lambda i: p.ids[i]):
        if at[i] < 0:
            s = p.sets[i]
            size = p.weight(s)
            best = max(((x, -j) for j, x in shared_weights(p, s, where).items() if clusters[j].load + size - x <= p.capacity), default=None)
            if best is None or best[0] <= 0:
                j = free.first(p.capacity - size, 0)
                if j is not None and (best is None or (0, -j) > best):
                    best = (0, -j)
            if best is not None:
                c = -best[1]
                at[i] = c
                clusters[c].add(p, s)
                free.put(c, clusters[c].load, 0)
                for v in s:
                    where[v].add(c)
    return at, clusters


def reassign_pass(p: Problem, at: list[int], clusters: list[MultiUnion]) -> int:
    """Move each item to the cluster that lowers the summed load most, if any does; one that shares nothing with the item cannot."""
    moves, where = 0, index_of(clusters)
    for i in sorted(range(len(p.sets)), key=lambda i: p.ids[i]):
        a, s = at[i], p.sets[i]
        if a < 0:
            continue
        saved, size = p.weight([v for v in s if clusters[a].times[v] == 1]), p.weight(s)
        best = (0, None)
        for j, x in sorted(shared_weights(p, s, where).items()):
            if j != a and saved - (size - x) > best[0] and clusters[j].load + size - x <= p.capacity:
                best = (saved - (size - x), j)
        if best[1] is not None:
            clusters[a].remove(p, s)
            clusters[best[1]].add(p, s)
            for v in s:
                where[v].add(best[1])
                if v not in clusters[a].times:
                    where[v].discard(a)
            at[i] = best[1]
            moves += 1
    return moves


def kmeans(p: Problem, k: int | None = None, max_iter: int = 10, k0_scale: float = 1.0, trace: list | None = None) -> list[int]:
    """Bins by clustering on shared weight; clusters are placed greedily at the end. k grows by half while over a tenth of the items find no cluster."""
    if not p.sets:
        return []
    k = min(k or estimate_k(p, k0_scale), len(p.sets))
    while True:
        at, clusters = first_assignment(p, k)
        if at.count(-1) <= 0.1 * len(at) or k >= len(p.sets):
            break
        k = min(math.ceil(1.5 * k), len(p.sets))
    for _ in range(max_iter):
        if trace is not None:
            trace.append(sum(c.load for c in clusters))
        if not reassign_pass(p, at, clusters):
            break
    groups = defaultdict(list)
    for i, c in enumerate(at):
        groups[c if c >= 0 else (-1, i)].append(i)
    return regroup(p, list(groups.values()))


def lower_bound(p: Problem) -> int:
    """The largest of: union over capacity, items over the cap, and a greedy set of items of which no two share a bin."""
    if not p.sets:
        return 0
    bound = max(1, math.ceil(p.weight(Set().union(*p.sets)) / p.capacity) if max(map(p.weight, p.sets)) <= p.capacity else 1)
    if p.max_items:
        bound = max(bound, math.ceil(len(p.sets) / p.max_items))
    apart: list[Set] = []
    for s in sorted(p.sets, key=lambda s: -p.weight(s)):
        if all(p.weight(s | t) > p.capacity for t in apart):
            apart.append(s)
    return max(bound, len(apart))


def exact(p: Problem, seconds: float = 5.0, nodes: int = 200_000) -> tuple[int, int, list[int]]:
    """(lower, upper, bins): branch and bound, largest item first; an item may open one new bin at most. Equal bounds prove the optimum."""
    order = sorted(range(len(p.sets)), key=lambda i: (-p.weight(p.sets[i]), p.ids[i]))
    best = place_greedy(Problem(p.ids, [p.sets[i] for i in order], p.capacity, p.max_items, p.weights))
    upper, lower = max(best, default=0), lower_bound(p)
    until, left, done = time.monotonic() + seconds, [nodes], [True]
    now = [0] * len(order)

    def go(k: int, bins: list[tuple[Set, int]]) -> None:
        nonlocal best, upper
        if upper == lower:
            return
        left[0] -= 1
        if left[0] < 0 or (left[0] % 256 == 0 and time.monotonic() > until):
            done[0] = False
            return
        if k == len(order):
            if len(bins) < upper:
                upper, best = len(bins), now[:]
            return
        s = p.sets[order[k]]
        for b, (union, n) in enumerate(bins):
            if n < p.limit() and p.weight(new := union | s) <= p.capacity:
                now[k] = b + 1
                bins[b] = (new, n + 1)
                go(k + 1, bins)
                bins[b] = (union, n)
                if not done[0]:
                    return
        if len(bins) + 1 < upper:
            now[k] = len(bins) + 1
            bins.append((s, 1))
            go(k + 1, bins)
            bins.pop()

    if upper > lower:
        sys.setrecursionlimit(max(sys.getrecursionlimit(), len(order) + 1000))  # a call an item
        go(0, [])
    if done[0]:
        lower = upper
    out = [0] * len(order)
    for k, i in enumerate(order):
        out[i] = best[k]
    return lower, upper, out
