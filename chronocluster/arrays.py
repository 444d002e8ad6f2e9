"""Leiden and Louvain in one task on whole arrays: vertices move in rounds, a round stays if the objective rises.

The sequential order of kernels.py visits one vertex after the other; here a random part of those that may
gain is looked at and moved at once, so the work is sorting and counting.  Both end where no vertex gains.
Levels that have become small are finished one vertex at a time, which costs little there and finds the
better optimum.
"""

from __future__ import annotations

import random

import numpy as np

from . import kernels

#: Entries of a dense table of community by slice; larger ones are looked up by key.
DENSE = 1 << 25
#: Part of the vertices that may gain which a round looks at.
SHARE = 0.25
#: Neighbours in all rows up to which a level is finished one vertex at a time.
SMALL = 200_000


def spread(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The numbers from each start on, as many as its size, one run after the other."""
    ends = np.cumsum(sizes)
    return np.arange(ends[-1] if len(ends) else 0) - np.repeat(ends - sizes, sizes) + np.repeat(starts, sizes)


def grouped(keys: np.ndarray, *values: np.ndarray) -> tuple[np.ndarray, ...]:
    """Distinct keys in order, and for each the sums of the values."""
    if not len(keys):
        return (keys, *values)
    order = np.argsort(keys, kind="stable")
    k = keys[order]
    first = np.flatnonzero(np.concatenate([[True], k[1:] != k[:-1]]))
    return (k[first], *(np.add.reduceat(v[order], first) for v in values))


class ArrayGraph:
    """Rows of neighbours with summed weights of both directions (no loops); strengths (v, s, ko, ki) in order of v."""

    def __init__(self, n: int, keys: np.ndarray, weights: np.ndarray, v: np.ndarray, s: np.ndarray, ko: np.ndarray, ki: np.ndarray, slices: int):
        self.n, self.slices = n, slices
        self.rows, self.cols = np.divmod(keys, max(n, 1))
        self.w = weights
        self.at = np.searchsorted(self.rows, np.arange(n + 1))
        self.v, self.s, self.ko, self.ki = v, s, ko, ki
        self.own = np.searchsorted(v, np.arange(n + 1))
        self.single = len(v) == n and bool((v == np.arange(n)).all())
        self.even = ko is ki or bool((ko == ki).all())

    @classmethod
    def of(cls, n: int, a: np.ndarray, b: np.ndarray, w: np.ndarray, v: np.ndarray, s: np.ndarray, ko: np.ndarray, ki: np.ndarray, slices: int) -> ArrayGraph:
        """From weighted pairs in any order; strengths of one vertex and slice add up."""
        off = a != b
        keys = np.concatenate([a[off] * np.int64(max(n, 1)) + b[off], b[off] * np.int64(max(n, 1)) + a[off]])
        keys, weights = grouped(keys, np.concatenate([w[off], w[off]]))
        vs, ko, ki = grouped(v * np.int64(slices) + s, ko, ki)
        return cls(n, keys, weights, vs // slices, vs % slices, ko, ki, slices)

    def merged(self, parts: np.ndarray) -> tuple[ArrayGraph, np.ndarray]:
        """The graph of parts, and the vertex of each old one."""
        names, to = np.unique(parts, return_inverse=True)
        m = len(names)
        a, b = to[self.rows], to[self.cols]
        off = a != b
        keys, weights = grouped(a[off] * np.int64(m) + b[off], self.w[off])
        vs, ko, ki = grouped(to[self.v] * np.int64(self.slices) + self.s, self.ko, self.ki)
        return ArrayGraph(m, keys, weights, vs // self.slices, vs % self.slices, ko, ki, self.slices), to


class Totals:
    """Strengths of communities by slice."""

    def __init__(self, g: ArrayGraph, part: np.ndarray):
        self.slices = g.slices
        key = part[g.v] * np.int64(g.slices) + g.s
        self.dense = g.n * g.slices <= DENSE
        if self.dense:
            size = g.n * g.slices
            self.ko = np.bincount(key, g.ko, minlength=size)
            self.ki = self.ko if g.even else np.bincount(key, g.ki, minlength=size)
        elif g.even:
            self.keys, self.ko = grouped(key, g.ko)
            self.ki = self.ko
        else:
            self.keys, self.ko, self.ki = grouped(key, g.ko, g.ki)

    def of(self, c: np.ndarray, s: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        key = c * np.int64(self.slices) + s if self.slices > 1 else c
        if self.dense:
            to = self.ko[key]
            return to, to if self.ki is self.ko else self.ki[key]
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        held = self.keys[at] == key
        to = np.where(held, self.ko[at], 0.0)
        return to, to if self.ki is self.ko else np.where(held, self.ki[at], 0.0)

    def held(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Keys (community * slices + slice) in order, and the strengths of each."""
        if not self.dense:
            return self.keys, self.ko, self.ki
        keys = np.flatnonzero(self.ko) if self.ki is self.ko else np.flatnonzero((self.ko != 0) | (self.ki != 0))
        return keys, self.ko[keys], self.ki[keys]

    def null(self, rate: np.ndarray) -> float:
        per = np.arange(len(self.ko)) % self.slices if self.dense else self.keys % self.slices
        return float((rate[per] * self.ko * self.ki).sum())

    def moved(self, g: ArrayGraph, some: np.ndarray, old: np.ndarray, new: np.ndarray, rate: np.ndarray) -> float:
        """Carry the strengths of vertices from old to new communities (dense tables); returns the change of the null."""
        number = g.own[some + 1] - g.own[some]
        e = spread(g.own[some], number)
        s, slices = g.s[e], np.int64(self.slices)
        keys, at = np.unique(np.concatenate([np.repeat(old, number) * slices + s, np.repeat(new, number) * slices + s]), return_inverse=True)
        per = rate[keys % self.slices]
        before = per * self.ko[keys] * self.ki[keys]
        for table, k in ((self.ko, g.ko),) if self.ki is self.ko else ((self.ko, g.ko), (self.ki, g.ki)):
            table[keys] += np.bincount(at, np.concatenate([-k[e], k[e]]), minlength=len(keys))
        return float((per * self.ko[keys] * self.ki[keys] - before).sum())


def links(g: ArrayGraph, some: np.ndarray, part: np.ndarray, inside: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Pairs (place in some, community, weight) in order, the own community of each vertex among them.

    With inside, a label of each vertex, links to other labels do not count.
    """
    degree = g.at[some + 1] - g.at[some]
    e = spread(g.at[some], degree)
    i = np.repeat(np.arange(len(some)), degree)
    if inside is not None:
        near = inside[g.cols[e]] == inside[some[i]]
        e, i = e[near], i[near]
    keys = np.concatenate([i * np.int64(g.n) + part[g.cols[e]], np.arange(len(some)) * np.int64(g.n) + part[some]])
    keys, w = grouped(keys, np.concatenate([g.w[e], np.zeros(len(some))]))
    return keys // g.n, keys % g.n, w


def gains(g: ArrayGraph, some: np.ndarray, i: np.ndarray, c: np.ndarray, w: np.ndarray, part: np.ndarray, rate: np.ndarray, totals: Totals) -> np.ndarray:
    """What each pair of links() adds to twice the objective, the vertex's own strength left out."""
    v = some[i]
    if g.single:
        e, pair = v, slice(None)
    else:
        number = g.own[v + 1] - g.own[v]
        e, pair = spread(g.own[v], number), np.repeat(np.arange(len(i)), number)
    s, ko = g.s[e], g.ko[e]
    to, ti = totals.of(c[pair], s)
    mine = (part[v] == c)[pair]
    if g.even:
        null = 2 * rate[s] * ko * (to - mine * ko)
    else:
        ki = g.ki[e]
        null = rate[s] * (ko * (ti - mine * ki) + ki * (to - mine * ko))
    return w - (null if g.single else np.bincount(pair, null, minlength=len(i)))


def _inside_change(g: ArrayGraph, part: np.ndarray, some: np.ndarray, new: np.ndarray) -> float:
    """How the weight inside communities changes when some vertices move to new ones."""
    degree = g.at[some + 1] - g.at[some]
    e = spread(g.at[some], degree)
    after, far = part.copy(), g.cols[e]
    after[some] = new
    moves = np.zeros(g.n, dtype=bool)
    moves[some] = True
    change = (np.repeat(new, degree) == after[far]).astype(float) - (np.repeat(part[some], degree) == part[far])
    return float((g.w[e] * change * np.where(moves[far], 1, 2)).sum()) / 2


def _empty(part: np.ndarray, n: int, count: int) -> np.ndarray:
    used = np.zeros(n, dtype=bool)
    used[part] = True
    return np.flatnonzero(~used)[:count]


def local_move(g: ArrayGraph, part: np.ndarray, rate: np.ndarray, rng: np.random.Generator, share: float = SHARE, movable: np.ndarray | None = None) -> int:
    """Move vertices to their best neighbouring community, or out of a bad one, until none gains; returns the moves.

    Vertices that are not movable stay where they are.
    If a round's moves do not raise the objective together, half of them are tried, at last the one that gains most.
    """
    totals = Totals(g, part)
    scale, moves = float(g.w.sum()), 0
    least = max(1e-9, 1e-13 * scale)
    movable = np.ones(g.n, dtype=bool) if movable is None else movable
    active = movable.copy()
    while len(some := np.flatnonzero(active)):
        if len(some) > 256:
            some = some[rng.random(len(some)) < share]
            if not len(some):
                continue
        i, c, w = links(g, some, part)
        gain = gains(g, some, i, c, w, part, rate, totals)
        first = np.flatnonzero(np.concatenate([[True], i[1:] != i[:-1]]))
        best = np.maximum.reduceat(gain, first)
        own = c == part[some][i]
        stay = np.full(len(some), -np.inf)
        stay[i[own]] = gain[own]
        top = np.flatnonzero(gain >= best[i] - 1e-12)
        target = c[top[np.concatenate([[True], i[top][1:] != i[top][:-1]])]]
        leaves = best < -1e-12  # the vertex is better off alone
        more = np.where(leaves, 0.0, best) - stay
        active[some] = False
        wants = more > least
        movers, more, to = some[wants], more[wants], np.where(leaves, -1, target)[wants]
        while len(movers):
            new = to.copy()
            alone = np.flatnonzero(to < 0)
            new[alone] = _empty(part, g.n, len(alone))
            old = part[movers]
            rise = _inside_change(g, part, movers, new)
            if totals.dense:
                rise -= totals.moved(g, movers, old, new, rate)
            else:
                before = totals.null(rate)
                after = part.copy()
                after[movers] = new
                there = Totals(g, after)
                rise -= there.null(rate) - before
            if rise > least / 4:
                part[movers] = new
                if not totals.dense:
                    totals = there
                near = g.cols[spread(g.at[movers], g.at[movers + 1] - g.at[movers])]
                by = np.repeat(new, g.at[movers + 1] - g.at[movers])
                near = near[part[near] != by]
                active[near[movable[near]]] = True
                moves += len(movers)
                break
            if totals.dense:
                totals.moved(g, movers, new, old, rate)
            if len(movers) == 1:
                break  # what it gains is below the rounding of the objective
            half = rng.random(len(movers)) < 0.5 if len(movers) > 2 else np.arange(len(movers)) == np.argmax(more)
            half[np.argmax(more)] = True
            active[movers[~half]] = True
            movers, more, to = movers[half], more[half], to[half]
    return moves


def refine(g: ArrayGraph, part: np.ndarray, rate: np.ndarray, rng: np.random.Generator, theta: float) -> np.ndarray:
    """Well-connected parts of each community, grown from single vertices until none can join another.

    In a round half of the vertices that are still alone may join a part that does not move itself; the
    target is drawn in proportion to exp(gain / (theta * mean gain)).
    """
    sub = np.arange(g.n)
    whole = Totals(g, part)
    same = part[g.rows] == part[g.cols]
    while True:
        cross = same & (sub[g.rows] != sub[g.cols])
        out = np.bincount(sub[g.rows[cross]], g.w[cross], minlength=g.n)
        totals = Totals(g, sub)
        vs, ko, ki = totals.held()
        r, s = vs // g.slices, vs % g.slices
        to, ti = whole.of(part[r], s)
        null = np.bincount(r, rate[s] * (ko * (ti - ki) + ki * (to - ko)), minlength=g.n)
        size = np.bincount(sub, minlength=g.n)
        good = (out >= null - 1e-9) & (size > 0)
        loose = np.flatnonzero(good & (size == 1) & (sub == np.arange(g.n)))
        if not len(loose):
            return sub
        i, c, w = links(g, loose, sub, part)
        gain = gains(g, loose, i, c, w, sub, rate, totals)
        can = (gain > 1e-9) & good[c] & (c != sub[loose][i])
        if not can.any():
            return sub
        turn = np.zeros(g.n, dtype=bool)
        turn[loose] = rng.random(len(loose)) < 0.5
        can &= turn[loose[i]] & ~turn[c]
        i, c, gain = i[can], c[can], gain[can]
        if not len(i):
            continue
        if theta > 0:
            mean = np.bincount(i, gain)[i] / np.bincount(i)[i]
            gain = gain / (theta * mean) + rng.gumbel(size=len(gain))
        order = np.lexsort((-gain, i))
        first = order[np.concatenate([[True], i[order][1:] != i[order][:-1]])]
        sub[loose[i[first]]] = c[first]


def connected(g: ArrayGraph, labels: np.ndarray) -> np.ndarray:
    """Labels of the connected parts of communities: a part apart from the rest only adds to the null."""
    inside = labels[g.rows] == labels[g.cols]
    rows, cols = g.rows[inside], g.cols[inside]
    low = np.arange(g.n)
    if not len(rows):
        return low
    first = np.flatnonzero(np.concatenate([[True], rows[1:] != rows[:-1]]))
    while True:
        after = low.copy()
        after[rows[first]] = np.minimum(low[rows[first]], np.minimum.reduceat(low[cols], first))
        after = after[after]
        if (after == low).all():
            return low
        low = after


def finish(g: ArrayGraph, part: np.ndarray, rate: np.ndarray, with_refinement: bool, theta: float, seed: int) -> np.ndarray:
    """The rest of a pass, one vertex at a time."""
    strengths: list[dict[int, tuple[float, float]]] = [{} for _ in range(g.n)]
    for v, s, ko, ki in zip(g.v.tolist(), g.s.tolist(), g.ko.tolist(), g.ki.tolist(), strict=True):
        strengths[v][s] = (ko, ki)
    objective = kernels.Objective({}, {})
    objective.rate = dict(enumerate(rate.tolist()))
    small = kernels.Graph(g.n, g.rows, g.cols, g.w / 2, strengths)
    return np.array(kernels.leiden(small, objective, 1, with_refinement, theta, seed, part.tolist()), dtype=np.int64)


def leiden(g: ArrayGraph, rate: np.ndarray, max_passes: int = 2, with_refinement: bool = True, theta: float = 0.01, seed: int = 1, start: np.ndarray | None = None, small: int = SMALL) -> np.ndarray:
    """The community of each vertex; a pass moves, refines and merges down to the coarsest graph.

    With refinement, communities that have come apart in the last moves of a pass are cut.
    """
    rng = np.random.default_rng(seed)
    labels = np.arange(g.n) if start is None else np.unique(start, return_inverse=True)[1]
    for p in range(max_passes):
        before = labels.copy()
        h, part, place = g, labels.copy(), np.arange(g.n)
        while True:
            if len(h.rows) <= small:
                part = finish(h, part, rate, with_refinement, theta, seed + p)
                break
            moves = local_move(h, part, rate, rng)
            parts = refine(h, part, rate, rng, theta) if with_refinement else part
            smaller, to = h.merged(parts)
            if smaller.n == h.n:
                break
            above = np.zeros(smaller.n, dtype=np.int64)
            above[to] = part
            part = np.unique(above, return_inverse=True)[1]
            place, h = to[place], smaller
            if not moves and smaller.n == part.max() + 1:
                break
        labels = part[place]
        labels = np.unique(connected(g, labels) if with_refinement else labels, return_inverse=True)[1]
        if (np.unique(before, return_inverse=True)[1] == labels).all():
            break
    return labels


def settle(v: np.ndarray, own_label: np.ndarray, strengths: tuple[np.ndarray, ...], totals: tuple[np.ndarray, ...], edges: tuple[np.ndarray, ...], rate: np.ndarray, seed: int) -> np.ndarray:
    """The communities of some vertices after they have moved until none gains, with all others held still.

    v: the vertices, in order; own_label: their communities; strengths: (v, s, ko, ki); totals: (community,
    s, ko, ki) of every community beside them; edges: (a, b, w, community of b), each pair from both ends.
    The held vertices of a community are one vertex that does not move.  A vertex that is better off
    alone gets a community with a negative number.
    """
    names, anchor = np.unique(np.concatenate([own_label, totals[0], edges[3]]), return_inverse=True)
    n = len(v)
    size = n + len(names)
    part = np.concatenate([n + anchor[:n], n + np.arange(len(names))])
    sv, ss, so, si = np.searchsorted(v, strengths[0]), *strengths[1:]
    tc = n + anchor[n : n + len(totals[0])]
    held = tuple(np.concatenate(x) for x in ((sv, tc, part[sv]), (ss, totals[1], ss), (so, totals[2], -so), (si, totals[3], -si)))
    a, b = np.searchsorted(v, edges[0]), np.minimum(np.searchsorted(v, edges[1]), n - 1)
    inner = v[b] == edges[1]
    once = ~inner | (a < b)
    far = np.where(inner, b, n + anchor[n + len(totals[0]) :])
    keys = np.concatenate([a[once] * np.int64(size) + far[once], far[once] * np.int64(size) + a[once]])
    keys, w = grouped(keys, np.concatenate([edges[2][once]] * 2))
    slices = max(1, len(rate))
    vs, ko, ki = grouped(held[0] * np.int64(slices) + held[1], held[2], held[3])
    g = ArrayGraph(size, keys, w, vs // slices, vs % slices, ko, ki, slices)
    local_move(g, part, rate, np.random.default_rng(seed), movable=np.arange(size) < n)
    label = part[:n]
    return np.where(label >= n, names[np.maximum(label - n, 0)], -(v[np.minimum(label, n - 1)] * 1024 + seed % 1024) - 1)
