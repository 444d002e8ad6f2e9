"""Single-task kernels on numpy arrays: Leiden and Louvain in the classical order, eigenpairs, k-means.

They stand for the one-machine path, run in one task behind a size check, and serve as reference.
"""

from __future__ import annotations

import math
import random
from collections import deque

import numpy as np


#: Visits of a vertex in one phase of moves, after which it counts as endless.
VISITS = 10_000
#: Entries of a table of communities by slices; larger ones are dictionaries.
DENSE = 1 << 24


class Objective:
    """sum over entries of A inside communities, less gamma_s KO KI / M_s for each community and slice.

    Modularity has strengths as ko and ki and their sum as M; the constant Potts model has sizes and M = 1.
    """

    def __init__(self, gamma: dict[int, float], total: dict[int, float]):
        self.rate = {s: gamma[s] / m if m else 0.0 for s, m in total.items()}


class Graph:
    """Neighbours with summed weights of both directions; strengths by slice for each vertex."""

    def __init__(self, n: int, a: np.ndarray, b: np.ndarray, w: np.ndarray, strengths: list[dict[int, tuple[float, float]]]):
        self.n, self.k = n, strengths
        off = a != b
        self.loops = float(w[~off].sum())
        rows, cols, vals = np.concatenate([a[off], b[off]]), np.concatenate([b[off], a[off]]), np.concatenate([w[off], w[off]])
        keys, inverse = np.unique(rows * np.int64(max(n, 1)) + cols, return_inverse=True)
        sums = np.bincount(inverse, vals, minlength=len(keys)) if len(keys) else np.zeros(0)
        r, c = keys // max(n, 1), keys % max(n, 1)
        ends = np.searchsorted(r, np.arange(n + 1))
        self.near = [list(zip(c[i:j].tolist(), sums[i:j].tolist(), strict=True)) for i, j in zip(ends[:-1], ends[1:], strict=True)]

    def aggregate(self, part: list[int]) -> tuple[Graph, list[int]]:
        """The graph of parts, and the vertex of each old one."""
        names: dict[int, int] = {}
        to = [names.setdefault(p, len(names)) for p in part]
        a = np.array([to[v] for v in range(self.n) for _ in self.near[v]], dtype=np.int64)
        b = np.array([to[u] for v in range(self.n) for u, _ in self.near[v]], dtype=np.int64)
        w = np.array([x / 2 for v in range(self.n) for _, x in self.near[v]], dtype=float)
        strengths: list[dict[int, tuple[float, float]]] = [{} for _ in names]
        for v, ks in enumerate(self.k):
            own = strengths[to[v]]
            for s, (o, i) in ks.items():
                p, q = own.get(s, (0.0, 0.0))
                own[s] = (p + o, q + i)
        made = Graph(len(names), a, b, w, strengths)
        made.loops += self.loops
        return made, to


def _null(k: dict[int, tuple[float, float]], total: dict[int, list[float]], rate: dict[int, float]) -> float:
    out = 0.0
    for s, (o, i) in k.items():
        t = total.get(s)
        if t is not None:
            out += rate[s] * (o * t[1] + i * t[0])
    return out


def _add(total: dict[int, list[float]], k: dict[int, tuple[float, float]], sign: int) -> None:
    for s, (o, i) in k.items():
        t = total.setdefault(s, [0.0, 0.0])
        t[0] += sign * o
        t[1] += sign * i


class _Sparse:
    """Strengths of communities by slice in dictionaries."""

    def __init__(self, g: Graph, objective: Objective):
        self.k, self.rate = g.k, objective.rate
        self.rows: dict[int, dict[int, list[float]]] = {}

    def add(self, c: int, v: int, sign: int) -> None:
        _add(self.rows.setdefault(c, {}), self.k[v], sign)

    def null(self, v: int, communities: list[int]) -> list[float]:
        return [_null(self.k[v], self.rows[c], self.rate) for c in communities]


class _Even:
    """The same with one number each, where strengths are equal in both directions."""

    def __init__(self, g: Graph, objective: Objective):
        self.k = [[(s, o) for s, (o, _) in k.items()] for k in g.k]
        self.twice = [[(s, 2 * objective.rate[s] * x) for s, x in k] for k in self.k]
        self.rows: dict[int, dict[int, float]] = {}

    def add(self, c: int, v: int, sign: int) -> None:
        row = self.rows.setdefault(c, {})
        for s, x in self.k[v]:
            row[s] = row.get(s, 0.0) + sign * x

    def null(self, v: int, communities: list[int]) -> list[float]:
        twice, rows = self.twice[v], map(self.rows.__getitem__, communities)
        return [sum([x * row[s] for s, x in twice if s in row]) for row in rows]


class _Single:
    """The same where there is one slice and strengths are equal in both directions."""

    def __init__(self, g: Graph, objective: Objective):
        self.k = [sum(o for o, _ in k.values()) for k in g.k]
        rate = next((objective.rate[s] for k in g.k for s in k), 0.0)
        self.twice = [2 * rate * k for k in self.k]
        self.rows = [0.0] * g.n

    def add(self, c: int, v: int, sign: int) -> None:
        if c >= len(self.rows):
            self.rows.extend([0.0] * (c + 1))
        self.rows[c] += sign * self.k[v]

    def null(self, v: int, communities: list[int]) -> list[float]:
        twice, rows = self.twice[v], self.rows
        return [twice * rows[c] for c in communities]


class _Dense:
    """The same for several slices, in one table of communities by slices."""

    def __init__(self, g: Graph, objective: Objective, slices: dict[int, int]):
        rate = np.array([objective.rate[s] for s in slices])
        self.at = [np.array([slices[s] for s in k], dtype=np.int64) for k in g.k]
        self.k = [np.array([o for o, _ in k.values()]) for k in g.k]
        self.twice = [2 * rate[at] * k for at, k in zip(self.at, self.k, strict=True)]
        self.rows = np.zeros((g.n, len(slices)))

    def add(self, c: int, v: int, sign: int) -> None:
        if c >= len(self.rows):
            self.rows = np.concatenate([self.rows, np.zeros((c + 1, self.rows.shape[1]))])
        self.rows[c, self.at[v]] += sign * self.k[v]

    def null(self, v: int, communities: list[int]) -> list[float]:
        return (self.rows[np.array(communities)[:, None], self.at[v]] @ self.twice[v]).tolist()


def _is_even(g: Graph) -> bool:
    return all(o == i for k in g.k for o, i in k.values())


def _table(g: Graph, objective: Objective) -> _Sparse | _Even | _Single | _Dense:
    slices = {s: i for i, s in enumerate(sorted({s for k in g.k for s in k}))}
    if not _is_even(g):
        return _Sparse(g, objective)
    if len(slices) <= 1:
        return _Single(g, objective)
    return _Dense(g, objective, slices) if g.n * len(slices) <= DENSE and sum(map(len, g.k)) >= 3 * g.n else _Even(g, objective)


def local_move(g: Graph, part: list[int], objective: Objective, rng: random.Random) -> int:
    """Move vertices to their best neighbouring community until none gains; returns the number of moves.

    A gain must exceed the rounding of the sums that it comes from; VISITS visits for each vertex are an error.
    """
    least = 1e-12 * max(1.0, max((w for near in g.near for _, w in near), default=0.0))
    table = _table(g, objective)
    for v in range(g.n):
        table.add(part[v], v, 1)
    order = list(range(g.n))
    rng.shuffle(order)
    queue, waiting, moves = deque(order), [True] * g.n, 0
    free = max(part, default=0) + 1
    visits = 0
    while queue:
        if (visits := visits + 1) > VISITS * g.n:
            raise RuntimeError(f"vertices still move after {VISITS} visits each")
        v = queue.popleft()
        waiting[v] = False
        own = part[v]
        links: dict[int, float] = {own: 0.0}
        for u, w in g.near[v]:
            c = part[u]
            links[c] = links.get(c, 0.0) + w
        table.add(own, v, -1)
        names = list(links)
        gains = [w - x for w, x in zip(links.values(), table.null(v, names), strict=True)]
        best, top = own, gains[0]
        for c, gain in zip(names, gains, strict=True):
            if c != own and (gain > top + least or abs(gain - top) <= least and best != own and c < best):
                best, top = c, gain
        if top < -least:
            best, free = free, free + 1
        table.add(best, v, 1)
        if best != own:
            part[v] = best
            moves += 1
            for u, _ in g.near[v]:
                if part[u] != best and not waiting[u]:
                    waiting[u] = True
                    queue.append(u)
    return moves


class _Parts:
    """Strengths by slice of parts, which are single vertices at first, and of the communities that hold them."""

    def __init__(self, g: Graph, part: list[int], objective: Objective):
        self.k, self.rate = g.k, objective.rate
        self.rows = [{s: list(x) for s, x in k.items()} for k in g.k]
        self.whole: dict[int, dict[int, list[float]]] = {}
        for c, k in zip(part, g.k, strict=True):
            _add(self.whole.setdefault(c, {}), k, 1)

    def add(self, t: int, v: int) -> None:
        _add(self.rows[t], self.k[v], 1)

    def null(self, v: int, t: int) -> float:
        return _null(self.k[v], self.rows[t], self.rate)

    def rest(self, t: int, c: int) -> float:
        """The null of a part and the rest of its community."""
        whole = self.whole[c]
        return sum([self.rate[s] * (o * (whole[s][1] - i) + i * (whole[s][0] - o)) for s, (o, i) in self.rows[t].items()])


class _EvenParts:
    """The same with one number each, where strengths are equal in both directions."""

    def __init__(self, g: Graph, part: list[int], objective: Objective):
        self.k = [[(s, o) for s, (o, _) in k.items()] for k in g.k]
        self.twice = {s: 2 * r for s, r in objective.rate.items()}
        self.rows = [dict(k) for k in self.k]
        self.whole: dict[int, dict[int, float]] = {}
        for c, k in zip(part, self.k, strict=True):
            own = self.whole.setdefault(c, {})
            for s, x in k:
                own[s] = own.get(s, 0.0) + x

    def add(self, t: int, v: int) -> None:
        row = self.rows[t]
        for s, x in self.k[v]:
            row[s] = row.get(s, 0.0) + x

    def null(self, v: int, t: int) -> float:
        twice, row = self.twice, self.rows[t]
        return sum([twice[s] * x * row[s] for s, x in self.k[v] if s in row])

    def rest(self, t: int, c: int) -> float:
        twice, whole = self.twice, self.whole[c]
        return sum([twice[s] * x * (whole[s] - x) for s, x in self.rows[t].items()])


def refine(g: Graph, part: list[int], objective: Objective, rng: random.Random, theta: float) -> list[int]:
    """Split each community into well-connected parts: from single vertices, merged only along gains."""
    sub, size = list(range(g.n)), [1] * g.n
    table = _EvenParts(g, part, objective) if _is_even(g) else _Parts(g, part, objective)
    outside = [sum(w for u, w in g.near[v] if part[u] == part[v]) for v in range(g.n)]

    def connected(t: int, c: int) -> bool:
        return outside[t] >= table.rest(t, c) - 1e-12

    order = list(range(g.n))
    rng.shuffle(order)
    for v in order:
        if size[sub[v]] != 1 or sub[v] != v or not connected(v, part[v]):
            continue
        links: dict[int, float] = {}
        for u, w in g.near[v]:
            if part[u] == part[v]:
                links[sub[u]] = links.get(sub[u], 0.0) + w
        links.pop(v, None)
        choices = [(t, w - table.null(v, t)) for t, w in links.items() if connected(t, part[v])]
        choices = [(t, x) for t, x in choices if x > 1e-12]
        if not choices:
            continue
        if theta > 0:
            scale = theta * max(1e-12, sum(abs(x) for _, x in choices) / len(choices))
            top = max(x for _, x in choices)
            t = rng.choices([t for t, _ in choices], [math.exp((x - top) / scale) for _, x in choices])[0]
        else:
            t = max(choices, key=lambda x: (x[1], -x[0]))[0]
        sub[v] = t
        size[t] += 1
        size[v] = 0
        outside[t] += outside[v] - 2 * links[t]
        table.add(t, v)
    return sub


def leiden(g: Graph, objective: Objective, max_passes: int = 2, with_refinement: bool = True, theta: float = 0.01, seed: int = 1, start: list[int] | None = None) -> list[int]:
    """Communities of the vertices; a pass moves, refines and aggregates down to the coarsest graph."""
    rng = random.Random(seed)
    labels = list(start) if start is not None else list(range(g.n))
    for _ in range(max_passes):
        before = list(labels)
        h, part, place = g, list(labels), list(range(g.n))
        while True:
            moves = local_move(h, part, objective, rng)
            parts = refine(h, part, objective, rng, theta) if with_refinement else part
            smaller, to = h.aggregate(parts)
            if smaller.n == h.n:
                labels = [part[place[v]] for v in range(g.n)]
                break
            above = [0] * smaller.n
            for v in range(h.n):
                above[to[v]] = part[v]
            place = [to[p] for p in place]
            h, part = smaller, above
            if not moves and smaller.n == len(set(part)):
                labels = [part[place[v]] for v in range(g.n)]
                break
        if labels == before:
            break
    return labels


def score(g: Graph, part: list[int], objective: Objective) -> float:
    inside = sum(w for v in range(g.n) for u, w in g.near[v] if part[u] == part[v]) / 2 + g.loops
    totals: dict[int, dict[int, list[float]]] = {}
    for v in range(g.n):
        _add(totals.setdefault(part[v], {}), g.k[v], 1)
    return inside - sum(objective.rate[s] * t[0] * t[1] for c in totals.values() for s, t in c.items())


def raise_surprise(n: int, a: np.ndarray, b: np.ndarray, w: np.ndarray, start: list[int], seed: int = 1) -> list[int]:
    """Labels after moves of vertices, then of whole communities, each the one that raises surprise most, until none does.

    Surprise is m D(x || y): x the share of weight inside communities, y the share of pairs inside.
    """
    m, pairs = float(w[a != b].sum()), n * (n - 1) / 2
    if not m or not pairs:
        return start
    rng = random.Random(seed)

    def worth(inside: float, within: float) -> float:
        x, y = min(1.0, inside / m), min(1.0, within / pairs)
        if x <= y:
            return -abs(x - y)  # fewer links than by chance are no surprise
        return x * math.log(x / y) + ((1 - x) * math.log((1 - x) / (1 - y)) if x < 1 else 0.0)

    labels, size, place = list(start), [1] * n, list(range(n))
    rows, cols, weights = a, b, w
    while True:
        g = Graph(len(size), rows, cols, weights, [{} for _ in size])
        members: dict[int, int] = {}
        for v, c in enumerate(labels):
            members[c] = members.get(c, 0) + size[v]
        inside = g.loops + sum(x for v in range(g.n) for u, x in g.near[v] if labels[u] == labels[v]) / 2
        within = sum(z * (z - 1) / 2 for z in members.values())
        now, moves, more = worth(inside, within), 0, True
        while more:
            more = False
            for v in rng.sample(range(g.n), g.n):
                links: dict[int, float] = {}
                for u, x in g.near[v]:
                    links[labels[u]] = links.get(labels[u], 0.0) + x
                own, z = labels[v], size[v]
                best = (now, own, inside, within)
                for c, x in links.items():
                    if c != own:
                        then = inside - links.get(own, 0.0) + x, within + z * (members[c] - members[own] + z)
                        if (value := worth(*then)) > best[0] + 1e-12:
                            best = (value, c, *then)
                if best[1] != own:
                    now, labels[v], inside, within = best
                    members[own] -= z
                    members[best[1]] += z
                    moves, more = moves + 1, True
        names: dict[int, int] = {}
        to = [names.setdefault(c, len(names)) for c in labels]
        place = [to[p] for p in place]
        if len(names) == g.n:
            return place
        merged = [0] * len(names)
        for v, t in enumerate(to):
            merged[t] += size[v]
        at = np.array(to)
        rows, cols, size, labels = at[rows], at[cols], merged, list(range(len(names)))


# Spectra.


def dense_operator(kind: str, a: np.ndarray, b: np.ndarray, w: np.ndarray, within: np.ndarray, slices: np.ndarray, p: dict) -> np.ndarray:
    """The matrix of an operator over vertices 0..n-1; within marks entries inside a slice."""
    n = len(slices)
    m = np.zeros((n, n))
    np.add.at(m, (a, b), w)
    d = m.sum(1)
    if kind == "deformed":
        return (p["r"] ** 2 - 1) * np.eye(n) - p["r"] * m + np.diag(d)
    if kind == "unnormalised":
        return np.diag(d) - m
    if kind in ("symmetric", "random_walk"):
        s = np.where(d > 0, 1 / np.sqrt(np.where(d > 0, d, 1)), 0)
        return np.diag((d > 0).astype(float)) - s[:, None] * m * s[None, :]
    if kind == "modularity":
        k = np.zeros(n)
        np.add.at(k, a[within], w[within])
        gamma, out = p.get("gamma", 1.0), m.copy()
        groups = slices if p.get("null", "slice") == "slice" else np.zeros(n, dtype=int)
        k = k if p.get("null", "slice") == "slice" else d
        for s in np.unique(groups):
            i = np.flatnonzero(groups == s)
            if k[i].sum() > 0:
                out[np.ix_(i, i)] -= gamma * np.outer(k[i], k[i]) / k[i].sum()
        return out
    if kind == "nonbacktracking":
        s, t = np.zeros((n, n)), np.zeros((n, n))
        np.add.at(s, (a[within], b[within]), 1.0)
        np.add.at(t, (a[~within], b[~within]), 1.0)
        ds, dt, e, z = np.diag(s.sum(1)), np.diag(t.sum(1)), np.eye(n), np.zeros((n, n))
        lam, eta = p["lam"], p["eta"]
        # Unknowns (gs, hs, gt, ht) as in operators.nonbacktracking.
        return np.block([[lam * s, -lam * e, lam * s, z], [lam * (ds - e), z, lam * ds, z], [eta * t, z, eta * t, -eta * e], [eta * dt, z, eta * (dt - e), z]])
    raise ValueError(kind)


def eigenpairs(kind: str, matrix: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All real pairs, most informative end first: smallest for Laplacians, largest for the others."""
    if kind == "nonbacktracking":
        values, vectors = np.linalg.eig(matrix)
        order = np.argsort(-values.real, kind="stable")
        n = matrix.shape[0] // 4
        keep, cols, vals = set(), [], []
        for i in order:
            if np.abs(values[i].imag) > 1e-9:
                key = (round(values[i].real, 9), round(abs(values[i].imag), 9))
                part = vectors[:, i].real if key not in keep else vectors[:, i].imag
                keep.add(key)
            else:
                part = vectors[:, i].real
            cols.append(part[:n] + part[2 * n : 3 * n])
            vals.append(values[i].real)
        return np.array(vals), np.stack(cols, 1)
    values, vectors = np.linalg.eigh(matrix)
    return (values, vectors) if kind != "modularity" else (values[::-1], vectors[:, ::-1])


def centre_slices(x: np.ndarray, slices: np.ndarray, weight: np.ndarray | None = None) -> np.ndarray:
    """Take the span of slice indicators (times weight) out of the columns."""
    weight = np.ones(len(x)) if weight is None else weight
    out = x.copy()
    for s in np.unique(slices):
        i = slices == s
        q = weight[i] / max(1e-300, np.linalg.norm(weight[i]))
        out[i] -= np.outer(q, q @ out[i])
    return out


def deflate(matrix: np.ndarray, slices: np.ndarray, weight: np.ndarray | None, shift: float) -> np.ndarray:
    """The operator on what is left after time modes; these get the value shift."""
    p = centre_slices(np.eye(len(matrix)), slices, weight)
    out = p @ matrix @ p.T + shift * (np.eye(len(matrix)) - p)
    return (out + out.T) / 2


def kmeans(x: np.ndarray, k: int, seed: int = 1, restarts: int = 8, rounds: int = 100) -> np.ndarray:
    """Lloyd's rounds from k-means++ starts; the labels of the cheapest restart."""
    rng, best, labels = np.random.default_rng(seed), math.inf, np.zeros(len(x), dtype=int)
    for _ in range(restarts):
        centres = x[[rng.integers(len(x))]]
        while len(centres) < min(k, len(x)):
            d = ((x[:, None] - centres[None]) ** 2).sum(2).min(1)
            centres = np.vstack([centres, x[rng.choice(len(x), p=d / d.sum()) if d.sum() > 0 else rng.integers(len(x))]])
        for _ in range(rounds):
            d = ((x[:, None] - centres[None]) ** 2).sum(2)
            own = d.argmin(1)
            moved = np.array([x[own == c].mean(0) if (own == c).any() else centres[c] for c in range(len(centres))])
            if np.allclose(moved, centres):
                break
            centres = moved
        if (cost := d.min(1).sum()) < best - 1e-12:
            best, labels = cost, own
    return labels


def lanczos(matvec, n: int, k: int, which: str = "SA", steps: int | None = None, seed: int = 1) -> tuple[np.ndarray, np.ndarray]:
    """k pairs of a symmetric operator at one end, with full re-orthogonalisation."""
    steps = min(n, steps or max(4 * k + 20, 60))
    rng = np.random.default_rng(seed)
    q = np.zeros((n, steps))
    alpha, beta = np.zeros(steps), np.zeros(steps)
    v = rng.standard_normal(n)
    q[:, 0] = v / np.linalg.norm(v)
    for j in range(steps):
        w = matvec(q[:, j])
        alpha[j] = q[:, j] @ w
        w -= q[:, : j + 1] @ (q[:, : j + 1].T @ w)
        w -= q[:, : j + 1] @ (q[:, : j + 1].T @ w)
        beta[j] = np.linalg.norm(w)
        if j + 1 == steps or beta[j] < 1e-12:
            steps = j + 1
            break
        q[:, j + 1] = w / beta[j]
    t = np.diag(alpha[:steps]) + np.diag(beta[: steps - 1], 1) + np.diag(beta[: steps - 1], -1)
    values, vectors = np.linalg.eigh(t)
    order = np.arange(steps) if which == "SA" else np.arange(steps)[::-1]
    return values[order[:k]], q[:, :steps] @ vectors[:, order[:k]]
