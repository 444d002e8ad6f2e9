"""Eigenpairs of distributed operators: the driver holds only small projected matrices."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .operators.base import LinearOperator, columns_of, random_block
from .session import cut


def gram(x: DataFrame, y: DataFrame | None = None) -> np.ndarray:
    """X'X, or X'Y of two frames with the same rows, in one aggregation."""
    cs = columns_of(x)
    if y is None:
        row = x.agg(*(F.sum(F.col(p) * F.col(q)) for i, p in enumerate(cs) for q in cs[i:])).first()
        out = np.zeros((len(cs), len(cs)))
        out[np.triu_indices(len(cs))] = [v or 0.0 for v in row]
        return out + np.triu(out, 1).T
    ds = columns_of(y)
    both = x.join(y.withColumnsRenamed({c: f"y{c}" for c in ds}), "sid")
    row = both.agg(*(F.sum(F.col(p) * F.col(f"y{q}")) for p in cs for q in ds)).first()
    return np.array([v or 0.0 for v in row]).reshape(len(cs), len(ds))


def rotate(x: DataFrame, t: np.ndarray) -> DataFrame:
    """X T; the coefficients travel as literals."""
    cs = columns_of(x)
    mix = lambda j: sum((F.col(c) * F.lit(float(t[i, j])) for i, c in enumerate(cs)), F.lit(0.0))
    return x.select("sid", *(mix(j).alias(f"c{j}") for j in range(t.shape[1])))


def combine(x: DataFrame, a: float, y: DataFrame, b: float) -> DataFrame:
    cs = columns_of(x)
    return x.join(y.withColumnsRenamed({c: f"y{c}" for c in cs}), "sid").select("sid", *((F.lit(a) * F.col(c) + F.lit(b) * F.col(f"y{c}")).alias(c) for c in cs))


def orthonormal(x: DataFrame) -> DataFrame:
    """Columns made orthonormal through the eigenvectors of X'X; dependent ones are left out."""
    values, vectors = np.linalg.eigh(gram(x))
    keep = values > values.max(initial=0.0) * 1e-12
    return rotate(x, vectors[:, keep] / np.sqrt(values[keep]))


def centred(x: DataFrame, nodes: DataFrame, weight: Column | None = None) -> DataFrame:
    """Take the slice indicators (times weight) out of every column; nodes has sid and slice."""
    cs = columns_of(x)
    w = F.lit(1.0) if weight is None else weight
    here = x.join(nodes.select("sid", "slice", w.alias("w")), "sid")
    means = here.groupBy("slice").agg(F.sum(F.col("w") * F.col("w")).alias("ww"), *(F.sum(F.col("w") * F.col(c)).alias(f"t{c}") for c in cs))
    part = lambda c: F.coalesce(F.try_divide(F.col("w") * F.col(f"t{c}"), F.col("ww")), F.lit(0.0))
    return here.join(F.broadcast(means), "slice").select("sid", *((F.col(c) - part(c)).alias(c) for c in cs))


def block_eigs(op: LinearOperator, k: int, which: str = "SA", degree: int = 6, tol: float = 1e-4, most: int = 12, seed: int = 1, project: Callable[[DataFrame], DataFrame] | None = None) -> tuple[np.ndarray, DataFrame, np.ndarray]:
    """k extreme pairs of a symmetric operator by Chebyshev-filtered subspace iteration.

    Returns values, vectors (sid, c0 ...) and residual norms.  An iteration costs degree products and
    two trips to the driver with b x b numbers, b = k + 3.
    """
    low, high = op.bounds()
    x = random_block(op.nodes, k + 3, seed)
    x = cut(orthonormal(project(x) if project else x), "block")
    values = residuals = np.zeros(0)
    for _ in range(most):
        y = cut(op.apply(x), "block")
        y = cut(project(y), "block") if project else y
        t = gram(x, y)
        vals, vecs = np.linalg.eigh((t + t.T) / 2)
        vecs, vals = (vecs, vals) if which == "SA" else (vecs[:, ::-1], vals[::-1])
        x, y = rotate(x, vecs), rotate(y, vecs)
        gap = combine(y, 1.0, _scaled(x, vals), -1.0)
        residuals = np.sqrt(np.maximum(np.diag(gram(gap)), 0))[:k]
        values = vals[:k]
        scale = max(1.0, abs(low), abs(high))
        if (residuals <= tol * scale).all():
            break
        edge = float(vals[-1])
        a, b = (edge, high) if which == "SA" else (low, edge)
        centre, half = (a + b) / 2, max((b - a) / 2, 1e-9)
        before, now = x, cut(combine(y, 1 / half, x, -centre / half), "block")
        for _ in range(degree - 1):
            z = op.apply(now)
            z = project(z) if project else z
            step = combine(z, 2 / half, now, -2 * centre / half)
            before, now = now, cut(combine(step, 1.0, before, -1.0), "block")
        x = cut(orthonormal(now), "block")
    return values, rotate(x, np.eye(len(columns_of(x)))[:, :k]), residuals


def _scaled(x: DataFrame, values: np.ndarray) -> DataFrame:
    return x.select("sid", *((F.col(c) * F.lit(float(v))).alias(c) for c, v in zip(columns_of(x), values, strict=True)))


def power_iteration(op: LinearOperator, steps: int = 30, shift: float = 0.0, seed: int = 1, project: Callable[[DataFrame], DataFrame] | None = None) -> tuple[float, DataFrame]:
    """The dominant pair of (operator - shift); project takes known directions out (deflation)."""
    x = orthonormal(random_block(op.nodes, 1, seed))
    value = 0.0
    for _ in range(steps):
        x = project(x) if project else x
        y = cut(combine(op.apply(x), 1.0, x, -shift), "vector")
        value = float(gram(x, y)[0, 0])
        x = cut(orthonormal(y), "vector")
    return value + shift, x


def lanczos(op: LinearOperator, k: int, which: str = "SA", steps: int = 20, seed: int = 1) -> tuple[np.ndarray, DataFrame]:
    """k pairs with full re-orthogonalisation; the basis is one wide frame, the driver has the tridiagonal."""
    q = cut(orthonormal(random_block(op.nodes, 1, seed)), "basis")
    alpha, beta = [], []
    for j in range(steps):
        last = q.select("sid", F.col(f"c{j}").alias("c0"))
        w = cut(op.apply(last), "vector")
        alpha.append(float(gram(last, w)[0, 0]))
        for _ in range(2):
            w = cut(combine(w, 1.0, rotate(q, gram(q, w)), -1.0), "vector")
        norm = float(np.sqrt(max(gram(w)[0, 0], 0.0)))
        if norm < 1e-10 or j + 1 == steps:
            break
        beta.append(norm)
        q = cut(q.join(w.select("sid", (F.col("c0") / norm).alias(f"c{j + 1}")), "sid"), "basis")
    n = len(alpha)
    t = np.diag(alpha) + np.diag(beta[: n - 1], 1) + np.diag(beta[: n - 1], -1)
    values, vectors = np.linalg.eigh(t)
    order = np.arange(n) if which == "SA" else np.arange(n)[::-1]
    return values[order[:k]], rotate(q.select("sid", *(f"c{i}" for i in range(n))), vectors[:, order[:k]])


def nonsymmetric_eigs(op, k: int, most: int = 25, seed: int = 1) -> tuple[np.ndarray, DataFrame]:
    """Leading pairs of the non-backtracking operator by subspace iteration: values, and (sid, c0 ...) of gs + gt.

    States (sid, gs, hs, gt, ht) are stacked as one frame per block column, so a step is one
    product for each; a complex pair gives its real and imaginary part as two columns.
    """
    width = k + 2
    parts = list(op.PARTS)
    frames = [op.nodes.select("sid", *((F.rand(seed + 10 * i + j) - 0.5).alias(p) for j, p in enumerate(parts))) for i in range(width)]
    frames = [cut(f, "state") for f in frames]
    values, weights = np.zeros(0), np.eye(width)
    for step in range(most):
        x = _stack(frames, parts)
        basis = orthonormal(x)
        basis = cut(basis, "state")
        frames = _unstack(basis, parts)
        applied = [cut(op.apply(f), "state") for f in frames]
        y = _stack(applied, parts)
        small = gram(basis, y)
        frames = applied
        if step == most - 1:
            vals, vecs = np.linalg.eig(small)
            order = np.argsort(-vals.real, kind="stable")[:k]
            cols, seen = [], set()
            for i in order:
                key = (round(vals[i].real, 6), round(abs(vals[i].imag), 6))
                cols.append(vecs[:, i].imag if abs(vals[i].imag) > 1e-9 and key in seen else vecs[:, i].real)
                seen.add(key)
            values, weights = vals[order], np.stack(cols, 1)
            whole = rotate(basis, weights)
            back = whole.withColumn("part", F.pmod("sid", F.lit(4))).withColumn("sid", F.floor(F.col("sid") / 4)).filter("part in (0, 2)")
            return values, back.groupBy("sid").agg(*(F.sum(c).alias(c) for c in columns_of(whole)))
    raise RuntimeError("no step was taken")


def _stack(frames: list[DataFrame], parts: list[str]) -> DataFrame:
    out = None
    for i, f in enumerate(frames):
        long = f.select("sid", F.posexplode(F.array(*parts)).alias("part", f"c{i}")).select((F.col("sid") * 4 + F.col("part")).alias("sid"), f"c{i}")
        out = long if out is None else out.join(long, "sid")
    return out


def _unstack(block: DataFrame, parts: list[str]) -> list[DataFrame]:
    cs = columns_of(block)
    wide = block.withColumn("part", F.pmod("sid", F.lit(4))).withColumn("sid", F.floor(F.col("sid") / 4)).groupBy("sid")
    every = cut(wide.agg(*(F.sum(F.when(F.col("part") == j, F.col(c)).otherwise(0.0)).alias(f"{c}_{p}") for c in cs for j, p in enumerate(parts))), "state")
    return [every.select("sid", *(F.col(f"{c}_{p}").alias(p) for p in parts)) for c in cs]
