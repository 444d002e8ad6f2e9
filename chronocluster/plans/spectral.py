"""Spectral clustering of temporal graphs, on distributed operators or in one task."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.ml.clustering import BisectingKMeans, GaussianMixture, KMeans
from pyspark.ml.feature import VectorAssembler
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .. import kernels
from ..linalg import block_eigs, centred, nonsymmetric_eigs
from ..operators import DeformedLaplacian, Laplacian, ModularityOp, MultisliceModularityOp, NonBacktracking, choose_r
from ..operators.base import columns_of
from ..session import cut, ship
from ..supra import auto_omega, supra_graph
from ..temporal import TemporalGraph

#: Temporal nodes up to which one task may hold the matrix.
DENSE_NODES = 4000
NAMES = {"laplacian": "symmetric", "deformed": "deformed", "modularity": "modularity", "nonbacktracking": "nonbacktracking"}


def normalise_rows(block: DataFrame) -> DataFrame:
    """Rows scaled to length 1; a zero row stays."""
    cs = columns_of(block)
    length = F.sqrt(sum((F.col(c) * F.col(c) for c in cs), F.lit(0.0)))
    return block.select("sid", *((F.when(length > 0, F.col(c) / length).otherwise(0.0)).alias(c) for c in cs))


def cluster_rows(block: DataFrame, k: int, method: str = "kmeans", seed: int = 1, restarts: int = 3) -> DataFrame:
    """sid, community by k-means (the cheapest of several starts), bisecting k-means or a Gaussian mixture."""
    rows = VectorAssembler(inputCols=columns_of(block), outputCol="x").transform(block).select("sid", "x")
    if method == "bisecting":
        fitted = BisectingKMeans(k=k, seed=seed, featuresCol="x").fit(rows)
    elif method == "mixture":
        fitted = GaussianMixture(k=k, seed=seed, featuresCol="x").fit(rows)
    else:
        fitted = min((KMeans(k=k, seed=seed + i, featuresCol="x", initMode="k-means||").fit(rows) for i in range(restarts)), key=lambda m: m.summary.trainingCost)
    return fitted.transform(rows).select("sid", F.col("prediction").cast("bigint").alias("community"))


def lloyd_step(points: DataFrame, centres: DataFrame, dims: list[str]) -> DataFrame:
    """One round of Lloyd: centre, n and the means of the points nearest to it; ties go to the smaller centre."""
    far = sum(((F.col(d) - F.col(f"m_{d}")) * (F.col(d) - F.col(f"m_{d}")) for d in dims), F.lit(0.0))
    both = points.crossJoin(F.broadcast(centres.select("centre", *(F.col(d).alias(f"m_{d}") for d in dims))))
    nearest = both.groupBy("id", *dims).agg(F.min(F.struct(far.alias("far"), "centre")).alias("best"))
    return nearest.groupBy(F.col("best.centre").alias("centre")).agg(F.count("*").alias("n"), *(F.avg(d).alias(d) for d in dims))


def spectral_clustering(
    tg: TemporalGraph,
    k: int | None = None,
    operator: str = "deformed",
    normalisation: str = "symmetric",
    objective: str | None = None,
    omega: float | str = "auto",
    gamma: float = 1.0,
    r: str | float = "degree_ratio",
    degree: str = "supra",
    lam: float = 0.5,
    eta: float = 0.9,
    null: str = "slice",
    time_modes: str | None = None,
    row_normalise: str | bool = "auto",
    order: str | None = None,
    time: str = "both",
    topology: str = "adjacent",
    clustering: str = "kmeans",
    solver: str = "auto",
    per_slice: bool = False,
    seed: int = 1,
    presence: str = "active",
    assortative: bool = True,
) -> DataFrame:
    """slice, node, community.

    presence: which copies a node has (active, span or all); assortative=False takes -r in the deformed
    Laplacian.  clustering: kmeans, bisecting or mixture; all but kmeans run on the cluster's rows.

    operator: deformed, laplacian (normalisation: symmetric, random_walk or unnormalised; objective
    ncut or rcut chooses between them), modularity or nonbacktracking.  time_modes='deflate' (default
    for several slices) takes the slice indicators out, which else lead the spectrum; 'keep' is the
    literal method.  order='centred' picks vectors of B by the energy left after slice means are gone.
    """
    tg = tg.stored()
    if objective:
        normalisation = {"ncut": "symmetric", "rcut": "unnormalised"}[objective]
    supra = supra_graph(tg, 0.0 if per_slice else auto_omega(tg.edges) if omega == "auto" else omega, topology, presence)
    if per_slice:
        supra = type(supra)(supra.nodes, supra.edges.filter("kind = 's'"), supra.directed)
    n = supra.nodes.count()
    slices = tg.edges.select("slice").distinct().count()
    if k is None:
        if slices > 1 and not per_slice:
            raise ValueError("for several slices k must be given: time modes and communities mix in the count")
    kind = {"deformed": "deformed", "modularity": "modularity", "nonbacktracking": "nonbacktracking", "laplacian": normalisation}[operator]
    params = {"r": choose_r(supra, r, degree) if kind == "deformed" and not per_slice else r, "sign": 1 if assortative else -1, "gamma": gamma, "null": null, "lam": lam, "eta": eta}
    modes = time_modes or ("deflate" if slices > 1 and not per_slice and kind != "nonbacktracking" else "keep")
    order = order or ("centred" if kind == "nonbacktracking" and slices > 1 and not per_slice else "largest")
    if per_slice and solver != "kernel":
        return _per_slice(tg, supra, k, kind, params, row_normalise, time, clustering, seed, solver)
    if solver == "kernel" or solver == "auto" and n <= DENSE_NODES:
        return _kernel(supra, k, kind, params, modes, row_normalise, order, time, seed, per_slice, clustering)
    return _distributed(tg, supra, k, kind, params, modes, row_normalise, order, time, clustering, seed)


def vectors_wanted(kind: str, k: int, modes: str) -> int:
    """Leading vectors: k of a Laplacian, k - 1 where the constant or the time modes are out, or of B and M."""
    return max(1, k - 1) if kind in ("modularity", "nonbacktracking") or modes == "deflate" else k


def _scale_rows(kind: str, row_normalise: str | bool, width: int) -> bool:
    return kind in ("symmetric", "deformed", "modularity", "unnormalised") and width >= 2 if row_normalise == "auto" else bool(row_normalise)


def embed(kind: str, m: np.ndarray, d: np.ndarray, slices: np.ndarray, k: int | None, modes: str, order: str) -> tuple[np.ndarray, np.ndarray]:
    """Eigenvalues and the columns that are clustered."""
    own = kind if kind != "random_walk" else "symmetric"
    if modes == "deflate" and own != "nonbacktracking":
        weight = np.sqrt(d) if own == "symmetric" else None
        far = np.abs(m).sum(1).max() + 1.0
        m = kernels.deflate(m, slices, weight, far if own != "modularity" else -far)
    values, vectors = kernels.eigenpairs(own, m)
    if k is None:
        k = max(1, int((values < -1e-9).sum())) if own == "deformed" else max(1, int((values > 1e-9).sum())) if own == "modularity" else 2
    width = vectors_wanted(kind, k, modes)
    if order == "centred":
        some = np.arange(min(len(values), 20 + 4 * width))
        x = vectors[:, some] / np.maximum(np.linalg.norm(vectors[:, some], axis=0), 1e-300)
        left = (kernels.centre_slices(x, slices) ** 2).sum(0)
        chosen = [i for i in some if left[i] >= 0.9][:width] or list(some[:width])
        vectors, values = vectors[:, chosen], values[chosen]
    else:
        vectors, values = vectors[:, :width], values[:width]
    if kind == "random_walk":
        vectors = vectors * np.where(d > 0, 1 / np.sqrt(np.where(d > 0, d, 1)), 0)[:, None]
    return values, vectors


def _per_slice(tg, supra, k, kind, params, row_normalise, time, clustering, seed, solver) -> DataFrame:
    """Small slices in one task each, by dense matrices; larger ones one after the other by the distributed operators."""
    sizes = supra.nodes.groupBy("slice").agg(F.count("*").alias("n")).filter(F.col("n") > (0 if solver == "distributed" else DENSE_NODES)).select("slice")
    large = [r.slice for r in sizes.collect()]
    at = F.floor(F.col("a") / F.lit(1 << 40)).cast("int")
    small = type(supra)(supra.nodes.filter(~F.col("slice").isin(large)), supra.edges.filter(~at.isin(large)), supra.directed) if large else supra
    out = _kernel(small, k, kind, params, "keep", row_normalise, "largest", time, seed, True, clustering)
    for s in large:
        one = type(supra)(cut(supra.nodes.filter(F.col("slice") == s), "nodes"), cut(supra.edges.filter(at == s), "edges"), supra.directed)
        part = tg.with_edges(tg.edges.filter(F.col("slice") == s))
        own = {**params, "r": choose_r(one, params["r"]) if kind == "deformed" else params["r"]}
        labels = _distributed(part, one, k, kind, own, "keep", row_normalise, "largest", time, clustering, seed)
        least = labels.groupBy("community").agg(F.min(F.col("slice").cast("bigint") * F.lit(1 << 40) + F.col("node")).alias("name"))
        out = out.unionByName(labels.join(F.broadcast(least), "community").select("slice", "node", F.col("name").alias("community")))
    return out


def _kernel(supra, k, kind, params, modes, row_normalise, order, time, seed, per_slice, clustering="kmeans") -> DataFrame:
    ship(supra.edges.sparkSession)
    if clustering != "kmeans" and (per_slice or k is None):
        raise ValueError("per slice, or without k, clustering is kmeans")
    key = (F.col("slice") if per_slice else F.lit(0)).alias("task")
    edges = supra.edges.withColumn("slice", F.floor(F.col("a") / F.lit(1 << 40)).cast("int")).select(key, "a", "b", "weight", (F.col("kind") == "s").alias("within"))
    nodes = supra.nodes.select(key, "sid", "slice", "node")

    def run(_: tuple, e: pa.Table, v: pa.Table) -> pa.Table:
        at = np.argsort(np.array(v.column("sid")))
        v = v.take(pa.array(at))
        ids, slices = np.array(v.column("sid")), np.array(v.column("slice"))
        n = len(ids)
        if n > DENSE_NODES:
            raise ValueError(f"{n} nodes in one task; the limit is {DENSE_NODES}")
        a, b = np.searchsorted(ids, np.array(e.column("a"), dtype=np.int64)), np.searchsorted(ids, np.array(e.column("b"), dtype=np.int64))
        w, within = np.array(e.column("weight"), dtype=float), np.array(e.column("within"), dtype=bool)
        if kind == "nonbacktracking" and time == "forward":
            keep = within | (slices[b] < slices[a])
            a, b, w, within = a[keep], b[keep], w[keep], within[keep]
        d = np.bincount(a, w, minlength=n)
        p = dict(params)
        if kind == "deformed" and isinstance(p["r"], str):
            p["r"] = np.sqrt(d.mean()) if p["r"] == "sqrt_mean_degree" else np.sqrt(max(0.0, (d**2).mean() / d.mean() - 1)) if d.any() else 0.0
        p["r"] = p["r"] * p.get("sign", 1) if kind == "deformed" else p["r"]
        matrix = kernels.dense_operator(kind, a, b, w, within, slices, p)
        _, x = embed(kind, matrix, d, slices, min(k, n) if k else None, modes, order)
        if _scale_rows(kind, row_normalise, x.shape[1]):
            x = x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-300)
        if clustering != "kmeans":
            return pa.table({"slice": v.column("slice"), "node": v.column("node"), "x": pa.array(x.tolist(), pa.list_(pa.float64()))})
        parts = k if k else x.shape[1] + (kind == "modularity")
        labels = kernels.kmeans(x, min(parts, n), seed)
        least: dict[int, int] = {}
        for i, c in zip(ids.tolist(), labels.tolist(), strict=True):
            least[c] = min(least.get(c, i), i)
        return pa.table({"slice": v.column("slice"), "node": v.column("node"), "community": pa.array([least[c] for c in labels.tolist()], pa.int64())})

    grouped = edges.groupBy("task").cogroup(nodes.groupBy("task"))
    if clustering == "kmeans":
        return grouped.applyInArrow(run, "slice int, node bigint, community bigint")
    rows = cut(grouped.applyInArrow(run, "slice int, node bigint, x array<double>"), "embedding")
    width = len((rows.first() or {"x": []})["x"])
    block = rows.join(supra.nodes, ["slice", "node"]).select("sid", *(F.col("x")[i].alias(f"c{i}") for i in range(width)))
    return supra.nodes.join(cut(cluster_rows(block, k, clustering, seed), "labels"), "sid").select("slice", "node", "community")


def operator_of(tg: TemporalGraph, supra, kind: str, params: dict, time: str = "both"):
    if kind == "deformed":
        return DeformedLaplacian(supra, params["r"], assortative=params.get("sign", 1) > 0)
    if kind == "modularity":
        return MultisliceModularityOp(tg, supra, params["gamma"]) if params["null"] == "slice" else ModularityOp(supra.edges, supra.nodes, params["gamma"])
    if kind == "nonbacktracking":
        return NonBacktracking(supra, params["lam"], params["eta"], time)
    return Laplacian(supra, "symmetric" if kind == "random_walk" else kind)


def _distributed(tg, supra, k, kind, params, modes, row_normalise, order, time, clustering, seed) -> DataFrame:
    if k is None:
        raise ValueError("the distributed solver needs k")
    op = operator_of(tg, supra, kind, params, time)
    width = vectors_wanted(kind, k, modes)
    if kind == "nonbacktracking":
        slices = supra.nodes.select("slice").distinct().count()
        for candidates in ((width + 4, width + 4 + slices, 20 + 4 * width + slices) if order == "centred" else (width,)):
            some = nonsymmetric_eigs(op, candidates, seed=seed)[1]
            x = _by_centred_energy(some, supra.nodes, width) if order == "centred" else some
            if x is not None:
                break
        else:
            raise RuntimeError(f"of {candidates} leading vectors fewer than {width} are more than slice means")
    else:
        weight = None
        nodes = supra.nodes
        if modes == "deflate" and kind in ("symmetric", "random_walk"):
            nodes = supra.nodes.join(op.nodes.select("sid", "d"), "sid")
            weight = F.sqrt("d")
        project = (lambda b: centred(b, nodes, weight)) if modes == "deflate" else None
        _, x, gaps = block_eigs(op, width, "LA" if kind == "modularity" else "SA", seed=seed, project=project, most=40)
        low, high = op.bounds()
        if (gaps > 1e-2 * max(1.0, abs(low), abs(high))).any():
            raise RuntimeError(f"eigenvectors did not converge: residuals {np.round(gaps, 4).tolist()}")
    if kind == "random_walk":
        d = F.when(F.col("d") > 0, 1 / F.sqrt("d")).otherwise(0.0)
        x = x.join(op.nodes.select("sid", "d"), "sid").select("sid", *((F.col(c) * d).alias(c) for c in columns_of(x)))
    if _scale_rows(kind, row_normalise, width):
        x = normalise_rows(x)
    labels = cut(cluster_rows(cut(x, "embedding"), k, clustering, seed), "labels")
    return supra.nodes.join(labels, "sid").select("slice", "node", "community")


def _by_centred_energy(x: DataFrame, nodes: DataFrame, width: int, least: float = 0.9) -> DataFrame | None:
    """The first width columns of which most is left when slice means are taken out; None if there are fewer."""
    cs = columns_of(x)
    left = centred(x, nodes)
    a = x.agg(*(F.sum(F.col(c) * F.col(c)) for c in cs)).first()
    b = left.agg(*(F.sum(F.col(c) * F.col(c)) for c in cs)).first()
    chosen = [c for c, p, q in zip(cs, a, b, strict=True) if p and q / p >= least][:width]
    if len(chosen) < width:
        return None
    return x.select("sid", *(F.col(c).alias(f"c{i}") for i, c in enumerate(chosen)))


def estimate_k(tg: TemporalGraph, seed: int = 1) -> DataFrame:
    """slice, k: how many eigenvalues of each snapshot's deformed Laplacian (r from its degrees) are negative.

    Slices up to DENSE_NODES nodes are a task each; for a larger one the smallest pairs are found by the
    distributed solver, ever more until one is not negative.
    """
    ship(tg.edges.sparkSession)
    edges = tg.edges.select("slice", "src", "dst", "weight")
    sizes = edges.select("slice", F.explode(F.array("src", "dst")).alias("node")).groupBy("slice").agg(F.count_distinct("node").alias("n"))
    large = [r.slice for r in sizes.filter(F.col("n") > DENSE_NODES).select("slice").collect()]

    def run(key: tuple, e: pa.Table) -> pa.Table:
        ids, inverse = np.unique(np.concatenate([np.array(e.column("src")), np.array(e.column("dst"))]), return_inverse=True)
        m = len(e)
        a, w = np.zeros((len(ids), len(ids))), np.array(e.column("weight"), dtype=float)
        np.add.at(a, (inverse[:m], inverse[m:]), w)
        a += a.T
        d = a.sum(1)
        r = np.sqrt(max(0.0, (d**2).mean() / d.mean() - 1))
        values = np.linalg.eigvalsh((r**2 - 1) * np.eye(len(ids)) - r * a + np.diag(d))
        return pa.table({"slice": pa.array([key[0].as_py()], pa.int32()), "k": pa.array([int((values < -1e-9).sum())], pa.int64())})

    out = edges.filter(~F.col("slice").isin(large)).groupBy("slice").applyInArrow(run, "slice int, k bigint")
    for s in large:
        supra = supra_graph(tg.with_edges(cut(tg.edges.filter(F.col("slice") == s), "edges")), 0.0)
        op, width, negative = DeformedLaplacian(supra), 8, 8
        while negative == width:  # all of them are negative: look for more
            width *= 2
            negative = int((block_eigs(op, width, seed=seed, most=40)[0] < -1e-9).sum())
        out = out.union(tg.edges.sparkSession.createDataFrame([(s, negative)], "slice int, k bigint"))
    return out


def fiedler_split(tg: TemporalGraph, omega: float = 1.0, threshold: str = "zero", form: str = "symmetric", solver: str = "auto") -> DataFrame:
    """slice, node, value, community 0 or 1 by the second eigenvector of the supra-Laplacian.

    threshold: zero, median, or sweep (the cut with the least conductance along the order of values).
    Above DENSE_NODES temporal nodes, or with solver='distributed', nothing dense is made.
    """
    supra = supra_graph(tg, omega)
    if solver == "distributed" or solver == "auto" and supra.nodes.count() > DENSE_NODES:
        return _fiedler_distributed(supra, threshold, form)
    ship(supra.edges.sparkSession)
    edges = supra.edges.withColumn("task", F.lit(0))

    def run(_: tuple, e: pa.Table, v: pa.Table) -> pa.Table:
        v = v.sort_by("sid")
        ids, n = np.array(v.column("sid")), len(v)
        a, b = np.searchsorted(ids, np.array(e.column("a"))), np.searchsorted(ids, np.array(e.column("b")))
        w = np.array(e.column("weight"), dtype=float)
        d = np.bincount(a, w, minlength=n)
        x = np.linalg.eigh(kernels.dense_operator(form, a, b, w, np.ones(len(a), bool), np.zeros(n, int), {}))[1][:, 1]
        x = x * np.sign(x[np.argmax(np.abs(x))])
        if form == "symmetric":
            x = x / np.sqrt(np.where(d > 0, d, 1))
        if threshold == "sweep":
            order = np.argsort(x, kind="stable")
            place = np.empty(n, int)
            place[order] = np.arange(n)
            lo, hi = np.minimum(place[a], place[b]), np.maximum(place[a], place[b])
            cross = np.cumsum(np.bincount(lo, w / 2, minlength=n) - np.bincount(hi, w / 2, minlength=n))[:-1]
            vol = np.cumsum(d[order])[:-1]
            best = int(np.argmin(cross / np.maximum(np.minimum(vol, d.sum() - vol), 1e-300)))
            side = (place > best).astype(np.int64)
        else:
            side = (x > (np.median(x) if threshold == "median" else 0.0)).astype(np.int64)
        return pa.table({"slice": v.column("slice"), "node": v.column("node"), "value": pa.array(x), "community": pa.array(side)})

    nodes = supra.nodes.withColumn("task", F.lit(0))
    return edges.select("task", "a", "b", "weight").groupBy("task").cogroup(nodes.select("task", "sid", "slice", "node").groupBy("task")).applyInArrow(run, "slice int, node bigint, value double, community bigint")


def running_sums(rows: DataFrame, by: str, *columns: str) -> DataFrame:
    """rows with sum_<column> of all rows up to each one in the order of by and sid: ranges are summed apart and then shifted."""
    parts = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranged = cut(rows.repartitionByRange(parts, by, "sid").withColumn("range", F.spark_partition_id()), "ranges")
    totals = ranged.groupBy("range").agg(*(F.sum(c).alias(f"t_{c}") for c in columns))
    ahead = Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)  # as many rows as ranges
    shifts = totals.select("range", *(F.coalesce(F.sum(f"t_{c}").over(ahead), F.lit(0.0)).alias(f"t_{c}") for c in columns))
    inside = Window.partitionBy("range").orderBy(by, "sid").rowsBetween(Window.unboundedPreceding, 0)
    return ranged.join(F.broadcast(shifts), "range").select(*rows.columns, *((F.sum(c).over(inside) + F.col(f"t_{c}")).alias(f"sum_{c}") for c in columns))


def _fiedler_distributed(supra, threshold: str, form: str) -> DataFrame:
    """The second vector by filtered iteration with the first, which is known, taken out; the sweep by running sums of cut and volume."""
    op = Laplacian(supra, form)
    d = op.nodes.select("sid", "d")
    one = supra.nodes.select("sid", F.lit(0).alias("slice")).join(d, "sid")  # one class: its weighted constant goes
    _, block, gaps = block_eigs(op, 1, project=lambda b: centred(b, one, F.sqrt("d") if form == "symmetric" else None), most=40)
    if (gaps > 1e-2 * max(1.0, *map(abs, op.bounds()))).any():
        raise RuntimeError(f"the eigenvector did not converge: residual {float(gaps[0]):.4f}")
    scale = F.when(F.col("d") > 0, 1 / F.sqrt("d")).otherwise(1.0) if form == "symmetric" else F.lit(1.0)
    x = cut(block.join(d, "sid").select("sid", "d", (F.col("c0") * scale).alias("value")), "values")
    if threshold == "sweep":
        far, near = x.select(F.col("sid").alias("b"), F.col("value").alias("vb")), x.select(F.col("sid").alias("a"), F.col("value").alias("va"))
        before = (F.col("vb") < F.col("va")) | (F.col("vb") == F.col("va")) & (F.col("b") < F.col("a"))
        # A node that joins the lower side cuts its edges to the rest and heals those to the side.
        step = supra.edges.join(far, "b").join(near, "a").groupBy(F.col("a").alias("sid")).agg(F.sum(F.when(before, -F.col("weight")).otherwise(F.col("weight"))).alias("step"))
        run = running_sums(x.join(step, "sid", "left").select("sid", "d", "value", F.coalesce("step", F.lit(0.0)).alias("step")), "value", "step", "d")
        volume = x.agg(F.sum("d")).first()[0]
        least = F.least(F.col("sum_d"), F.lit(volume) - F.col("sum_d"))
        best = run.filter(least > 1e-9).select((F.col("sum_step") / least).alias("phi"), "value", "sid").orderBy("phi", "value", "sid").first()
        side = (F.col("value") > best.value) | (F.col("value") == best.value) & (F.col("sid") > best.sid)
    else:
        side = F.col("value") > (x.agg(F.percentile_approx("value", 0.5, 10_000)).first()[0] if threshold == "median" else 0.0)
    return supra.nodes.join(x, "sid").select("slice", "node", "value", side.cast("bigint").alias("community"))


def modularity_bisect(edges: DataFrame, gamma: float = 1.0, recursive: bool = False, most_levels: int | None = None) -> DataFrame:
    """node, community of a static graph by the sign of the leading modularity vector; a part without a positive eigenvalue stays whole.

    With recursive all parts of a level are split by one job, a task for each, until none splits (or
    most_levels is reached).  A part of more than DENSE_NODES nodes is refused.
    """
    both = edges.select(F.col("src").alias("a"), F.col("dst").alias("b"), "weight").union(edges.select("dst", "src", "weight"))
    d = cut(both.groupBy(F.col("a").alias("node")).agg(F.sum("weight").alias("k")), "degrees")
    ship(edges.sparkSession)
    two_m = d.agg(F.sum("k")).first()[0] or 1.0
    labels = d.select("node", F.lit(0).cast("bigint").alias("community"))

    def run(key: tuple, v: pa.Table, e: pa.Table) -> pa.Table:
        v = v.sort_by("node")
        ids, k, c = np.array(v.column("node")), np.array(v.column("k"), dtype=float), key[0].as_py()
        if len(ids) > DENSE_NODES:
            raise ValueError(f"{len(ids)} nodes in one task; the limit is {DENSE_NODES}")
        m = np.zeros((len(ids), len(ids)))
        np.add.at(m, (np.searchsorted(ids, np.array(e.column("a"), dtype=np.int64)), np.searchsorted(ids, np.array(e.column("b"), dtype=np.int64))), np.array(e.column("weight"), dtype=float))
        m -= gamma * np.outer(k, k) / two_m
        m -= np.diag(m.sum(1))
        values, vectors = np.linalg.eigh(m)
        side = (vectors[:, -1] * np.sign(vectors[np.argmax(np.abs(vectors[:, -1])), -1]) > 0).astype(np.int64)
        s = 2.0 * side - 1
        split = values[-1] > 1e-9 and s @ m @ s > 1e-9 and 0 < side.sum() < len(ids)
        return pa.table({"node": pa.array(ids), "community": pa.array(2 * c + 1 + side if split else np.full(len(ids), c)), "split": pa.array([bool(split)] * len(ids))})

    levels = range(1 if not recursive else most_levels if most_levels is not None else d.count())
    for _ in levels:
        inside = both.join(labels.toDF("a", "community"), "a").join(labels.toDF("b", "cb"), "b").filter("community = cb").select("community", "a", "b", "weight")
        own = labels.join(d, "node").select("community", "node", "k")
        after = cut(own.groupBy("community").cogroup(inside.groupBy("community")).applyInArrow(run, "node bigint, community bigint, split boolean"), "parts")
        labels = after.select("node", "community")
        if after.filter("split").isEmpty():
            break
    return labels
