"""The two-triangle fixture against numbers from an independent dense calculation."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from chronocluster import kernels, quality
from chronocluster.linalg import block_eigs, gram, lanczos, nonsymmetric_eigs, power_iteration
from chronocluster.operators import DeformedLaplacian, Laplacian, ModularityOp, MultisliceModularityOp, NonBacktracking, choose_r, random_block
from chronocluster.operators.base import columns_of
from chronocluster.plans import baseline_multislice_sequential, fiedler_split, independent_snapshots, leiden, louvain, modularity_bisect, spectral_clustering, windowed
from chronocluster.supra import supra_graph, supra_size
from chronocluster.temporal import snapshot


def value(df):
    return df.first()[0]


def same_parts(rows, truth):
    found = {}
    for r in rows:
        found.setdefault(r.community, set()).add((r.slice, r.node))
    want = {}
    for s, v, c in truth:
        want.setdefault(c, set()).add((s, v))
    return sorted(map(sorted, found.values())) == sorted(map(sorted, want.values()))


TRIANGLES = [(s, v, v // 3) for s in (1, 2) for v in range(6)]


@pytest.fixture(scope="module")
def first(toy):
    return snapshot(toy.edges, 1)


@pytest.fixture(scope="module")
def static(toy_labels):
    return toy_labels.filter("slice = 1").select("node", "community")


def test_modularity(first, static):
    assert value(quality.modularity(first, static)) == pytest.approx(5 / 14)
    assert value(quality.modularity(first, static.withColumn("community", F.lit(0)))) == pytest.approx(0)


@pytest.mark.parametrize(("omega", "q", "mu"), [(1.0, 0.55, 40), (0.5, 0.470588, 34), (0.0, 0.357143, 28)])
def test_multislice_modularity(toy, toy_labels, omega, q, mu):
    r = quality.multislice_modularity(toy, toy_labels, omega=omega).first()
    assert r.q_ms == pytest.approx(q, abs=1e-6) and r.two_mu == mu


def test_multislice_modularity_of_other_labels(toy, toy_labels):
    swapped = toy_labels.withColumn("community", F.when(F.col("slice") == 2, 1 - F.col("community")).otherwise(F.col("community")))
    assert value(quality.multislice_modularity(toy, swapped)) == pytest.approx(0.25)
    one = toy_labels.withColumn("community", F.lit(0))
    assert value(quality.multislice_modularity(toy, one)) == pytest.approx(0.30)
    assert value(quality.multislice_modularity(toy, one, gamma=0.0)) == pytest.approx(1.0)


def test_supra_modularity_and_cuts(toy, toy_labels, first, static):
    supra = supra_graph(toy)
    assert value(quality.supra_modularity(supra, toy_labels)) == pytest.approx(0.40)
    assert value(quality.supra_modularity(supra, toy_labels.withColumn("community", F.lit(0)))) == pytest.approx(0.0)
    assert value(quality.ncut(first, static)) == pytest.approx(2 / 7)
    assert value(quality.rcut(first, static)) == pytest.approx(2 / 3)
    assert value(quality.supra_ncut(supra, toy_labels)) == pytest.approx(0.20)
    assert value(quality.cpm(first, static, 0.5)) == pytest.approx(3.0)
    assert [r.conductance for r in quality.conductance(first, static).collect()] == pytest.approx([1 / 7, 1 / 7])
    assert supra_size(supra).first()[:3] == (12, 14, 6)


def dense(op, n):
    """The matrix of an operator, column by column."""
    ids = [r.sid for r in op.nodes.select("sid").orderBy("sid").collect()]
    spark = op.nodes.sparkSession
    rows = [(s, *(float(i == j) for j in range(n))) for i, s in enumerate(ids)]
    unit = spark.createDataFrame(rows, "sid bigint, " + ", ".join(f"c{j} double" for j in range(n)))
    return np.array([[r[f"c{j}"] for j in range(n)] for r in op.apply(unit).orderBy("sid").collect()])


def test_laplacian_spectra(toy, first):
    one = supra_graph(toy.with_edges(first))
    plain = dense(Laplacian(one, "unnormalised"), 6)
    assert np.linalg.eigvalsh(plain)[1] == pytest.approx(0.438447, abs=1e-6)
    normal = dense(Laplacian(one, "symmetric"), 6)
    assert np.linalg.eigvalsh(normal)[1] == pytest.approx(0.204666, abs=1e-6)
    walk = dense(Laplacian(one, "random_walk"), 6)
    assert np.sort(np.linalg.eigvals(walk).real) == pytest.approx(np.linalg.eigvalsh(normal), abs=1e-9)
    assert dense(DeformedLaplacian(one, 1.0), 6) == pytest.approx(plain)


def test_deformed_laplacian(toy, first):
    one, both = supra_graph(toy.with_edges(first)), supra_graph(toy)
    assert choose_r(one, "sqrt_mean_degree") == pytest.approx(1.527525, abs=1e-6)
    assert choose_r(one) == pytest.approx(1.195229, abs=1e-6)
    assert np.linalg.eigvalsh(dense(DeformedLaplacian(one, "sqrt_mean_degree"), 6))[:2] == pytest.approx([0.088452, 0.870644], abs=1e-6)
    assert np.linalg.eigvalsh(dense(DeformedLaplacian(one), 6))[:2] == pytest.approx([-0.029366, 0.534633], abs=1e-6)
    assert choose_r(both) == pytest.approx(1.549193, abs=1e-6)
    assert np.linalg.eigvalsh(dense(DeformedLaplacian(both), 12))[:2] == pytest.approx([-0.440991, 0.412944], abs=1e-6)


def test_modularity_matrices(toy, toy_labels, first):
    one, both = supra_graph(toy.with_edges(first)), supra_graph(toy)
    m = dense(ModularityOp(one.edges, one.nodes), 6)
    values, vectors = np.linalg.eigh(m)
    assert values[-1] == pytest.approx(3**0.5)
    assert len({v > 0 for v in vectors[:3, -1]}) == 1 and (vectors[0, -1] > 0) != (vectors[5, -1] > 0)
    c = np.repeat(np.eye(2), 3, axis=0)
    assert np.trace(c.T @ m @ c) / 14 == pytest.approx(5 / 14)
    mm = dense(MultisliceModularityOp(toy, both), 12)
    assert mm == pytest.approx(mm.T)
    cc = np.vstack([c, c])
    assert np.trace(cc.T @ mm @ cc) / 40 == pytest.approx(0.55)


def test_nonbacktracking_step_is_the_block_matrix(toy, spark):
    supra = supra_graph(toy)
    op = NonBacktracking(supra, 0.6, 0.7)
    ids = [r.sid for r in supra.nodes.orderBy("sid").collect()]
    at = {s: i for i, s in enumerate(ids)}
    e = supra.edges.collect()
    a, b = np.array([at[r.a] for r in e]), np.array([at[r.b] for r in e])
    matrix = kernels.dense_operator("nonbacktracking", a, b, np.ones(len(e)), np.array([r.kind == "s" for r in e]), np.zeros(12, int), {"lam": 0.6, "eta": 0.7})
    x = np.random.default_rng(0).standard_normal((12, 4))
    block = spark.createDataFrame([(s, *map(float, x[i])) for i, s in enumerate(ids)], "sid bigint, gs double, hs double, gt double, ht double")
    got = np.array([[r.gs, r.hs, r.gt, r.ht] for r in op.apply(block).orderBy("sid").collect()])
    assert got.T.ravel() == pytest.approx(matrix @ x.T.ravel())
    values = np.linalg.eigvals(matrix)
    values = values[np.argsort(-values.real)]
    assert values[0].real == pytest.approx(1.486070, abs=1e-5)
    assert sorted([values[1].imag, values[2].imag]) == pytest.approx([-0.360086, 0.360086], abs=1e-5)
    top, _ = nonsymmetric_eigs(op, 1, most=10)
    assert top[0].real == pytest.approx(1.486070, abs=5e-2)


def test_distributed_solvers(toy):
    supra = supra_graph(toy)
    op = DeformedLaplacian(supra)
    want = np.linalg.eigvalsh(dense(op, 12))
    values, vectors, residuals = block_eigs(op, 2, most=4)
    assert values == pytest.approx(want[:2], abs=1e-3) and residuals.max() < 1e-1
    assert gram(vectors) == pytest.approx(np.eye(2), abs=1e-6)
    assert lanczos(op, 1, steps=11)[0] == pytest.approx(want[:1], abs=2e-2)
    top, _ = power_iteration(op, steps=12)
    assert 0.85 * want[-1] <= top <= want[-1] + 1e-6
    assert len(columns_of(random_block(supra.nodes, 3))) == 3


@pytest.mark.parametrize(("null", "backend"), [("slice", "kernel"), ("global", "kernel"), ("slice", "distributed")])
def test_leiden(toy, null, backend):
    labels = leiden(toy, omega=1.0, null=null, backend_name=backend, finish=0)
    assert same_parts(labels.collect(), TRIANGLES)


def test_other_front_doors(toy):
    assert same_parts(louvain(toy, omega=1.0).collect(), TRIANGLES)
    assert same_parts(baseline_multislice_sequential(toy, omega=1.0).collect(), TRIANGLES)
    assert same_parts(leiden(toy, omega=1.0, gamma=0.5, quality="cpm").collect(), TRIANGLES)
    assert same_parts(leiden(toy, omega=1.0, quality="surprise").collect(), TRIANGLES)
    assert same_parts(windowed(toy, 2, 1, omega=1.0).collect(), TRIANGLES)
    assert same_parts(independent_snapshots(toy, match=True).collect(), TRIANGLES)
    assert len({r.community for r in independent_snapshots(toy).collect()}) == 4


@pytest.mark.parametrize("operator", ["deformed", "modularity", "laplacian", "nonbacktracking"])
def test_spectral(toy, operator):
    assert same_parts(spectral_clustering(toy, 2, operator, omega=1.0, lam=0.6, eta=0.7).collect(), TRIANGLES)


def test_splits(toy, first):
    assert same_parts(fiedler_split(toy.with_edges(first)).collect(), TRIANGLES[:6])
    assert same_parts(fiedler_split(toy.with_edges(first), threshold="sweep").collect(), TRIANGLES[:6])
    found = {r.node: r.community for r in modularity_bisect(first, recursive=True).collect()}
    assert len(set(found.values())) == 2 and found[0] == found[1] == found[2] != found[3]


def test_exhaustive_optimum(toy, first):
    """No partition of the first slice is better than the triangles."""
    e = [(r.src, r.dst) for r in first.collect()]
    k = np.bincount(np.array(e).ravel(), minlength=6)

    def q(p):
        p = np.array(p)
        return sum(p[u] == p[v] for u, v in e) / 7 - sum((k[p == c].sum() / 14) ** 2 for c in set(p.tolist()))

    def strings(prefix):
        if len(prefix) == 6:
            yield prefix
            return
        for c in range(max(prefix, default=-1) + 2):
            yield from strings([*prefix, c])

    every = list(strings([0]))
    assert len(every) == 203
    assert max(map(q, every)) == pytest.approx(5 / 14)
