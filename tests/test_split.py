"""Graphs that fall into components: one task for each pack of them, with rates of the whole graph."""

import importlib
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from chronocluster import arrays, kernels, plans, quality, supra
from chronocluster.components import check_connected, components, inner_parts, rooted
from chronocluster.session import cut
from chronocluster.temporal import TemporalGraph

plan = importlib.import_module("chronocluster.plans.leiden")


def clumps(spark, copies: int = 3) -> TemporalGraph:
    """Copies of a graph of two slices with cliques of five, joined in a ring."""
    rows = []
    for copy in range(copies):
        for t in (0, 1):
            for c in range(4):
                x = [100 * copy + 5 * c + i for i in range(5)]
                rows += [(t, a, b, 1.0 + t) for a in x for b in x if a < b]
                rows += [(t, *sorted((x[0], 100 * copy + (5 * c + 5) % 20)), 1.0)]
    return TemporalGraph(cut(spark.createDataFrame(rows, "slice int, src bigint, dst bigint, weight double"), "clumps"))


@pytest.mark.parametrize("null", ["slice", "global"])
def test_split_is_the_kernel(spark, monkeypatch, null):
    tg = clumps(spark).stored()
    known = {(r.slice, r.node): r.community for r in plans.leiden(tg, 1.0, null=null, backend_name="kernel").collect()}
    asked = []
    inner = plan._kernel_labels
    monkeypatch.setattr(plan, "SPLIT_EDGES", 40)
    monkeypatch.setattr(plan, "_kernel_labels", lambda *a, **o: asked.append(o.get("keys")) or inner(*a, **o))
    labels = cut(plans.leiden(tg, 1.0, null=null), "labels")
    assert asked == [["task"]]
    assert {(r.slice, r.node): r.community for r in labels.collect()} == known
    own = labels.select(supra.sid(F.col("slice"), F.col("node")).alias("sid"), "community")
    assert check_connected(supra.supra_graph(tg, 1.0).edges, own).first().broken == 0
    assert quality.multislice_modularity(tg, labels, omega=1.0).first().q_ms > 0.6


def test_components_are_found_once(spark, monkeypatch):
    tg = clumps(spark).stored()
    asked, inner = [], plan.rooted
    monkeypatch.setattr(plan, "SPLIT_EDGES", 40)
    monkeypatch.setattr(plan, "rooted", lambda e: asked.append(1) or inner(e))
    for null in ("slice", "global"):
        plans.leiden(tg, 1.0, null=null)
    assert len(asked) == 1
    less = tg.with_edges(cut(tg.edges.filter("src < 200"), "less"))
    assert cut(plans.leiden(less, 1.0), "labels").agg(F.max("node")).first()[0] < 200
    assert len(asked) == 2


def test_nodes_are_stored_with_edges(spark):
    tg = clumps(spark)
    nodes = tg.stored().active
    assert sorted(map(tuple, nodes.collect())) == sorted(map(tuple, tg.nodes.collect()))
    assert "explode" not in supra.supra_graph(tg.stored()).nodes._jdf.queryExecution().toString()


def test_components_of_arrays(spark, monkeypatch):
    rng = random.Random(3)
    rows = [(a := rng.randrange(900), a + rng.choice([0, 1, 1, 7])) for _ in range(700)]
    edges = spark.createDataFrame(rows, "src bigint, dst bigint").repartition(5)
    want = {r.node: r.component for r in components(edges).collect()}
    for most in (10, 2_000_000):
        monkeypatch.setattr("chronocluster.components.GATHERED", most)
        got = {r.node: r.component for r in rooted(edges).collect()}
        assert {v: c for v, c in got.items() if v in want} == want
        assert all(v == c for v, c in got.items() if v not in want)
    labels = spark.createDataFrame([(v, v % 2) for v in range(910)], "v bigint, c bigint")
    near = edges.filter("src % 2 = dst % 2 and src <> dst")
    want = {v: v for v in range(910)} | {r.node: r.component for r in components(near).collect()}
    assert {r.v: r.part for r in inner_parts(edges.toDF("a", "b"), labels).collect()} == want


@pytest.mark.parametrize("slices", [1, 4])
def test_tables_of_strengths(monkeypatch, slices):
    rng = np.random.default_rng(5)
    a, b = rng.integers(0, 60, (2, 400))
    k = [{s: (x, x) for s, x in enumerate(rng.random(slices).tolist())} for _ in range(60)]
    g, objective = kernels.Graph(60, a, b, np.ones(400), k), kernels.Objective(dict.fromkeys(range(slices), 1.0), dict.fromkeys(range(slices), 30.0))
    assert not isinstance(kernels._table(g, objective), kernels._Sparse)
    fast = kernels.leiden(g, objective)
    monkeypatch.setattr(kernels, "_table", kernels._Sparse)
    assert kernels.leiden(g, objective) == fast


def test_even_strengths_in_one_number(monkeypatch):
    rng = np.random.default_rng(7)
    a, b = rng.integers(0, 80, (2, 500))
    k = [{int(s): (x, x) for s, x in zip(rng.choice(40, 4, replace=False), rng.random(4).tolist(), strict=True)} for _ in range(80)]
    g, objective = kernels.Graph(80, a, b, np.ones(500), k), kernels.Objective(dict.fromkeys(range(40), 1.0), dict.fromkeys(range(40), 0.5))
    monkeypatch.setattr(kernels, "DENSE", 1)
    assert type(kernels._table(g, objective)) is kernels._Even
    fast = kernels.leiden(g, objective)
    monkeypatch.setattr(kernels, "_is_even", lambda g: False)
    assert type(kernels._table(g, objective)) is kernels._Sparse
    assert kernels.leiden(g, objective) == fast
    assert 1 < len(set(fast)) < 80


def test_totals_held_are_those_of_the_parts(monkeypatch):
    rng = np.random.default_rng(9)
    a, b, s = rng.integers(0, 50, 300), rng.integers(0, 50, 300), rng.integers(0, 6, 50)
    g = arrays.ArrayGraph.of(50, a, b, np.ones(300), np.arange(50), s, np.ones(50), np.ones(50), 6)
    part = rng.integers(0, 9, 50)
    dense = arrays.Totals(g, part).held()
    monkeypatch.setattr(arrays, "DENSE", 1)
    assert all((x == y).all() for x, y in zip(dense, arrays.Totals(g, part).held(), strict=True))
