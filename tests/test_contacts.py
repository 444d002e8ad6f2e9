"""Contact graphs: what needs no pair makes none, and what needs pairs does not move them."""

import re

import pytest
from pyspark.sql import functions as F

from chronocluster import catalog, complete, plans, quality, supra, tracking, workloads
from chronocluster.components import check_connected
from chronocluster.temporal import TemporalGraph, active_nodes, co_occurrence, meetings, slice_members

MEETINGS = [(0, 1), (0, 1), (0, 2), (0, 3), (1, 1), (3, 2), (3, 3), (4, 9), (4, 9), (7, 1), (7, 3), (7, None), (None, 1)]


@pytest.fixture(scope="module")
def rows(spark):
    return spark.createDataFrame(MEETINGS, "slice int, who bigint")


def in_order(df, *columns):
    return sorted(tuple(r) for r in df.select(*columns).collect())


def plan(df):
    return df._jdf.queryExecution().optimizedPlan().toString()


def test_meetings_are_the_pairs_of_a_slice(rows):
    want = co_occurrence(rows.withColumn("g", F.col("slice")), "slice", "g", "who")
    got = meetings(rows, "slice", "who")
    columns = ("slice", "src", "dst", "weight")
    assert in_order(got, *columns) == in_order(want, *columns) == [(0, 1, 2, 1.0), (0, 1, 3, 1.0), (0, 2, 3, 1.0), (3, 2, 3, 1.0), (7, 1, 3, 1.0)]
    assert in_order(slice_members(rows, "slice", "who"), "slice", "node") == in_order(active_nodes(got), "slice", "node")


@pytest.mark.parametrize("name", ["absent_nodes", "carry_labels", "coupling_next_seen", "lifecycle", "asof_labels"])
def test_no_pair_is_made_for_what_nodes_tell(spark, sf, name):
    assert not re.search(r"\b(src|dst)#", plan(catalog.QUERIES[name](spark, sf)))


def test_pairs_are_not_grouped(spark, sf):
    made = plan(catalog.QUERIES["index_slices"](spark, sf))
    assert "src" in made and "count(1)" not in made
    assert workloads.WORKLOADS["contact_10min"].active is not None


def test_carried_labels_skip_empty_ones_and_unknown_slices(spark):
    edges = spark.createDataFrame([(0, 1, 2, 1.0), (2, 1, 3, 1.0), (5, 2, 3, 1.0)], "slice int, src bigint, dst bigint, weight double")
    labels = spark.createDataFrame([(0, 1, 7), (2, 1, None), (2, 3, 8), (5, 3, 9), (1, 2, 4), (0, 99, 1)], "slice int, node bigint, community bigint")
    assert in_order(tracking.carry_labels(labels, edges), "slice", "node", "community") == [(0, 1, 7), (2, 1, 7), (2, 3, 8), (5, 1, 7), (5, 3, 9)]


@pytest.mark.parametrize("block", [2, 5, 16_384])
def test_pairs_that_meet_are_counted_once(spark, monkeypatch, block):
    monkeypatch.setattr(supra, "PAIR_BLOCK", block)
    monkeypatch.setattr(supra, "PAIR_PIECE", 3)
    rows = spark.createDataFrame([(s, (7 * s + 5 * i) % 23 * 10**12) for s in range(12) for i in range(s)] + [(50, 1), (60, None)], "slice int, who bigint")
    want = supra.dataset_properties(meetings(rows, "slice", "who"))
    got = supra.meeting_properties(slice_members(rows, "slice", "who"))
    assert got.columns == want.columns and got.first() == want.first() and got.first().e > 0
    assert supra.meeting_properties(slice_members(rows.filter("slice > 40"), "slice", "who")).first()[:5] == (0, 0, 0, 0, 0)


def test_properties_of_contacts_make_no_pair(spark, sf):
    assert "dst#" not in plan(catalog.QUERIES["properties_contact_5min"](spark, sf))


def test_approximate_counts_are_within_five_percent(spark):
    """On these ids a sketch of Spark's own default is off by more."""
    for first in (5000, 7000, 37000):
        edges = spark.range(first, first + 1000, 2).select(F.lit(0).alias("slice"), F.col("id").alias("src"), (F.col("id") + 1).alias("dst"), F.lit(1.0).alias("weight"))
        near = supra.dataset_properties(edges, approx=True).first()
        assert abs(near.v - 1000) <= 50 and abs(near.e - 500) <= 25


@pytest.fixture(scope="module")
def both(spark):
    """A graph of complete slices, some of two nodes, with a gap; without its edges, and with them."""
    rows = spark.createDataFrame([(s + (s > 6), (11 * s * s + 3 * i * (1 + s % 3)) % 17) for s in range(12) for i in range(1 + s % 5)], "slice int, who bigint")
    members = slice_members(rows, "slice", "who")
    edges = meetings(rows, "slice", "who")
    return TemporalGraph(edges, active=members, complete=True).stored(), TemporalGraph(edges).stored()


@pytest.mark.parametrize("classes", [1, 3])
def test_complete_slices_score_as_their_pairs(both, classes):
    fast, plain = both
    labels = plain.nodes.select("slice", "node", F.pmod(F.col("node") + F.floor(F.col("slice") / 3), F.lit(classes)).alias("community"))
    got, want = (quality.multislice_modularity(g, labels, omega=0.7).first() for g in both)
    assert got.q_ms == pytest.approx(want.q_ms) and got.two_mu == pytest.approx(want.two_mu)
    whole = check_connected(supra.supra_graph(plain, 1.0).edges, labels.select(supra.sid(F.col("slice"), F.col("node")).alias("sid"), "community")).first()
    assert complete.check_connected(labels).first() == whole


@pytest.mark.parametrize("null", ["slice", "global"])
def test_complete_slices_are_labelled_without_pairs(spark, both, null):
    fast, plain = both
    known = plans.leiden(plain, 0.5, null=null, backend_name="kernel")
    spark.conf.set("chronocluster.kernel_edges", "5")
    try:
        labels = plans.leiden(fast, 0.5, null=null)
    finally:
        spark.conf.unset("chronocluster.kernel_edges")
    assert not re.search(r"\bdst#", plan(labels))
    assert in_order(labels, "slice", "node") == in_order(plain.nodes, "slice", "node")
    assert complete.check_connected(labels).first().broken == 0
    if null == "slice":
        q, best = (quality.multislice_modularity(plain, x, omega=0.5).first().q_ms for x in (labels, known))
        assert q >= best - 1e-9
    else:
        graph = supra.supra_graph(plain, 0.5)
        q, best = (quality.supra_modularity(graph, x).first().q for x in (labels, known))
        assert q >= best - 0.02


def test_slices_are_not_taken_as_wholes_where_copies_tie_more(both):
    pairs = both[1].edges.count()
    assert complete.ties_are_weak(both[0], 0.5, pairs - 1)
    assert not complete.ties_are_weak(both[0], 0.5, pairs)
    assert not complete.ties_are_weak(both[0], 6.0, 5)
