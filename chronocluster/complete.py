"""Communities of graphs whose slices are complete with weights of 1: no pair is made.

What pairs tell follows from how many members of a slice a community has.  Couplings lead to the next slice
only, so the parts of a community hang together by runs of slices.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .session import cut, forget
from .supra import sid
from .temporal import TemporalGraph

#: Rounds after which nodes that still move are an error.
ROUNDS = 1000


def sums(tg: TemporalGraph, labels: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(slice, w): weight inside communities; (slice, kk): squares of their strengths; (slice, two_m)."""
    n = F.col("n")
    totals = tg.nodes.groupBy("slice").agg(F.count("*").alias("n"))
    per = tg.nodes.join(labels, ["slice", "node"]).groupBy("slice", "community").agg(F.count("*").cast("double").alias("x"))
    parts = per.join(F.broadcast(totals), "slice").groupBy("slice").agg(F.sum(F.col("x") * (F.col("x") - 1) / 2).alias("w"), F.sum((F.col("x") * (n - 1)) * (F.col("x") * (n - 1))).alias("kk"))
    return parts.select("slice", "w"), parts.select("slice", "kk"), totals.select("slice", (n * (n - 1)).cast("double").alias("two_m"))


def runs(labels: DataFrame) -> DataFrame:
    """slice, community, run: slices of a community that hang together by couplings have one number."""
    ahead = Window.partitionBy("node").orderBy("slice")
    on = (F.lead("slice").over(ahead) == F.col("slice") + 1) & (F.lead("community").over(ahead) == F.col("community"))
    parts = labels.select("slice", "community", F.coalesce(on, F.lit(False)).alias("on")).groupBy("slice", "community").agg(F.max("on").alias("on"))
    order = Window.partitionBy("community").orderBy("slice")
    joined = F.lag("on").over(order) & (F.lag("slice").over(order) == F.col("slice") - 1)
    first = parts.withColumn("first", F.when(joined, 0).otherwise(1))
    return first.select("slice", "community", F.sum("first").over(order.rowsBetween(Window.unboundedPreceding, 0)).alias("run"))


def check_connected(labels: DataFrame) -> DataFrame:
    """One row: communities, and how many of them do not hang together."""
    per = runs(labels).groupBy("community").agg(F.max("run").alias("runs"))
    return per.agg(F.count("*").alias("communities"), F.count(F.when(F.col("runs") > 1, 1)).alias("broken"))


def _named(labels: DataFrame) -> DataFrame:
    """slice, node, community: every run is a community, named after its smallest temporal node."""
    parts = labels.groupBy("slice", "community").agg(F.min(sid(F.col("slice"), F.col("node"))).alias("least"))
    names = runs(labels).join(parts, ["slice", "community"]).withColumn("name", F.min("least").over(Window.partitionBy("community", "run"))).select("slice", "community", "name")
    return labels.join(names, ["slice", "community"]).select("slice", "node", F.col("name").alias("community"))


def slice_null(tg: TemporalGraph, omega: float) -> DataFrame:
    """The best labels under a null for each slice with a resolution of at most 1.

    Two of a slice's n nodes have an edge of 1 and expect (n - 1) / n at most, and couplings are not negative:
    to part nodes gains nothing, so the components are the optimum.
    """
    all_ = F.lit(0).cast("bigint") if omega > 0 else F.col("slice").cast("bigint")
    return _named(tg.nodes.select("slice", "node", all_.alias("community")))


def ties_are_weak(tg: TemporalGraph, omega: float, kernel_edges: int) -> bool:
    """Whether global_null serves: more pairs than one task takes, and copies that tie a node less than its slice does on average."""
    n = F.col("n")
    sizes = tg.nodes.groupBy("slice").agg(F.count("*").alias("n")).agg(F.sum(n * (n - 1) / 2).alias("pairs"), F.sum("n").alias("nodes")).first()
    return (sizes.pairs or 0) > kernel_edges and 2 * omega <= 2 * sizes.pairs / sizes.nodes


def global_null(tg: TemporalGraph, omega: float, gamma: float, solve) -> DataFrame:
    """Labels under one null for the supra-graph, where ties_are_weak().

    solve(edges, nulls) labels the graph of whole slices; then nodes move to the communities of their own copies,
    half of them at a time, as long as the objective rises.
    """
    at = Window.partitionBy("node").orderBy("slice")
    after, before = F.coalesce(F.lead("slice").over(at) == F.col("slice") + 1, F.lit(False)), F.coalesce(F.lag("slice").over(at) == F.col("slice") - 1, F.lit(False))
    tied = tg.nodes.select("slice", "node", after.cast("int").alias("after"), before.cast("int").alias("before"))
    slices = cut(tied.groupBy("slice").agg(F.count("*").alias("n"), F.sum("after").alias("after"), F.sum("before").alias("before")), "slices")
    n, w = F.col("n"), F.lit(float(omega))
    total = slices.agg(F.sum(n * (n - 1) + w * (F.col("after") + F.col("before")))).first()[0]
    if not total:
        return _named(tg.nodes.select("slice", "node", F.col("slice").cast("bigint").alias("community")))
    v = F.col("slice").cast("bigint")
    k = (n * (n - 1) + w * (F.col("after") + F.col("before"))).cast("double")
    upper = slices.filter("after > 0").select(v.alias("a"), (v + 1).alias("b"), (w * F.col("after")).alias("weight"))
    whole = solve(upper.unionByName(upper.select(F.col("b").alias("a"), F.col("a").alias("b"), "weight")), slices.select(v.alias("v"), F.lit(0).alias("s"), k.alias("ko"), k.alias("ki")))
    rows = tied.join(F.broadcast(slices.select("slice", "n")), "slice").join(F.broadcast(whole.select(F.col("v").cast("int").alias("slice"), "community")), "slice")
    rows = cut(rows.select("slice", "node", (n - 1 + w * (F.col("after") + F.col("before"))).cast("double").alias("d"), "community"), "state")
    value = _objective(rows, omega, gamma / total)
    for r in range(ROUNDS):
        moving = cut(_moves(rows, omega, gamma / total), "moves")
        count = moving.count()
        for share in (1 << i for i in range(1, count.bit_length() + 1)):
            some = moving.filter(F.pmod(F.xxhash64("slice", "node", F.lit(r)), F.lit(share)) == 0)
            then_rows = cut(rows.join(some, ["slice", "node"], "left").select("slice", "node", "d", F.coalesce("to", "community").alias("community")), "state")
            then = _objective(then_rows, omega, gamma / total)
            if then > value + max(5e-10, 1e-13 * abs(value)):
                forget(rows)
                rows, value = then_rows, then
                break
            forget(then_rows)
        else:
            break
    else:
        raise RuntimeError(f"nodes still move after {ROUNDS} rounds")
    return _named(rows.select("slice", "node", "community"))


def _beside(rows: DataFrame) -> DataFrame:
    """rows with cb and ca, the communities of a node's copies one slice before and after."""
    at = Window.partitionBy("node").orderBy("slice")
    near = lambda f, step: F.when(f("slice").over(at) == F.col("slice") + step, f("community").over(at))
    return rows.withColumns({"cb": near(F.lag, -1), "ca": near(F.lead, 1)})


def _objective(rows: DataFrame, omega: float, rate: float) -> float:
    parts = rows.groupBy("slice", "community").agg(F.count("*").cast("double").alias("n"), F.sum("d").alias("d"))
    inside = parts.agg(F.sum(F.col("n") * (F.col("n") - 1) / 2)).first()[0]
    null = parts.groupBy("community").agg(F.sum("d").alias("d")).agg(F.sum(F.col("d") * F.col("d") / 2)).first()[0]
    kept = _beside(rows).filter("ca = community").count()
    return inside + omega * kept - rate * null


def _moves(rows: DataFrame, omega: float, rate: float) -> DataFrame:
    """slice, node, to of every node that gains in the community of a copy of its own."""
    edge = _beside(rows).filter("cb <> community or ca <> community")
    choices = edge.withColumn("to", F.explode(F.array_distinct(F.array("community", F.coalesce("cb", "community"), F.coalesce("ca", "community")))))
    parts = rows.groupBy("slice", F.col("community").alias("to")).agg(F.count("*").alias("n"), F.sum("d").alias("part"))
    volumes = parts.groupBy("to").agg(F.sum("part").alias("volume"))
    own = F.when(F.col("to") == F.col("community"), 1.0).otherwise(0.0)
    copies = F.coalesce((F.col("cb") == F.col("to")).cast("int"), F.lit(0)) + F.coalesce((F.col("ca") == F.col("to")).cast("int"), F.lit(0))
    gain = F.coalesce("n", F.lit(0)) - own + F.lit(float(omega)) * copies - F.lit(rate) * F.col("d") * (F.col("volume") - own * F.col("d"))
    scored = choices.join(parts.select("slice", "to", "n"), ["slice", "to"], "left").join(volumes, "to").select("slice", "node", "to", own.alias("own"), gain.alias("gain"))
    best = scored.groupBy("slice", "node").agg(F.max(F.struct("gain", (-F.col("to")).alias("minus"))).alias("best"), F.max(F.when(F.col("own") == 1, F.col("gain"))).alias("stay"))
    return best.filter("best.gain > stay + 1e-9").select("slice", "node", (-F.col("best.minus")).alias("to"))
