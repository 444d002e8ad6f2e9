"""Communities over time: persistence, transitions, life cycles and structure."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .temporal import active_nodes


def by_node():
    return Window.partitionBy("node").orderBy("slice")


def persistence(labels: DataFrame) -> DataFrame:
    """slice, n, kept, rate: nodes seen in the slice before too, and those whose label is the same."""
    back = labels.withColumn("was", F.lag("community").over(by_node())).withColumn("before", F.lag("slice").over(by_node())).filter("before = slice - 1")
    return back.groupBy("slice").agg(F.count("*").alias("n"), F.count(F.when(F.col("was") == F.col("community"), 1)).alias("kept")).withColumn("rate", F.col("kept") / F.col("n"))


def label_changes(labels: DataFrame) -> DataFrame:
    """slice, node, was, community where the label differs from the node's last one, first sight included."""
    return labels.withColumn("was", F.lag("community").over(by_node())).filter(~F.col("was").eqNullSafe(F.col("community"))).select("slice", "node", "was", "community")


def community_timeline(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """slice, community, size, volume, inside (inner weight), cut."""
    a = labels.select("slice", F.col("node").alias("src"), F.col("community").alias("ca"))
    b = labels.select("slice", F.col("node").alias("dst"), F.col("community").alias("cb"))
    ends = edges.join(a, ["slice", "src"]).join(b, ["slice", "dst"])
    both = ends.select("slice", "ca", "cb", "weight").union(ends.select("slice", "cb", "ca", "weight"))
    per = both.groupBy("slice", F.col("ca").alias("community")).agg(
        F.sum("weight").alias("volume"), (F.sum(F.when(F.col("ca") == F.col("cb"), F.col("weight")).otherwise(0.0)) / 2).alias("inside"), F.sum(F.when(F.col("ca") != F.col("cb"), F.col("weight")).otherwise(0.0)).alias("cut")
    )
    sizes = labels.groupBy("slice", "community").agg(F.count("*").alias("size"))
    zero = F.lit(0.0)
    return sizes.join(per, ["slice", "community"], "left").select("slice", "community", "size", *(F.coalesce(c, zero).alias(c) for c in ("volume", "inside", "cut")))


def transitions(labels: DataFrame) -> DataFrame:
    """slice, from_community, to_community, n: nodes that go from one label to another between slice and the next."""
    after = labels.select((F.col("slice") - 1).alias("slice"), "node", F.col("community").alias("to_community"))
    return labels.join(after, ["slice", "node"]).groupBy("slice", F.col("community").alias("from_community"), "to_community").agg(F.count("*").alias("n"))


def lifecycle(labels: DataFrame) -> DataFrame:
    """slice, community, before, after, event between slice - 1 and slice: birth, death, growth, shrinkage or same."""
    sizes = labels.groupBy("slice", "community").agg(F.count("*").alias("size"))
    ends = labels.agg(F.min("slice").alias("lo"), F.max("slice").alias("hi"))
    earlier = sizes.select((F.col("slice") + 1).alias("slice"), "community", F.col("size").alias("before"))
    both = sizes.withColumnRenamed("size", "after").join(earlier, ["slice", "community"], "full_outer").crossJoin(F.broadcast(ends)).filter("slice > lo and slice <= hi")
    zero = F.lit(0)
    before, after = F.coalesce("before", zero), F.coalesce("after", zero)
    event = F.when(before == 0, "birth").when(after == 0, "death").when(after > before, "growth").when(after < before, "shrinkage").otherwise("same")
    return both.select("slice", "community", before.alias("before"), after.alias("after"), event.alias("event"))


def splits_and_merges(labels: DataFrame, share: float = 0.3) -> DataFrame:
    """slice, community, kind: split if two or more parts of at least share of it leave for different labels, merge for the reverse."""
    moves = transitions(labels)
    out = moves.withColumn("of", F.sum("n").over(Window.partitionBy("slice", "from_community"))).filter(F.col("n") >= share * F.col("of"))
    into = moves.withColumn("of", F.sum("n").over(Window.partitionBy("slice", "to_community"))).filter(F.col("n") >= share * F.col("of"))
    split = out.groupBy("slice", F.col("from_community").alias("community")).agg(F.count("*").alias("parts")).filter("parts > 1").withColumn("kind", F.lit("split"))
    merge = into.groupBy("slice", F.col("to_community").alias("community")).agg(F.count("*").alias("parts")).filter("parts > 1").withColumn("kind", F.lit("merge"))
    return split.unionByName(merge)


def match_labels(before: DataFrame, after: DataFrame, score: str = "overlap") -> DataFrame:
    """old, new, n, score of the mutual best pairs of two labellings (node, community) by overlap or Jaccard."""
    pairs = before.select("node", F.col("community").alias("old")).join(after.select("node", F.col("community").alias("new")), "node").groupBy("old", "new").agg(F.count("*").alias("n"))
    if score == "jaccard":
        a = before.groupBy(F.col("community").alias("old")).agg(F.count("*").alias("na"))
        b = after.groupBy(F.col("community").alias("new")).agg(F.count("*").alias("nb"))
        pairs = pairs.join(a, "old").join(b, "new").select("old", "new", "n", (F.col("n") / (F.col("na") + F.col("nb") - F.col("n"))).alias("score"))
    else:
        pairs = pairs.withColumn("score", F.col("n").cast("double"))
    first = F.row_number().over(Window.partitionBy("old").orderBy(F.desc("score"), "new"))
    second = F.row_number().over(Window.partitionBy("new").orderBy(F.desc("score"), "old"))
    return pairs.withColumns({"x": first, "y": second}).filter("x = 1 and y = 1").select("old", "new", "n", "score")


def structure_over_time(edges: DataFrame) -> DataFrame:
    """slice, nodes, edges, density, mean_degree, mean_square_degree."""
    ends = edges.select("slice", F.explode(F.array("src", "dst")).alias("node")).groupBy("slice", "node").agg(F.count("*").alias("d"))
    per = ends.groupBy("slice").agg(F.count("*").alias("nodes"), (F.sum("d") / 2).cast("bigint").alias("edges"), F.avg("d").alias("mean_degree"), F.avg(F.col("d") * F.col("d")).alias("mean_square_degree"))
    return per.select("slice", "nodes", "edges", F.coalesce(F.try_divide(2 * F.col("edges"), F.col("nodes") * (F.col("nodes") - 1)), F.lit(0.0)).alias("density"), "mean_degree", "mean_square_degree")


def edge_survival(edges: DataFrame) -> DataFrame:
    """slice, n, kept: edges of a slice and those that are there in the next one too."""
    ahead = F.lead("slice").over(Window.partitionBy("src", "dst").orderBy("slice"))
    return edges.withColumn("next", ahead).groupBy("slice").agg(F.count("*").alias("n"), F.count(F.when(F.col("next") == F.col("slice") + 1, 1)).alias("kept"))


def slice_jaccard(edges: DataFrame) -> DataFrame:
    """slice, jaccard of its edges with those of the next slice."""
    s = edge_survival(edges)
    after = s.select((F.col("slice") - 1).alias("slice"), F.col("n").alias("m"))
    return s.join(after, "slice").select("slice", (F.col("kept") / (F.col("n") + F.col("m") - F.col("kept"))).alias("jaccard"))


def first_seen(labels: DataFrame) -> DataFrame:
    """node, first and second slice of each node, and its first label."""
    w = by_node().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return labels.select("node", F.first("slice").over(w).alias("first"), F.nth_value("slice", 2).over(w).alias("second"), F.first("community").over(w).alias("community")).distinct()


def carry_labels(labels: DataFrame, edges: DataFrame, active: DataFrame | None = None) -> DataFrame:
    """The label in force for every node in every slice from its first on: carried over absence.

    Each label is repeated up to the node's next one, so no grid of nodes and slices is moved.
    active (slice, node), where it is known, spares the edges.
    """
    active = active_nodes(edges) if active is None else active
    slices = active.select("slice").distinct()
    numbered = F.broadcast(slices.withColumn("at", F.row_number().over(Window.orderBy("slice"))).withColumn("last", F.count("*").over(Window.partitionBy())))
    known = labels.filter("community is not null").join(active.select("node").distinct(), "node", "left_semi").join(numbered, "slice")
    until = F.coalesce(F.lead("at").over(by_node()) - 1, F.col("last"))
    lasting = known.select("node", "community", F.col("at").alias("lo"), until.alias("hi")).filter("lo <= hi")
    carried = lasting.select("node", "community", F.explode(F.sequence("lo", "hi")).alias("at"))
    return carried.join(numbered.select("slice", "at"), "at").select("slice", "node", "community")


def asof_labels(events: DataFrame, labels: DataFrame) -> DataFrame:
    """event, node, slice, community: the node's label of the latest slice not after the event's; one shuffle by node."""
    both = labels.select("slice", "node", "community", F.lit(None).cast("bigint").alias("event"), F.lit(0).alias("late")).unionByName(
        events.select("slice", "node", F.lit(None).cast("bigint").alias("community"), "event", F.lit(1).alias("late"))
    )
    w = Window.partitionBy("node").orderBy("slice", "late", "event").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("community", F.last("community", ignorenulls=True).over(w)).filter("late = 1").select("event", "node", "slice", "community")
