"""Temporal graphs: a time-stamped relation cut into snapshots over one node set."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .session import cut

#: Slices per unit that date_trunc knows; other widths are intervals such as "5 minutes".
UNITS = ("year", "quarter", "month", "week", "day", "hour", "minute")


@dataclass(frozen=True)
class TemporalGraph:
    """Lazy frames: edges (slice, src, dst, weight; src < dst unless directed) and what is known beside them."""

    edges: DataFrame
    directed: bool = False
    slices: DataFrame | None = None
    meta: dict = field(default_factory=dict)
    #: (slice, node) where these are known without making the edges.
    active: DataFrame | None = None
    #: Every slice holds all pairs of its active nodes, each with weight 1: the edges need not be made.
    complete: bool = False

    @property
    def nodes(self) -> DataFrame:
        """(slice, node): the end points of each slice's edges."""
        return active_nodes(self.edges) if self.active is None else self.active

    def stored(self) -> TemporalGraph:
        """The same graph with its edges and nodes written once to the shared folder, for methods that read them again and again.

        Of a complete one the nodes are written, and its edges made from these where a method asks for them.
        """
        if self.complete and not self.meta.get("stored"):
            members = cut(self.nodes, "members")
            return replace(self, edges=meetings(members, "slice", "node"), active=members, meta={**self.meta, "stored": True})
        if self.meta.get("stored"):
            return self
        edges = cut(self.edges, "edges")
        return replace(self, edges=edges, active=cut(active_nodes(edges), "nodes"), meta={**self.meta, "stored": True})

    def with_edges(self, edges: DataFrame) -> TemporalGraph:
        return replace(self, edges=edges, meta={**{k: x for k, x in self.meta.items() if k != "packed"}, "stored": False}, active=None, complete=False)


def active_nodes(edges: DataFrame) -> DataFrame:
    return edges.select("slice", F.explode(F.array("src", "dst")).alias("node")).distinct()


def slice_number(time: Column, every: str, origin: str = "1970-01-01") -> Column:
    """Index of the slice that holds a time, counted from the slice that holds origin."""
    start = F.lit(origin).cast("timestamp")
    if every in ("year", "quarter", "month"):
        months = (F.year(time) - F.year(start)) * 12 + F.month(time) - F.month(start)
        if every == "month":
            return months.cast("int")
        if every == "year":
            return (F.year(time) - F.year(start)).cast("int")
        return ((F.year(time) * 4 + F.quarter(time)) - (F.year(start) * 4 + F.quarter(start))).cast("int")
    width = {"week": 604800, "day": 86400, "hour": 3600, "minute": 60}.get(every) or _seconds(every)
    return F.floor((F.unix_micros(time) - F.unix_micros(start)) / F.lit(width * 1_000_000)).cast("int")


def _seconds(every: str) -> int:
    n, unit = every.split()
    return int(n) * {"second": 1, "minute": 60, "hour": 3600, "day": 86400}[unit.rstrip("s")]


def canonicalise(edges: DataFrame, directed: bool = False, loops: str = "drop", weight: str = "sum") -> DataFrame:
    """One row per slice and pair: src < dst unless directed; weights summed, or 1 if weight is binary."""
    kept = edges if loops == "keep" else edges.filter("src <> dst")
    ends = [F.col("src"), F.col("dst")] if directed else [F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")]
    total = F.lit(1.0) if weight == "binary" else F.sum("weight").cast("double")
    return kept.select("slice", *ends, "weight").groupBy("slice", "src", "dst").agg(total.alias("weight") if weight != "binary" else F.max(F.lit(1.0)).alias("weight"))


def slice_edges(df: DataFrame, time: str, every: str, src: str, dst: str, weight: str = "count", origin: str = "1970-01-01", directed: bool = False, loops: str = "drop") -> TemporalGraph:
    """Cut a relation with a time column into snapshots.

    weight: count of rows, sum:<column>, or binary.  Filters on the time column itself still reach the scan.
    """
    value = F.col(weight[4:]).cast("double") if weight.startswith("sum:") else F.lit(1.0)
    rows = df.select(slice_number(F.col(time), every, origin).alias("slice"), F.col(src).cast("bigint").alias("src"), F.col(dst).cast("bigint").alias("dst"), value.alias("weight"))
    return TemporalGraph(canonicalise(rows.dropna(subset=["slice", "src", "dst"]), directed, loops, "binary" if weight == "binary" else "sum"), directed, meta={"every": every, "origin": origin})


def index_slices(edges: DataFrame, gaps: str = "keep", active: DataFrame | None = None) -> DataFrame:
    """Slices from 0: shifted by the first (keep), or numbered without gaps (close); the frame of slices is one row each.

    active (slice, node), where it is known, spares a pass over the edges.
    """
    slices = (edges if active is None else active).select("slice").distinct()
    numbered = slices.withColumn("ix", (F.dense_rank().over(Window.orderBy("slice")) - 1) if gaps == "close" else F.col("slice") - F.min("slice").over(Window.partitionBy()))
    return edges.join(F.broadcast(numbered), "slice").select(F.col("ix").cast("int").alias("slice"), "src", "dst", "weight")


def index_nodes(df: DataFrame, columns: list[str]) -> tuple[DataFrame, DataFrame]:
    """Replace external ids by dense longs; also returns the dictionary (name, ix).

    Names are sorted over range partitions; each partition's start is the sum of the sizes before
    it (one row per partition), so no task sees all names.
    """
    names = df.select(F.explode(F.array(*columns)).alias("name")).filter("name is not null").distinct()
    sorted_names = names.sort("name").withColumn("at", F.monotonically_increasing_id())
    part = F.shiftright("at", 33)
    sizes = sorted_names.groupBy(part.alias("part")).agg(F.count("*").alias("n"))
    starts = sizes.select("part", (F.sum("n").over(Window.orderBy("part")) - F.col("n")).alias("start"))
    dictionary = sorted_names.withColumn("part", part).join(F.broadcast(starts), "part").select("name", (F.col("start") + F.col("at") % F.lit(1 << 33)).alias("ix"))
    for c in columns:
        df = df.join(dictionary.select(F.col("name").alias(c), F.col("ix").alias(f"__{c}")), c, "left").drop(c).withColumnRenamed(f"__{c}", c)
    return df, dictionary


def presence(edges: DataFrame, policy: str = "active") -> DataFrame:
    """(slice, node): active in a slice, all (every node in every slice), or span (first to last seen)."""
    active = active_nodes(edges)
    if policy == "active":
        return active
    if policy == "all":
        return active.select("node").distinct().crossJoin(F.broadcast(edges.select("slice").distinct())).select("slice", "node")
    if policy == "span":
        return active.groupBy("node").agg(F.min("slice").alias("lo"), F.max("slice").alias("hi")).select(F.explode(F.sequence("lo", "hi")).alias("slice"), "node")
    raise ValueError(policy)


def flatten(edges: DataFrame) -> DataFrame:
    """The static graph of all slices together."""
    return edges.groupBy("src", "dst").agg(F.sum("weight").alias("weight")).select(F.lit(0).alias("slice"), "src", "dst", "weight")


def snapshot(edges: DataFrame, t: int) -> DataFrame:
    return edges.filter(F.col("slice") == t)


def between_slices(edges: DataFrame, lo: int, hi: int) -> DataFrame:
    return edges.filter(F.col("slice").between(lo, hi))


def min_weight(edges: DataFrame, least: float) -> DataFrame:
    return edges.filter(F.col("weight") >= least)


def backbone(edges: DataFrame, k: int) -> DataFrame:
    """Edges among the k strongest of at least one end, per slice; ties go to the smaller neighbour."""
    ends = edges.select("slice", F.col("src").alias("node"), F.col("dst").alias("other"), "weight").union(edges.select("slice", "dst", "src", "weight"))
    rank = F.row_number().over(Window.partitionBy("slice", "node").orderBy(F.desc("weight"), "other"))
    best = ends.withColumn("rank", rank).filter(F.col("rank") <= k)
    return best.select("slice", F.least("node", "other").alias("src"), F.greatest("node", "other").alias("dst"), "weight").distinct()


def induced(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    """The edges with both ends among nodes (node)."""
    return edges.join(nodes.select(F.col("node").alias("src")), "src", "left_semi").join(nodes.select(F.col("node").alias("dst")), "dst", "left_semi").select("slice", "src", "dst", "weight")


def ego(edges: DataFrame, node: int, hops: int = 1) -> DataFrame:
    """Nodes at most hops edges away, time ignored, with their distance."""
    pairs = edges.select("src", "dst").distinct()
    both = pairs.union(pairs.select("dst", "src")).toDF("u", "v")
    reached = edges.sparkSession.createDataFrame([(node, 0)], "node bigint, distance int")
    frontier = reached
    for d in range(1, hops + 1):
        frontier = frontier.join(both, F.col("node") == F.col("u")).select(F.col("v").alias("node"), F.lit(d).alias("distance")).distinct()
        reached = reached.union(frontier)
    return reached.groupBy("node").agg(F.min("distance").alias("distance"))


def absent_nodes(edges: DataFrame, t: int, active: DataFrame | None = None) -> DataFrame:
    """Nodes without an edge in slice t; active (slice, node), where it is known, spares the edges."""
    active = active_nodes(edges) if active is None else active
    return active.select("node").distinct().join(active.filter(F.col("slice") == t), "node", "left_anti")


def co_occurrence(rows: DataFrame, slice_: str, group: str, member: str, max_group: int | None = None) -> DataFrame:
    """Members that share a group, per slice; the weight is the number of shared groups.

    Pairs grow with the square of a group.  max_group leaves out larger groups, as an explicit choice of the caller.
    """
    members = rows.select(F.col(slice_).cast("int").alias("slice"), F.col(group).alias("g"), F.col(member).cast("bigint").alias("m")).distinct()
    if max_group is not None:
        sizes = members.groupBy("slice", "g").agg(F.count("*").alias("n")).filter(F.col("n") <= max_group)
        members = members.join(sizes.select("slice", "g"), ["slice", "g"], "left_semi")
    other = members.select("slice", "g", F.col("m").alias("o"))
    return members.join(other, ["slice", "g"]).filter("m < o").groupBy("slice", F.col("m").alias("src"), F.col("o").alias("dst")).agg(F.count("*").cast("double").alias("weight"))


def slice_members(rows: DataFrame, slice_: str, member: str) -> DataFrame:
    """(slice, node): members of slices that hold at least two, which are the active nodes of meetings()."""
    members = rows.select(F.col(slice_).cast("int").alias("slice"), F.col(member).cast("bigint").alias("node")).dropna()
    several = members.groupBy("slice").agg(F.min("node").alias("lo"), F.max("node").alias("hi")).filter("lo < hi").select("slice")
    return members.distinct().join(F.broadcast(several), "slice", "left_semi").select("slice", "node")


def meetings(rows: DataFrame, slice_: str, member: str) -> DataFrame:
    """All pairs of members of a slice, with weight 1: co_occurrence() where the slice itself is the group.

    A pair is there once in a slice, so the pairs are neither counted nor moved.
    """
    members = rows.select(F.col(slice_).cast("int").alias("slice"), F.col(member).cast("bigint").alias("src")).distinct()
    other = members.select("slice", F.col("src").alias("dst"))
    return members.join(other, "slice").filter("src < dst").select("slice", "src", "dst", F.lit(1.0).alias("weight"))


def contacts_within(events: DataFrame, who: str, at: str, seconds: int) -> DataFrame:
    """Pairs of different users at most so many seconds apart, with the number of such event pairs.

    Times fall into buckets of that width; an event meets its own bucket and the next one only.
    """
    e = events.select(F.col(who).alias("u"), F.unix_micros(at).alias("t")).withColumn("bucket", F.floor(F.col("t") / F.lit(seconds * 1_000_000)))
    near = e.select(F.explode(F.array(F.col("bucket"), F.col("bucket") + 1)).alias("bucket"), F.col("u").alias("v"), F.col("t").alias("s"), F.col("bucket").alias("home"))
    both = e.join(near, "bucket").filter((F.abs(F.col("t") - F.col("s")) <= F.lit(seconds * 1_000_000)) & (F.col("u") != F.col("v")))
    once = both.filter((F.col("home") < F.col("bucket")) | (F.col("u") < F.col("v")))
    return once.groupBy(F.least("u", "v").alias("src"), F.greatest("u", "v").alias("dst")).agg(F.count("*").alias("contacts"))
