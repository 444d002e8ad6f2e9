"""Quality of a labelling.  Every measure is one pass over edges and one over strengths; no pair of nodes is formed."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .complete import sums as complete_sums
from .supra import SupraGraph, couple, degrees, strengths
from .temporal import TemporalGraph


def _ends(edges: DataFrame, labels: DataFrame, by: list[str]) -> DataFrame:
    """Edges with the communities ca and cb of their ends; labels join on by and the node."""
    left = labels.select(*by, F.col("node").alias("src"), F.col("community").alias("ca"))
    right = labels.select(*by, F.col("node").alias("dst"), F.col("community").alias("cb"))
    return edges.join(left, [*by, "src"]).join(right, [*by, "dst"])


def modularity(edges: DataFrame, labels: DataFrame, gamma: float = 1.0, directed: bool = False, convention: str = "literal") -> DataFrame:
    """One row q for a static graph; labels (node, community).

    For a directed graph the literal form divides by twice the total weight, convention='directed' by the weight.
    """
    inside = _ends(edges, labels, []).groupBy(F.col("ca").alias("community")).agg(F.sum(F.when(F.col("ca") == F.col("cb"), F.col("weight")).otherwise(0.0)).alias("w"))
    k = strengths(edges, directed).groupBy("node").agg(F.sum("k_out").alias("k_out"), F.sum("k_in").alias("k_in"))
    volumes = k.join(labels, "node").groupBy("community").agg(F.sum("k_out").alias("k_out"), F.sum("k_in").alias("k_in"))
    total = F.broadcast(edges.agg(F.sum("weight").alias("m")))
    norm = F.col("m") if directed and convention == "directed" else 2 * F.col("m")
    share = F.col("w") if directed else 2 * F.col("w")
    per = volumes.join(inside, "community", "left").withColumn("w", F.coalesce("w", F.lit(0.0))).crossJoin(total)
    return per.agg(F.sum(share / norm - F.lit(float(gamma)) * F.col("k_out") * F.col("k_in") / (norm * norm)).alias("q"))


def multislice_modularity(tg: TemporalGraph, labels: DataFrame, gamma: float | DataFrame = 1.0, omega: float | DataFrame = 1.0, topology: str = "adjacent") -> DataFrame:
    """One row: q_ms, two_mu.  gamma may be a frame (slice, gamma), omega one (slice_a, slice_b, omega); slices without edges add nothing.

    For a directed graph a slice's null is that of out- and in-strengths over its weight, and its weight counts once.
    """
    both = 1 if tg.directed else 2
    if tg.complete:
        inside, squares, totals = complete_sums(tg, labels)
    else:
        inside = _ends(tg.edges, labels, ["slice"]).filter("ca = cb").groupBy("slice").agg(F.sum("weight").alias("w"))
        k = strengths(tg.edges, tg.directed).join(labels, ["slice", "node"]).groupBy("slice", "community").agg(F.sum("k_out").alias("k"), F.sum("k_in").alias("k_in"))
        squares = k.groupBy("slice").agg(F.sum(F.col("k") * F.col("k_in")).alias("kk"))
        totals = tg.edges.groupBy("slice").agg((both * F.sum("weight")).alias("two_m"))
    per = totals.join(squares, "slice").join(inside, "slice", "left")
    per = per.join(F.broadcast(gamma), "slice") if isinstance(gamma, DataFrame) else per.withColumn("gamma", F.lit(float(gamma)))
    within = per.agg(F.sum(both * F.coalesce("w", F.lit(0.0)) - F.col("gamma") * F.try_divide("kk", "two_m")).alias("within"), F.sum("two_m").alias("sum_m"))
    ties = couple(tg.nodes, omega, topology)
    at = lambda side: labels.select(F.col("slice").alias(f"slice_{side}"), "node", F.col("community").alias(f"c{side}"))
    tied = ties.join(at("a"), ["slice_a", "node"]).join(at("b"), ["slice_b", "node"])
    between = tied.agg((2 * F.coalesce(F.sum(F.when(F.col("ca") == F.col("cb"), F.col("weight")).otherwise(0.0)), F.lit(0.0))).alias("kept"), (2 * F.coalesce(F.sum("weight"), F.lit(0.0))).alias("ties"))
    mu = F.col("sum_m") + F.col("ties")
    return within.crossJoin(between).select(F.try_divide(F.col("within") + F.col("kept"), mu).alias("q_ms"), mu.alias("two_mu"))


def supra_labels(labels: DataFrame, supra: SupraGraph) -> DataFrame:
    """sid, slice, node, community."""
    return supra.nodes.join(labels, ["slice", "node"])


def supra_modularity(supra: SupraGraph, labels: DataFrame, gamma: float = 1.0) -> DataFrame:
    """One row q: modularity of the supra-graph against one global null."""
    own = supra_labels(labels, supra).select(F.col("sid").alias("node"), "community")
    upper = supra.edges.filter("a < b").select(F.lit(0).alias("slice"), F.col("a").alias("src"), F.col("b").alias("dst"), "weight")
    return modularity(upper, own, gamma)


def community_cuts(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """community, size, volume, inside (twice the inner weight), cut; of a static undirected graph."""
    ends = _ends(edges, labels, [])
    both = ends.select("ca", "cb", "weight").union(ends.select("cb", "ca", "weight"))
    per = both.groupBy(F.col("ca").alias("community")).agg(
        F.sum("weight").alias("volume"), F.sum(F.when(F.col("ca") == F.col("cb"), F.col("weight")).otherwise(0.0)).alias("inside"), F.sum(F.when(F.col("ca") != F.col("cb"), F.col("weight")).otherwise(0.0)).alias("cut")
    )
    sizes = labels.groupBy("community").agg(F.count("*").alias("size"))
    zero = F.lit(0.0)
    return sizes.join(per, "community", "left").select("community", "size", F.coalesce("volume", zero).alias("volume"), F.coalesce("inside", zero).alias("inside"), F.coalesce("cut", zero).alias("cut"))


def ncut(edges: DataFrame, labels: DataFrame) -> DataFrame:
    return community_cuts(edges, labels).agg(F.sum(F.coalesce(F.try_divide("cut", "volume"), F.lit(0.0))).alias("ncut"))


def rcut(edges: DataFrame, labels: DataFrame) -> DataFrame:
    return community_cuts(edges, labels).agg(F.sum(F.col("cut") / F.col("size")).alias("rcut"))


def conductance(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """community, conductance: cut over the smaller of both volumes; null where that is 0."""
    cuts = community_cuts(edges, labels)
    total = cuts.agg(F.sum("volume").alias("all"))
    return cuts.crossJoin(F.broadcast(total)).select("community", F.try_divide("cut", F.least("volume", F.col("all") - F.col("volume"))).alias("conductance"))


def cpm(edges: DataFrame, labels: DataFrame, gamma: float = 1.0) -> DataFrame:
    """One row: inner weight less gamma times inner pairs."""
    return community_cuts(edges, labels).agg(F.sum(F.col("inside") / 2 - F.lit(float(gamma)) * F.col("size") * (F.col("size") - 1) / 2).alias("cpm"))


def multislice_cpm(tg: TemporalGraph, labels: DataFrame, gamma: float = 1.0, omega: float = 1.0, topology: str = "adjacent") -> DataFrame:
    """One row: inner weight of all slices less gamma times inner pairs of each slice, plus kept couplings."""
    inside = _ends(tg.edges, labels, ["slice"]).filter("ca = cb").agg(F.coalesce(F.sum("weight"), F.lit(0.0)).alias("w"))
    n = F.col("n")
    pairs = tg.nodes.join(labels, ["slice", "node"]).groupBy("slice", "community").agg(F.count("*").alias("n")).agg(F.sum(n * (n - 1) / 2).alias("pairs"))
    at = lambda side: labels.select(F.col("slice").alias(f"slice_{side}"), "node", F.col("community").alias(f"c{side}"))
    kept = couple(tg.nodes, omega, topology).join(at("a"), ["slice_a", "node"]).join(at("b"), ["slice_b", "node"]).filter("ca = cb").agg(F.coalesce(F.sum("weight"), F.lit(0.0)).alias("kept"))
    return inside.crossJoin(pairs).crossJoin(kept).select((F.col("w") - F.lit(float(gamma)) * F.col("pairs") + F.col("kept")).alias("cpm"))


def _entropy_term(x: Column, y: Column) -> Column:
    return F.when(x > 0, x * F.ln(F.try_divide(x, y))).otherwise(0.0)


def surprise(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """One row: total weight times the divergence of the inner share of weight from the inner share of pairs."""
    c = community_cuts(edges, labels).agg(F.sum(F.col("inside") / 2).alias("w"), F.sum(F.col("volume") / 2).alias("m"), F.sum(F.col("size") * (F.col("size") - 1) / 2).alias("p"), F.sum("size").alias("n"))
    x, y = F.col("w") / F.col("m"), F.col("p") / (F.col("n") * (F.col("n") - 1) / 2)
    return c.select((F.col("m") * (_entropy_term(x, y) + _entropy_term(1 - x, 1 - y))).alias("surprise"))


def resolution_limit(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """community, links (its inner weight), scale (root of twice the total weight), below."""
    scale = F.broadcast(edges.agg(F.sqrt(2 * F.sum("weight")).alias("scale")))
    return community_cuts(edges, labels).crossJoin(scale).select("community", (F.col("inside") / 2).alias("links"), "scale", (F.col("inside") / 2 < F.col("scale")).alias("below"))


def slice_modularity(edges: DataFrame, labels: DataFrame, gamma: float = 1.0) -> DataFrame:
    """slice, q: modularity of every snapshot on its own."""
    inside = _ends(edges, labels, ["slice"]).filter("ca = cb").groupBy("slice").agg(F.sum("weight").alias("w"))
    k = strengths(edges).join(labels, ["slice", "node"]).groupBy("slice", "community").agg(F.sum("k_out").alias("k"))
    squares = k.groupBy("slice").agg(F.sum(F.col("k") * F.col("k")).alias("kk"))
    totals = edges.groupBy("slice").agg((2 * F.sum("weight")).alias("two_m"))
    two_m = F.col("two_m")
    return totals.join(squares, "slice").join(inside, "slice", "left").select("slice", (2 * F.coalesce("w", F.lit(0.0)) / two_m - F.lit(float(gamma)) * F.col("kk") / (two_m * two_m)).alias("q"))


def time_degenerate(labels: DataFrame, share: float = 0.9) -> DataFrame:
    """One row: communities, those in one slice only, and whether these are most (a labelling by time, not by structure)."""
    per = labels.groupBy("community").agg(F.countDistinct("slice").alias("t"))
    slices = labels.agg(F.countDistinct("slice").alias("slices"))
    one = per.agg(F.count("*").alias("communities"), F.count(F.when(F.col("t") == 1, 1)).alias("in_one"))
    return one.crossJoin(slices).select("communities", "in_one", ((F.col("slices") > 1) & (F.col("in_one") >= share * F.col("communities"))).alias("degenerate_time"))


def supra_ncut(supra: SupraGraph, labels: DataFrame) -> DataFrame:
    own = supra_labels(labels, supra).select(F.col("sid").alias("node"), "community")
    return ncut(supra.edges.filter("a < b").select(F.lit(0).alias("slice"), F.col("a").alias("src"), F.col("b").alias("dst"), "weight"), own)


def mean_degree(supra: SupraGraph) -> DataFrame:
    """One row: c, the mean strength, and d2, the mean of its square."""
    return degrees(supra).agg(F.avg("d").alias("c"), F.avg(F.col("d") * F.col("d")).alias("d2"))
