"""The supra-graph: snapshots as diagonal blocks, couplings of a node's copies beside them."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .session import ship
from .temporal import TemporalGraph, active_nodes, presence

#: Temporal node (slice, node) is numbered slice * STRIDE + node.
STRIDE = 1 << 40
#: More node-slice cells than this are refused for presence='all'.
MOST_CELLS = 10_000_000_000
#: Relative standard deviation of approximate counts, a fifth of the 5 % that these keep within.
APPROX_SD = 0.01
#: Nodes of a block on average where pairs are counted as bits; two blocks take a bit for each pair of theirs, 32 MB.
PAIR_BLOCK = 16_384
#: Nodes of a slice that travel in one row; bounds a batch of rows in a Python worker.
PAIR_PIECE = 256


def sid(slice_: Column, node: Column) -> Column:
    return slice_.cast("bigint") * F.lit(STRIDE) + node


def decode(df: DataFrame, column: str = "sid") -> DataFrame:
    """Split a temporal-node number into slice and node."""
    return df.withColumns({"slice": F.floor(F.col(column) / F.lit(STRIDE)).cast("int"), "node": F.pmod(F.col(column), F.lit(STRIDE))})


@dataclass(frozen=True)
class SupraGraph:
    """nodes (sid, slice, node) and edges (a, b, weight, kind: s within, t between slices), both orientations."""

    nodes: DataFrame
    edges: DataFrame
    directed: bool = False


def auto_omega(edges: DataFrame) -> float:
    """Half the mean strength of a node in a slice."""
    ends = edges.select("slice", F.explode(F.array("src", "dst")).alias("node"), "weight").groupBy("slice", "node").agg(F.sum("weight").alias("k"))
    return float((ends.agg(F.avg("k")).first()[0] or 0.0) / 2)


def constant_omega(spark: SparkSession, slices: list[int], omega: float) -> DataFrame:
    rows = [(s, r, omega) for s in slices for r in slices if s != r]
    return spark.createDataFrame(rows, "slice_a int, slice_b int, omega double")


def couple(nodes: DataFrame, omega: float | DataFrame = 1.0, topology: str = "adjacent") -> DataFrame:
    """Coupling rows (slice_a, slice_b, node, weight) with slice_a < slice_b.

    adjacent: copies in neighbouring slices; next_seen: a node's consecutive appearances;
    all: every pair of copies; table: omega is a frame (slice_a, slice_b, omega) of any pairs.
    """
    if topology in ("adjacent", "next_seen"):
        ahead = F.lead("slice").over(Window.partitionBy("node").orderBy("slice"))
        pairs = nodes.select(F.col("slice").alias("slice_a"), ahead.alias("slice_b"), "node").filter("slice_b is not null")
        pairs = pairs.filter("slice_b = slice_a + 1") if topology == "adjacent" else pairs
    else:
        later = nodes.select(F.col("slice").alias("slice_b"), "node")
        pairs = nodes.withColumnRenamed("slice", "slice_a").join(later, "node").filter("slice_a < slice_b").select("slice_a", "slice_b", "node")
    if isinstance(omega, DataFrame):
        return pairs.join(F.broadcast(omega), ["slice_a", "slice_b"]).select("slice_a", "slice_b", "node", F.col("omega").alias("weight")).filter("weight <> 0")
    return pairs.withColumn("weight", F.lit(float(omega)))


def supra_graph(tg: TemporalGraph, omega: float | str | DataFrame = 1.0, topology: str = "adjacent", policy: str = "active") -> SupraGraph:
    """Both orientations of every edge and coupling; nothing of size n x T is made unless policy is all."""
    if policy == "all":
        cells = tg.edges.agg(F.countDistinct("slice")).first()[0] * active_nodes(tg.edges).select("node").distinct().count()
        if cells > MOST_CELLS:
            raise ValueError(f"{cells} cells; use presence active or span")
    nodes = tg.nodes if policy == "active" else presence(tg.edges, policy)
    omega = auto_omega(tg.edges) if omega == "auto" else omega
    within = tg.edges.select(sid(F.col("slice"), F.col("src")).alias("a"), sid(F.col("slice"), F.col("dst")).alias("b"), "weight", F.lit("s").alias("kind"))
    ties = couple(nodes, omega, topology).select(sid(F.col("slice_a"), F.col("node")).alias("a"), sid(F.col("slice_b"), F.col("node")).alias("b"), "weight", F.lit("t").alias("kind"))
    upper = within.unionByName(ties)
    flip = upper if not tg.directed else ties
    mirrored = upper.unionByName(flip.filter("a <> b").select(F.col("b").alias("a"), F.col("a").alias("b"), "weight", "kind"))
    return SupraGraph(nodes.select(sid(F.col("slice"), F.col("node")).alias("sid"), "slice", "node"), mirrored, tg.directed)


def degrees(supra: SupraGraph) -> DataFrame:
    """sid, d_s and d_t (strengths within and between slices), d (their sum); nodes without an edge have 0."""
    per = supra.edges.groupBy(F.col("a").alias("sid")).agg(F.sum(F.when(F.col("kind") == "s", F.col("weight")).otherwise(0.0)).alias("d_s"), F.sum(F.when(F.col("kind") == "t", F.col("weight")).otherwise(0.0)).alias("d_t"))
    zero = F.lit(0.0)
    return supra.nodes.join(per, "sid", "left").select("sid", "slice", "node", F.coalesce("d_s", zero).alias("d_s"), F.coalesce("d_t", zero).alias("d_t"), (F.coalesce("d_s", zero) + F.coalesce("d_t", zero)).alias("d"))


def strengths(edges: DataFrame, directed: bool = False) -> DataFrame:
    """slice, node, k_out, k_in; equal for an undirected graph."""
    out = edges.select("slice", F.col("src").alias("node"), F.col("weight").alias("k_out"), F.lit(0.0).alias("k_in"))
    into = edges.select("slice", F.col("dst").alias("node"), F.lit(0.0).alias("k_out"), F.col("weight").alias("k_in"))
    both = out.union(into)
    if not directed:
        both = both.select("slice", "node", (F.col("k_out") + F.col("k_in")).alias("k_out"), (F.col("k_out") + F.col("k_in")).alias("k_in"))
    return both.groupBy("slice", "node").agg(F.sum("k_out").alias("k_out"), F.sum("k_in").alias("k_in"))


def slice_totals(edges: DataFrame) -> DataFrame:
    """slice, m (edges), w (total weight), two_m."""
    return edges.groupBy("slice").agg(F.count("*").alias("m"), F.sum("weight").alias("w"), (2 * F.sum("weight")).alias("two_m"))


def supra_size(supra: SupraGraph) -> DataFrame:
    """n temporal nodes, e edges, p couplings, and the entries of the non-backtracking operator."""
    e = supra.edges.agg(F.count(F.when(F.col("kind") == "s", 1)).alias("es"), F.count(F.when(F.col("kind") == "t", 1)).alias("et"))
    n = supra.nodes.agg(F.count("*").alias("nodes"))
    return n.crossJoin(e).select("nodes", (F.col("es") / 2).cast("bigint").alias("edges"), (F.col("et") / 2).cast("bigint").alias("couplings"), (2 * F.col("es") + 2 * F.col("et") + 6 * F.col("nodes")).alias("nb_entries"))


def dataset_properties(edges: DataFrame, labels: DataFrame | None = None, approx: bool = False) -> DataFrame:
    """One row: unique nodes and edges, their sums over time, slices, and classes if labels (node, label) are given.

    approx: unique nodes and edges by sketches, within 5 % (five standard deviations).
    """
    active = active_nodes(edges)
    slices = active.select("slice").distinct().agg(F.count("*").alias("t"))
    if approx:
        nodes = active.agg(F.approx_count_distinct("node", APPROX_SD).alias("v"), F.count("*").alias("v_sum"))
        pairs = edges.agg(F.approx_count_distinct(F.struct("src", "dst"), APPROX_SD).alias("e"), F.count("*").alias("e_sum"))
    else:  # two levels, so that no task holds a set
        nodes = active.groupBy("node").agg(F.count("*").alias("n")).agg(F.count("*").alias("v"), F.coalesce(F.sum("n"), F.lit(0)).alias("v_sum"))
        pairs = edges.groupBy("src", "dst").agg(F.count("*").alias("n")).agg(F.count("*").alias("e"), F.coalesce(F.sum("n"), F.lit(0)).alias("e_sum"))
    one = nodes.crossJoin(pairs).crossJoin(slices).select("v", "v_sum", "e", "e_sum", "t")
    if labels is None:
        return one.withColumn("c", F.lit(None).cast("bigint"))
    return one.crossJoin(labels.agg(F.countDistinct("label").alias("c")))


def distinct_pairs(active: DataFrame) -> DataFrame:
    """One row e: pairs of nodes that share a slice, where all nodes (slice, node) of a slice are linked.

    Nodes fall into blocks by hash and take places in these.  For each two blocks a task sets the bits of
    each slice in one matrix of bits, so pairs are counted once however many slices hold them, and only
    lists of places are moved.
    """
    import numpy as np

    ship(active.sparkSession)
    nodes = active.select("node").distinct()
    blocks = max(1, -(-nodes.count() // PAIR_BLOCK))
    within = Window.partitionBy("block")
    placed = nodes.withColumn("block", F.pmod(F.xxhash64("node"), F.lit(blocks)).cast("int")).withColumns({"place": F.row_number().over(within.orderBy("node")) - 1, "size": F.count("*").over(within)})
    cells = active.join(placed, "node").groupBy("slice", "block", "size", F.floor(F.col("place") / PAIR_PIECE).alias("piece")).agg(F.collect_list("place").alias("places"))
    sided = lambda to: cells.select(F.explode(to).alias("other"), F.col("block"), "size", "slice", "places")
    last = F.lit(blocks - 1)
    up = sided(F.sequence(F.col("block"), last)).select(F.col("block").alias("a"), F.col("other").alias("b"), "slice", F.lit(1).alias("row"), "size", "places")
    down = sided(F.sequence(F.lit(0), F.col("block"))).select(F.col("other").alias("a"), F.col("block").alias("b"), "slice", F.lit(0).alias("row"), "size", "places")
    dealt = up.unionByName(down).repartition("a", "b").sortWithinPartitions("a", "b", "slice", "row")

    def count(batches):
        import pyarrow as pa

        pair = slice_ = line = bits = None
        own = width = 0

        def total():
            n = int(np.bitwise_count(bits).sum(dtype=np.int64)) if bits is not None else 0
            return (n - own) // 2 if pair[0] == pair[1] else n

        for batch in batches:
            places = batch.column("places")
            flat, ends = places.flatten().to_numpy(), places.offsets.to_numpy() - places.offsets[0].as_py()
            sums = []
            for i, (a, b, s, row, size) in enumerate(zip(*(batch.column(c).to_pylist() for c in ("a", "b", "slice", "row", "size")), strict=True)):
                here = flat[ends[i] : ends[i + 1]]
                if (a, b) != pair:
                    if pair is not None:
                        sums.append(total())
                    pair, slice_, bits, width = (a, b), None, None, 0
                if not row:  # the columns of a slice come first
                    if s != slice_:
                        slice_, width, line = s, size, np.zeros(size, dtype=np.uint8)
                    line[here] = 1
                elif s == slice_:
                    if bits is None:
                        own, bits = size, np.zeros((size, -(-width // 8)), dtype=np.uint8)
                    bits[here] |= np.packbits(line)
            if sums:
                yield pa.RecordBatch.from_arrays([pa.array(sums, pa.int64())], names=["n"])
        if pair is not None:
            yield pa.RecordBatch.from_arrays([pa.array([total()], pa.int64())], names=["n"])

    return dealt.mapInArrow(count, "n bigint").agg(F.coalesce(F.sum("n"), F.lit(0)).cast("bigint").alias("e"))


def meeting_properties(active: DataFrame) -> DataFrame:
    """dataset_properties() of a graph that links all nodes (slice, node) of a slice, with no pair made."""
    per = active.groupBy("slice").agg(F.count("*").alias("n"))
    sums = per.agg(F.count("*").alias("t"), F.coalesce(F.sum("n"), F.lit(0)).alias("v_sum"), F.coalesce(F.sum(F.expr("n * (n - 1) div 2")), F.lit(0)).alias("e_sum"))
    nodes = active.select("node").distinct().agg(F.count("*").alias("v"))
    return nodes.crossJoin(sums).crossJoin(distinct_pairs(active)).select("v", "v_sum", "e", "e_sum", "t", F.lit(None).cast("bigint").alias("c"))
