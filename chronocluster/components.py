"""Connected components by falling labels with shortcuts."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .session import cut, ship
from .temporal import active_nodes

#: Edges that a task gathers before it keeps only which nodes hang together; and rows of (node, root) that one task may merge.
GATHERED, MERGED = 2_000_000, 40_000_000


def roots(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The nodes of edges (a, b) in order, and the smallest node that each hangs together with."""
    ids, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    a, b = at[: len(a)], at[len(a) :]
    low = np.arange(len(ids))
    while len(a):
        la, lb = low[a], low[b]
        apart = la != lb
        a, b = a[apart], b[apart]
        np.minimum.at(low, np.maximum(la, lb)[apart], np.minimum(la, lb)[apart])
        while not (low[low] == low).all():
            low = low[low]
    return ids, ids[low]


def _rooted(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(node, root) of all edges in batches (a, b); what is held at a time grows with the nodes, not with the edges."""
    held: list[tuple[np.ndarray, np.ndarray]] = []
    size, least = 0, GATHERED
    for batch in batches:
        held.append((batch.column(0).to_numpy(zero_copy_only=False), batch.column(1).to_numpy(zero_copy_only=False)))
        size += batch.num_rows
        if size >= least:
            held = [roots(*(np.concatenate(x) for x in zip(*held, strict=True)))]
            size = len(held[0][0])
            least = 2 * size + GATHERED
    if held:
        ids, root = roots(*(np.concatenate(x) for x in zip(*held, strict=True)))
        for at in range(0, len(ids), 100_000):
            yield pa.RecordBatch.from_arrays([pa.array(ids[at : at + 100_000]), pa.array(root[at : at + 100_000])], names=["node", "component"])


def rooted(edges: DataFrame) -> DataFrame:
    """node and component, as components(); each task first keeps what its own edges tell, and one task merges that."""
    ship(edges.sparkSession)
    per = cut(edges.select("src", "dst").mapInArrow(_rooted, "node bigint, component bigint"), "roots")
    if per.count() > MERGED:
        return components(per.toDF("src", "dst"), per.select("node"))
    return per.coalesce(1).mapInArrow(_rooted, "node bigint, component bigint")


def inner_parts(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """v, part of every vertex of labels (v, c): the smallest vertex that it hangs together with by edges (a, b) inside its community.

    All edges of a community meet in one task, which keeps its vertices only.
    """
    ship(edges.sparkSession)
    ends = edges.filter("a <> b").select("a", "b").join(labels.toDF("a", "c"), "a").join(labels.toDF("b", "cb"), "b").filter("c = cb")
    parts = ends.repartition(int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions")), "c").select("a", "b").mapInArrow(_rooted, "node bigint, component bigint")
    return labels.select("v").join(parts.toDF("v", "part"), "v", "left").select("v", F.coalesce("part", "v").alias("part"))


def components(edges: DataFrame, nodes: DataFrame | None = None, most_rounds: int = 60) -> DataFrame:
    """node and component (its smallest node) of an undirected graph (src, dst); nodes without an edge are their own.

    A label falls to the smallest label next to it and then to its label's label, so rounds grow with
    the logarithm of the longest path.  Each round costs two joins and is written to the shared folder.
    """
    pairs = edges.select("src", "dst").filter("src <> dst").distinct()
    both = cut(pairs.union(pairs.select("dst", "src")).toDF("u", "v"), "pairs")
    labels = cut(both.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("node"), F.least("u", "m").alias("component")), "labels")
    for _ in range(most_rounds):
        near = both.join(labels.withColumnsRenamed({"node": "v"}), "v").groupBy(F.col("u").alias("node")).agg(F.min("component").alias("near"))
        lower = labels.join(near, "node").select("node", "component", F.least("component", "near").alias("to"))
        up = labels.select(F.col("node").alias("to"), F.col("component").alias("top"))
        to = F.least("to", F.coalesce("top", "to"))
        after = cut(lower.join(up, "to", "left").select("node", to.alias("component"), (to < F.col("component")).alias("fell")), "labels")
        labels = after.select("node", "component")
        if after.filter("fell").isEmpty():
            break
    else:
        raise RuntimeError("the labels did not settle")
    if nodes is None:
        return labels
    return nodes.select("node").distinct().join(labels, "node", "left").select("node", F.coalesce("component", "node").alias("component"))


def largest_component(edges: DataFrame) -> DataFrame:
    """The edges within the component with the most nodes; ties go to the smallest id."""
    labels = components(edges)
    best = labels.groupBy("component").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "component").limit(1)
    inside = labels.join(F.broadcast(best), "component", "left_semi").select(F.col("node").alias("src"))
    return edges.join(inside, "src", "left_semi").select(edges.columns)


def check_connected(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """One row: communities, and how many of them do not hang together; edges (a, b), labels (sid, community)."""
    parts = inner_parts(edges, labels.select(F.col("sid").alias("v"), F.col("community").alias("c")))
    per = labels.join(parts, F.col("sid") == F.col("v")).filter(F.col("part") == F.col("v")).groupBy("community").agg(F.count("*").alias("parts"))
    return per.agg(F.count("*").alias("communities"), F.count(F.when(F.col("parts") > 1, 1)).alias("broken"))


def isolated_nodes(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    return nodes.join(active_nodes(edges), ["slice", "node"], "left_anti")
