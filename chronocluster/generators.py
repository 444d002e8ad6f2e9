"""Dynamic planted partitions from integer hashes: the same rows on every engine and partitioning."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .sources.tables import load


@dataclass(frozen=True)
class PlantedPartition:
    """n nodes, k classes, slices, mean degree c, affinity lam = (c_in - c_out) / (k c), and eta, the chance that a node keeps its class."""

    n: int
    k: int = 10
    slices: int = 5
    c: float = 10.0
    lam: float = 0.6
    eta: float = 0.95
    seed: int = 1

    @property
    def c_in(self) -> float:
        return self.c * (1 + (self.k - 1) * self.lam)

    @property
    def c_out(self) -> float:
        return self.c * (1 - self.lam)

    @property
    def candidates(self) -> int:
        """Pairs drawn per slice, of which c / max(c_in, c_out) are taken."""
        return int(self.n * max(self.c_in, self.c_out) / 2)


def preset(name: str, n: int = 50_000, **other) -> PlantedPartition:
    """base, or with twice the nodes, edges or snapshots."""
    shapes = {"base": {}, "nodes": {"n": 2 * n}, "edges": {"c": 20.0}, "snapshots": {"slices": 10}}
    return PlantedPartition(**{"n": n, **shapes[name], **other})


def _part(h: Column, i: int) -> Column:
    return F.conv(F.substring(h, 1 + 8 * i, 8), 16, 10).cast("bigint")


def planted_labels(spark: SparkSession, p: PlantedPartition) -> DataFrame:
    """slice, node, label."""
    return _drawn_labels(spark.range(p.n).select(F.col("id").alias("node")), p)


def _drawn_labels(nodes: DataFrame, p: PlantedPartition) -> DataFrame:
    cells = nodes.select("node", F.explode(F.sequence(F.lit(0), F.lit(p.slices - 1))).alias("slice"))
    h = F.md5(F.concat_ws(":", F.lit("label"), F.lit(p.seed), "slice", "node").cast("binary"))
    drawn = cells.withColumn("h", h).select("slice", "node", F.when(F.col("slice") == 0, F.col("node") % p.k).when(_part(F.col("h"), 0) >= int(p.eta * 2**32), _part(F.col("h"), 1) % p.k).alias("new"))
    w = Window.partitionBy("node").orderBy("slice").rowsBetween(Window.unboundedPreceding, 0)
    return drawn.select("slice", "node", F.last("new", ignorenulls=True).over(w).alias("label"))


def planted_edges(spark: SparkSession, p: PlantedPartition) -> DataFrame:
    """slice, src, dst, weight."""
    pairs = spark.range(p.candidates * p.slices).select((F.col("id") % p.slices).cast("int").alias("slice"), F.floor(F.col("id") / p.slices).alias("j"))
    return _drawn_edges(pairs, planted_labels(spark, p), p, F.lit(p.n))


def _drawn_edges(pairs: DataFrame, labels: DataFrame, p: PlantedPartition, n: Column, counted: bool = False) -> DataFrame:
    """Draws (slice, j) that the classes of their two nodes let pass; n is one more than the largest node.

    counted: the weight of a pair is the number of its draws, not 1.
    """
    h = F.md5(F.concat_ws(":", F.lit("edge"), F.lit(p.seed), "slice", "j").cast("binary"))
    # Filters do not pass an explode, so a draw is worked out once and not again by each of them.
    drawn = pairs.select(*(c for c in pairs.columns if c != "j"), F.explode(F.array(h)).alias("h"))
    ends = drawn.select("slice", F.inline(F.array(F.struct((_part(F.col("h"), 0) % n).alias("u"), (_part(F.col("h"), 1) % n).alias("v"), _part(F.col("h"), 2).alias("r")))))
    a = labels.select("slice", F.col("node").alias("u"), F.col("label").alias("lu"))
    b = labels.select("slice", F.col("node").alias("v"), F.col("label").alias("lv"))
    top = max(p.c_in, p.c_out)
    limit = F.when(F.col("lu") == F.col("lv"), F.lit(int(p.c_in / top * 2**32))).otherwise(F.lit(int(p.c_out / top * 2**32)))
    kept = ends.filter("u <> v").join(a, ["slice", "u"]).join(b, ["slice", "v"]).filter(F.col("r") < limit)
    pairs = kept.select("slice", F.least("u", "v").alias("src"), F.greatest("u", "v").alias("dst"), F.lit(1.0).alias("weight"))
    return pairs.groupBy("slice", "src", "dst").agg(F.count("*").cast("double").alias("weight")) if counted else pairs.distinct()


@dataclass(frozen=True)
class PlantedTable:
    """A planted partition on given tables: customers are the nodes, each order line draws pairs.

    A customer has so many copies as nodes, a line so many draws; mean degrees follow from the number of lines.
    Of p the number of nodes and the mean degree are not used.  Draws that meet no customer are dropped.
    With cells the customers are dealt to so many nodes, and a pair's weight is the number of its draws: the
    graph keeps its size and grows in weight.
    """

    p: PlantedPartition
    copies: int = 1
    draws: int = 1
    cells: int | None = None

    def labels(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        """slice, node, label."""
        return _drawn_labels(self._nodes(spark, sf_dir), self.p)

    def edges(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        """slice, src, dst, weight."""
        nodes = self._nodes(spark, sf_dir)
        line = F.col("l_orderkey") * 8 + F.col("l_linenumber")
        at = load(spark, sf_dir, "lineitem").select(F.explode(F.sequence(line * self.draws, line * self.draws + (self.draws - 1))).alias("id"))
        pairs = at.select(F.pmod("id", F.lit(self.p.slices)).cast("int").alias("slice"), F.floor(F.col("id") / self.p.slices).alias("j"))
        n = F.broadcast(nodes.agg((F.max("node") + 1).alias("n")))
        # Spark takes exploded rows for as small as their table and would gather all labels on the driver.
        labels = _drawn_labels(nodes, self.p).hint("broadcast" if self.cells else "shuffle_hash")
        return _drawn_edges(pairs.crossJoin(n), labels, self.p, F.col("n"), bool(self.cells))

    def _nodes(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        if self.cells:
            return load(spark, sf_dir, "customer").select(F.pmod("c_custkey", F.lit(self.cells)).cast("bigint").alias("node")).distinct()
        first = F.col("c_custkey") * self.copies
        return load(spark, sf_dir, "customer").select(F.explode(F.sequence(first, first + (self.copies - 1))).alias("node"))

    @property
    def labels_sql(self) -> str:
        return labels_sql(self.p, self._nodes_sql)

    @property
    def edges_sql(self) -> str:
        ids = f"(SELECT (l_orderkey * 8 + l_linenumber) * {self.draws} + d.range AS range FROM lineitem, range({self.draws}) d)"
        return edges_sql(self.p, self._nodes_sql, ids, bool(self.cells))

    @property
    def _nodes_sql(self) -> str:
        if self.cells:
            return f"(SELECT DISTINCT c_custkey % {self.cells} AS range FROM customer)"
        return f"(SELECT c_custkey * {self.copies} + c.range AS range FROM customer, range({self.copies}) c)"


def labels_sql(p: PlantedPartition, nodes: str | None = None) -> str:
    """nodes: a relation of the nodes (range), else 0 to n - 1."""
    part = lambda i: f"('0x' || substr(h, {1 + 8 * i}, 8))::BIGINT"
    return f"""(SELECT slice, node, last_value(new IGNORE NULLS) OVER (PARTITION BY node ORDER BY slice ROWS UNBOUNDED PRECEDING) AS label FROM (
      SELECT slice, node, CASE WHEN slice = 0 THEN node % {p.k} WHEN {part(0)} >= {int(p.eta * 2**32)} THEN {part(1)} % {p.k} END AS new FROM (
        SELECT s.range::INT AS slice, n.range AS node, md5('label:{p.seed}:' || s.range || ':' || n.range) AS h FROM {nodes or f"range({p.n})"} n, range({p.slices}) s)))"""


def edges_sql(p: PlantedPartition, nodes: str | None = None, draws: str | None = None, counted: bool = False) -> str:
    """nodes and draws: relations of both (range), else counted from 0; counted: draws of a pair are its weight."""
    n = f"(SELECT max(range) + 1 FROM {nodes})" if nodes else p.n
    part = lambda i: f"('0x' || substr(h, {1 + 8 * i}, 8))::BIGINT"
    top = max(p.c_in, p.c_out)
    return f"""(WITH planted AS (SELECT * FROM {labels_sql(p, nodes)}),
      drawn AS (SELECT slice, {part(0)} % {n} AS u, {part(1)} % {n} AS v, {part(2)} AS r FROM (
        SELECT (range % {p.slices})::INT AS slice, md5('edge:{p.seed}:' || (range % {p.slices}) || ':' || (range // {p.slices})) AS h FROM {draws or f"range({p.candidates * p.slices})"}))
      SELECT {"" if counted else "DISTINCT "}d.slice, least(u, v) AS src, greatest(u, v) AS dst, {"count(*)" if counted else "1.0"}::DOUBLE AS weight
      FROM drawn d JOIN planted a ON a.slice = d.slice AND a.node = d.u JOIN planted b ON b.slice = d.slice AND b.node = d.v
      WHERE u <> v AND r < CASE WHEN a.label = b.label THEN {int(p.c_in / top * 2**32)} ELSE {int(p.c_out / top * 2**32)} END{" GROUP BY ALL" if counted else ""})"""
