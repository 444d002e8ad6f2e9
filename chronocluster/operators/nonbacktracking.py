"""The temporal non-backtracking operator in message form.

The state of a temporal node is (gs, hs, gt, ht): what reaches it over spatial edges, what it sends
over them, and the same for temporal edges.  With z = gs + gt, one step is
gs' = lam (A_s z - hs), hs' = lam (d_s z - gs), gt' = eta (A_t z - ht), ht' = eta (d_t z - gt):
one join and one aggregation with two sums, although the operator is four times as wide.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..supra import SupraGraph
from ..tracking import persistence
from .base import LinearOperator


class NonBacktracking(LinearOperator):
    """time='both' lets messages run both ways along time, 'forward' only to later slices; edges count once, whatever their weight."""

    symmetric = False
    PARTS = ("gs", "hs", "gt", "ht")

    def __init__(self, supra: SupraGraph, lam: float, eta: float, time: str = "both"):
        if time not in ("both", "forward"):
            raise ValueError(time)
        self.lam, self.eta = float(lam), float(eta)
        edges = supra.edges.select("a", "b", "kind")
        self.edges = edges if time == "both" else edges.filter("kind = 's' or b < a")
        per = self.edges.groupBy(F.col("a").alias("sid")).agg(F.count(F.when(F.col("kind") == "s", 1)).cast("double").alias("ds"), F.count(F.when(F.col("kind") == "t", 1)).cast("double").alias("dt"))
        self.nodes = supra.nodes.select("sid").join(per, "sid", "left").select("sid", F.coalesce("ds", F.lit(0.0)).alias("ds"), F.coalesce("dt", F.lit(0.0)).alias("dt"))

    def apply(self, block: DataFrame) -> DataFrame:
        """block: sid, gs, hs, gt, ht."""
        far = block.select(F.col("sid").alias("b"), (F.col("gs") + F.col("gt")).alias("z"))
        heard = self.edges.join(far, "b").groupBy(F.col("a").alias("sid")).agg(F.sum(F.when(F.col("kind") == "s", F.col("z")).otherwise(0.0)).alias("s"), F.sum(F.when(F.col("kind") == "t", F.col("z")).otherwise(0.0)).alias("t"))
        zero = F.lit(0.0)
        x = self.nodes.join(block, "sid").join(heard, "sid", "left").withColumns({"s": F.coalesce("s", zero), "t": F.coalesce("t", zero), "z": F.col("gs") + F.col("gt")})
        return x.select(
            "sid",
            (self.lam * (F.col("s") - F.col("hs"))).alias("gs"),
            (self.lam * (F.col("ds") * F.col("z") - F.col("gs"))).alias("hs"),
            (self.eta * (F.col("t") - F.col("ht"))).alias("gt"),
            (self.eta * (F.col("dt") * F.col("z") - F.col("gt"))).alias("ht"),
        )

    def bounds(self) -> tuple[float, float]:
        top = self.nodes.agg(F.max(F.col("ds") * abs(self.lam) + F.col("dt") * abs(self.eta))).first()[0] or 0.0
        return -top, top


def estimate_affinity(edges: DataFrame, labels: DataFrame) -> float:
    """lam from a labelling: pairs of a slice drawn at random meet at rates c_in within and c_out between classes."""
    k = labels.agg(F.countDistinct("community")).first()[0]
    a, b = labels.select("slice", F.col("node").alias("src"), F.col("community").alias("ca")), labels.select("slice", F.col("node").alias("dst"), F.col("community").alias("cb"))
    e = edges.join(a, ["slice", "src"]).join(b, ["slice", "dst"]).groupBy("slice").agg(F.count("*").alias("m"), F.count(F.when(F.col("ca") == F.col("cb"), 1)).alias("inside"))
    sizes = labels.groupBy("slice", "community").agg(F.count("*").alias("n"))
    pairs = sizes.groupBy("slice").agg(F.sum("n").alias("n"), F.sum(F.col("n") * (F.col("n") - 1) / 2).alias("p_in"))
    m, inside, n, p_in, p_all = e.join(pairs, "slice").agg(F.sum("m"), F.sum("inside"), F.avg("n"), F.sum("p_in"), F.sum(F.col("n") * (F.col("n") - 1) / 2)).first()
    c = 2 * m / (p_all * 2 / (n - 1)) if p_all else 0.0
    c_in, c_out = n * inside / p_in if p_in else 0.0, n * (m - inside) / (p_all - p_in) if p_all > p_in else 0.0
    return (c_in - c_out) / (k * c) if c else 0.0


def estimate_eta(labels: DataFrame) -> float:
    """The share of nodes whose label is that of the slice before."""
    n, kept = persistence(labels).agg(F.sum("n"), F.sum("kept")).first()
    return kept / n if n else 1.0
