"""Modularity matrices: sparse parts as joins, null models as sums that are broadcast back."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..supra import SupraGraph, sid, strengths
from ..temporal import TemporalGraph
from .base import LinearOperator, columns_of, spmv


class ModularityOp(LinearOperator):
    """A x - gamma d_out (d_in . x) / 2m of a static graph (a, b, weight; both orientations unless directed).

    symmetrise=True takes the mean of a directed operator and its transpose.
    """

    def __init__(self, edges: DataFrame, nodes: DataFrame, gamma: float = 1.0, directed: bool = False, symmetrise: bool = False):
        self.gamma, self.symmetric = gamma, not directed or symmetrise
        both = edges.select("a", "b", "weight")
        self.factor = 2.0 if directed else 1.0
        if directed and symmetrise:
            both = both.union(both.select("b", "a", "weight")).select("a", "b", (F.col("weight") / 2).alias("weight"))
        self.edges, self.mean = both, directed and symmetrise
        out = edges.groupBy(F.col("a").alias("sid")).agg(F.sum("weight").alias("k_out"))
        into = edges.groupBy(F.col("b").alias("sid")).agg(F.sum("weight").alias("k_in"))
        zero = F.lit(0.0)
        self.nodes = nodes.select("sid").join(out, "sid", "left").join(into, "sid", "left").select("sid", F.coalesce("k_out", zero).alias("k_out"), F.coalesce("k_in", zero).alias("k_in"))

    def apply(self, block: DataFrame) -> DataFrame:
        cs = columns_of(block)
        here = self.nodes.join(block, "sid")
        sums = [F.sum(F.col("k_in") * F.col(c)).alias(f"i{c}") for c in cs] + [F.sum(F.col("k_out") * F.col(c)).alias(f"o{c}") for c in cs]
        null = F.broadcast(here.agg((F.sum("k_out") * self.factor).alias("two_m"), *sums))
        product = spmv(self.edges, block).withColumnsRenamed({c: f"p{c}" for c in cs})
        whole = here.join(product, "sid", "left").crossJoin(null)

        def expected(c: str):
            one = F.col("k_out") * F.col(f"i{c}")
            return F.try_divide((one + F.col("k_in") * F.col(f"o{c}")) / 2 if self.mean else one, F.col("two_m"))

        return whole.select("sid", *((F.coalesce(f"p{c}", F.lit(0.0)) - F.lit(float(self.gamma)) * F.coalesce(expected(c), F.lit(0.0))).alias(c) for c in cs))

    def bounds(self) -> tuple[float, float]:
        top = self.nodes.agg(F.max(F.greatest("k_out", "k_in"))).first()[0] or 0.0
        return -(1 + abs(self.gamma)) * top, top


class MultisliceModularityOp(LinearOperator):
    """Per-slice modularity matrices on the diagonal and couplings beside it; gamma may be a frame (slice, gamma)."""

    def __init__(self, tg: TemporalGraph, supra: SupraGraph, gamma: float | DataFrame = 1.0):
        if supra.directed:
            raise ValueError("the multislice matrix is symmetric for undirected graphs only")
        self.edges = supra.edges
        k = strengths(tg.edges).select(sid(F.col("slice"), F.col("node")).alias("sid"), F.col("k_out").alias("k"))
        nodes = supra.nodes.select("sid", "slice").join(k, "sid", "left").withColumn("k", F.coalesce("k", F.lit(0.0)))
        self.nodes = nodes.join(F.broadcast(gamma), "slice") if isinstance(gamma, DataFrame) else nodes.withColumn("gamma", F.lit(float(gamma)))

    def apply(self, block: DataFrame) -> DataFrame:
        cs = columns_of(block)
        here = self.nodes.join(block, "sid")
        null = here.groupBy("slice").agg(F.sum("k").alias("two_m"), *(F.sum(F.col("k") * F.col(c)).alias(f"t{c}") for c in cs))
        product = spmv(self.edges, block).withColumnsRenamed({c: f"p{c}" for c in cs})
        whole = here.join(product, "sid", "left").join(F.broadcast(null), "slice")
        expected = lambda c: F.coalesce(F.try_divide(F.col("gamma") * F.col("k") * F.col(f"t{c}"), F.col("two_m")), F.lit(0.0))
        return whole.select("sid", *((F.coalesce(f"p{c}", F.lit(0.0)) - expected(c)).alias(c) for c in cs))

    def bounds(self) -> tuple[float, float]:
        d = self.edges.groupBy("a").agg(F.sum("weight").alias("d")).agg(F.max("d")).first()[0] or 0.0
        g = self.nodes.agg(F.max(F.abs("gamma"))).first()[0] or 0.0
        return -(1 + g) * d, d
