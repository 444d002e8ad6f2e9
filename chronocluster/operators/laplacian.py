"""Laplacians and the deformed Laplacian of a supra-graph."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import cut, forget
from ..supra import SupraGraph
from .base import LinearOperator, diagonal_and_edges, row_sums, spmv


class Laplacian(LinearOperator):
    """unnormalised: D - A; symmetric: its both-sided scaling by D^-1/2; random_walk: its rows scaled by D^-1.

    A node without edges has the row 0.
    """

    def __init__(self, supra: SupraGraph, form: str = "symmetric"):
        if form not in ("unnormalised", "symmetric", "random_walk"):
            raise ValueError(form)
        self.form, self.symmetric = form, form != "random_walk"
        self.nodes = row_sums(supra.edges, supra.nodes.select("sid"))
        self.edges = supra.edges
        if form == "symmetric":
            d = self.nodes.select("sid", "d")
            scaled = supra.edges.join(d.toDF("a", "da"), "a").join(d.toDF("b", "db"), "b")
            self.edges = scaled.select("a", "b", (F.col("weight") / F.sqrt(F.col("da") * F.col("db"))).alias("weight"))

    def apply(self, block: DataFrame) -> DataFrame:
        if self.form == "unnormalised":
            return diagonal_and_edges(self.nodes, self.edges, block, F.col("d"), F.lit(-1.0))
        here = F.when(F.col("d") > 0, 1.0).otherwise(0.0)
        scale = F.lit(-1.0) if self.form == "symmetric" else F.coalesce(-F.try_divide(F.lit(1.0), F.col("d")), F.lit(0.0))
        return diagonal_and_edges(self.nodes, self.edges, block, here, scale)

    def bounds(self) -> tuple[float, float]:
        return (0.0, 2.0) if self.form != "unnormalised" else (0.0, 2 * (self.nodes.agg(F.max("d")).first()[0] or 0.0))


def choose_r(supra: SupraGraph, rule: str | float = "degree_ratio", degree: str = "supra") -> float:
    """The r of the deformed Laplacian: root of the mean degree, root of <d^2>/<d> - 1 (degree_ratio), root of the radius of the non-backtracking operator (nb_radius), or a number.

    degree='spatial' leaves couplings out.
    """
    if not isinstance(rule, str):
        return float(rule)
    edges = supra.edges if degree == "supra" else supra.edges.filter("kind = 's'")
    c, d2 = row_sums(edges, supra.nodes.select("sid")).agg(F.avg("d"), F.avg(F.col("d") * F.col("d"))).first()
    if rule == "sqrt_mean_degree":
        return float(c) ** 0.5
    if rule == "degree_ratio":
        return max(0.0, d2 / c - 1) ** 0.5 if c else 0.0
    if rule == "nb_radius":
        return nb_radius(edges, supra.nodes.select("sid")) ** 0.5
    raise ValueError(rule)


def nb_radius(edges: DataFrame, nodes: DataFrame, steps: int = 30, tol: float = 1e-4) -> float:
    """The largest eigenvalue of the non-backtracking operator, by power iteration on [[A, I - D], [I, 0]], which shares it."""
    held = cut(row_sums(edges, nodes), "nodes")
    state, value = cut(held.select("sid", "d", F.lit(1.0).alias("x"), F.lit(0.0).alias("y")), "vector"), 0.0
    for _ in range(steps):
        product = spmv(edges, state.select("sid", F.col("x").alias("c0")))
        after = cut(state.join(product, "sid", "left").select("sid", "d", (F.coalesce("c0", F.lit(0.0)) - (F.col("d") - 1) * F.col("y")).alias("x"), F.col("x").alias("y")), "vector")
        size, last = after.agg(F.sqrt(F.sum(F.col("x") * F.col("x"))), F.sqrt(F.sum(F.col("y") * F.col("y")))).first()
        forget(state)
        if not last or not size:
            return 0.0
        before, value = value, size / last
        state = after.select("sid", "d", (F.col("x") / size).alias("x"), (F.col("y") / size).alias("y"))
        if abs(value - before) <= tol * value:
            break
    return value


class DeformedLaplacian(LinearOperator):
    """(r^2 - 1) I - r A + D; r = 1 is the unnormalised Laplacian; assortative=False takes -r."""

    def __init__(self, supra: SupraGraph, r: float | str = "degree_ratio", degree: str = "supra", assortative: bool = True):
        self.r = choose_r(supra, r, degree) * (1 if assortative else -1)
        self.nodes = row_sums(supra.edges, supra.nodes.select("sid"))
        self.edges = supra.edges

    def apply(self, block: DataFrame) -> DataFrame:
        return diagonal_and_edges(self.nodes, self.edges, block, F.col("d") + F.lit(self.r**2 - 1), F.lit(-self.r))

    def bounds(self) -> tuple[float, float]:
        low, high = self.nodes.agg(F.min(F.col("d") * (1 - abs(self.r))), F.max(F.col("d") * (1 + abs(self.r)))).first()
        return min(low or 0.0, 0.0) + self.r**2 - 1, (high or 0.0) + self.r**2 - 1
