"""Blocks of vectors are frames (sid, c0, c1, ...): flat columns keep sums inside generated code."""

from __future__ import annotations

from abc import ABC, abstractmethod

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def columns_of(block: DataFrame) -> list[str]:
    return [c for c in block.columns if c[0] == "c" and c[1:].isdigit()]


def spmv(edges: DataFrame, block: DataFrame) -> DataFrame:
    """Adjacency times block: one join on the far end and one aggregation; rows without an edge are left out."""
    cs = columns_of(block)
    far = block.select(F.col("sid").alias("b"), *cs)
    return edges.select("a", "b", "weight").join(far, "b").groupBy(F.col("a").alias("sid")).agg(*(F.sum(F.col("weight") * F.col(c)).alias(c) for c in cs))


def random_block(nodes: DataFrame, width: int, seed: int = 1) -> DataFrame:
    """Normal deviates from hashes of (seed, column, sid): the same on any partitioning."""

    def unit(c: int, part: int) -> Column:
        return (F.pmod(F.xxhash64(F.lit(seed), F.lit(c), F.lit(part), "sid"), F.lit(1 << 52)) + 0.5) / float(1 << 52)

    normal = lambda c: F.sqrt(-2 * F.ln(unit(c, 0))) * F.cos(2 * F.pi() * unit(c, 1))
    return nodes.select("sid", *(normal(c).alias(f"c{c}") for c in range(width)))


class LinearOperator(ABC):
    """nodes (sid, ...) and apply(block); symmetric says whether Rayleigh-Ritz may take it as such."""

    symmetric = True
    nodes: DataFrame

    @abstractmethod
    def apply(self, block: DataFrame) -> DataFrame: ...

    @abstractmethod
    def bounds(self) -> tuple[float, float]:
        """An interval that holds every eigenvalue."""


def row_sums(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    """nodes with d, their strength over all edges."""
    d = edges.groupBy(F.col("a").alias("sid")).agg(F.sum("weight").alias("d"))
    return nodes.join(d, "sid", "left").withColumn("d", F.coalesce("d", F.lit(0.0)))


def diagonal_and_edges(nodes: DataFrame, edges: DataFrame, block: DataFrame, diagonal: Column, scale: Column) -> DataFrame:
    """diagonal * x + scale * (A x); nodes has the columns that diagonal and scale use."""
    cs = columns_of(block)
    product = spmv(edges, block).withColumnsRenamed({c: f"p{c}" for c in cs})
    both = nodes.join(block, "sid").join(product, "sid", "left")
    return both.select("sid", *((diagonal * F.col(c) + scale * F.coalesce(f"p{c}", F.lit(0.0))).alias(c) for c in cs))
