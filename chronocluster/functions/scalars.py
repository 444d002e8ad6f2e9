"""Column expressions; every argument is a column or a number."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def _col(x) -> Column:
    return x if isinstance(x, Column) else F.lit(float(x))


def affinity_lambda(c_in, c_out, k, c) -> Column:
    """Second eigenvalue of the normalised affinity matrix: (c_in - c_out) / (k c)."""
    return F.try_divide(_col(c_in) - _col(c_out), _col(k) * _col(c))


def affinity_rates(c, k, lam) -> tuple[Column, Column]:
    """c_in and c_out that give mean degree c and affinity lam."""
    return _col(c) * (1 + (_col(k) - 1) * _col(lam)), _col(c) * (1 - _col(lam))


def detectability(c, lam, k) -> Column:
    """struct(snr, regime): detectable above c lam^2 = 1; below it, hard for more than four classes, else undetectable."""
    snr = _col(c) * _col(lam) * _col(lam)
    regime = F.when(snr > 1, "detectable").when(_col(k) > 4, "hard or undetectable").otherwise("undetectable")
    return F.struct(snr.alias("snr"), regime.alias("regime"))


def cheeger_bounds(lam2) -> Column:
    """struct(low, high) around the conductance of the best bipartition."""
    return F.struct((_col(lam2) / 2).alias("low"), F.sqrt(2 * _col(lam2)).alias("high"))


def register(spark: SparkSession) -> None:
    """SQL functions affinity_lambda(c_in, c_out, k, c) and snr(c, lam) for this session."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION affinity_lambda(c_in DOUBLE, c_out DOUBLE, k DOUBLE, c DOUBLE) RETURNS DOUBLE RETURN try_divide(c_in - c_out, k * c)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION snr(c DOUBLE, lam DOUBLE) RETURNS DOUBLE RETURN c * lam * lam")
