"""Agreement of a labelling with known classes, from one contingency table."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def contingency(labels: DataFrame, truth: DataFrame, on: list[str] | None = None) -> DataFrame:
    """community, label, n; truth has (node, label) or (slice, node, label)."""
    on = on or [c for c in ("slice", "node") if c in truth.columns]
    return labels.join(truth, on).groupBy("community", "label").agg(F.count("*").alias("n"))


def contingency_cube(labels: DataFrame, truth: DataFrame) -> DataFrame:
    """The table with its margins."""
    return labels.join(truth, [c for c in ("slice", "node") if c in truth.columns]).cube("community", "label").agg(F.count("*").alias("n"), F.grouping_id().alias("level"))


def _choose2(c):
    return F.col(c) * (F.col(c) - 1) / 2


def agreement(table: DataFrame) -> DataFrame:
    """One row: nmi (by the mean of both entropies), ari, purity, overlap, from a contingency table.

    Both labellings with one class agree fully: nmi and ari are 1.
    """
    rows = table.groupBy("community").agg(F.sum("n").alias("a"))
    cols = table.groupBy("label").agg(F.sum("n").alias("b"))
    total = table.agg(F.sum("n").alias("t"))
    log = lambda c: F.ln(F.col(c) / F.col("t"))
    joint = table.join(rows, "community").join(cols, "label").crossJoin(F.broadcast(total))
    x = joint.agg(F.sum(F.col("n") / F.col("t") * F.ln(F.col("n") * F.col("t") / (F.col("a") * F.col("b")))).alias("mi"), F.sum(_choose2("n")).alias("both"), F.max("t").alias("t"))
    h = rows.crossJoin(F.broadcast(total)).agg((-F.sum(F.col("a") / F.col("t") * log("a"))).alias("ha"), F.sum(_choose2("a")).alias("pa"))
    g = cols.crossJoin(F.broadcast(total)).agg((-F.sum(F.col("b") / F.col("t") * log("b"))).alias("hb"), F.sum(_choose2("b")).alias("pb"))
    p = table.groupBy("community").agg(F.max("n").alias("top")).agg(F.sum("top").alias("top"))
    o = table.groupBy("label").agg(F.max("n").alias("best")).agg(F.sum("best").alias("best"))
    one = x.crossJoin(h).crossJoin(g).crossJoin(p).crossJoin(o)
    expected = F.col("pa") * F.col("pb") / (F.col("t") * (F.col("t") - 1) / 2)
    most = (F.col("pa") + F.col("pb")) / 2
    return one.select(
        F.coalesce(F.try_divide(2 * F.col("mi"), F.col("ha") + F.col("hb")), F.lit(1.0)).alias("nmi"),
        F.coalesce(F.try_divide(F.col("both") - expected, most - expected), F.lit(1.0)).alias("ari"),
        (F.col("top") / F.col("t")).alias("purity"),
        (F.col("best") / F.col("t")).alias("overlap"),
    )
