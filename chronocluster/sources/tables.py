"""Scans of the given tables; zone-less times become UTC timestamps."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TIMES = {"orders": ["o_orderdate"], "lineitem": ["l_shipdate"], "events": ["ts"]}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.withColumns({c: F.col(c).cast("timestamp") for c in TIMES.get(name, []) if dict(df.dtypes)[c] == "timestamp_ntz"})


def register_views(spark: SparkSession, sf_dir: str, graphs: dict[str, DataFrame] | None = None) -> None:
    """Temporary views of tables and graphs, so that both can be asked in SQL."""
    for name in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events"):
        load(spark, sf_dir, name).createOrReplaceTempView(name)
    for name, edges in (graphs or {}).items():
        edges.createOrReplaceTempView(name)
