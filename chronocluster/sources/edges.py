"""Edge lists in and out of files."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..schemas import EDGES


def read_edges(spark: SparkSession, path: str, form: str = "parquet", columns: dict[str, str] | None = None, **options: str) -> DataFrame:
    """Edges from parquet, orc, json, csv (with a header) or white-space separated text.

    columns maps slice, src, dst and weight to the names in the file; a missing slice is 0 and a missing weight 1.
    """
    names = {f.name: (columns or {}).get(f.name, f.name) for f in EDGES}
    if form == "text":
        parts = F.split(F.trim("value"), r"\s+")
        df = spark.read.text(path).filter(~F.col("value").startswith("#"))
        return df.select(*(F.get(parts, i).try_cast(f.dataType).alias(f.name) for i, f in enumerate(EDGES.fields)))
    reader = spark.read.options(**options)
    if form in ("csv", "json"):
        reader = reader.schema(", ".join(f"`{names[f.name]}` {f.dataType.simpleString()}" for f in EDGES.fields if f.name in ("src", "dst") or columns is None or f.name in columns))
        reader = reader.option("header", True) if form == "csv" else reader
    df = reader.format(form).load(path)
    default = {"slice": F.lit(0), "weight": F.lit(1.0)}
    return df.select(*((F.col(names[f.name]) if names[f.name] in df.columns else default[f.name]).cast(f.dataType).alias(f.name) for f in EDGES.fields))


def read_snapshots(spark: SparkSession, path: str, form: str = "parquet") -> DataFrame:
    """A folder with one sub-folder slice=<i> per snapshot; filters on slice skip folders."""
    df = spark.read.format(form).load(path)
    return df.select(*(F.col(f.name).cast(f.dataType) for f in EDGES.fields))


def from_frames(frames: list[tuple[int, DataFrame]]) -> DataFrame:
    """One snapshot per frame with src, dst and, if it is there, weight."""
    parts = [df.select(F.lit(t).cast("int").alias("slice"), F.col("src").cast("bigint"), F.col("dst").cast("bigint"), (F.col("weight") if "weight" in df.columns else F.lit(1.0)).cast("double").alias("weight")) for t, df in frames]
    return reduce(DataFrame.unionByName, parts)


def write_edges(edges: DataFrame, path: str, form: str = "parquet", by_slice: bool = False) -> None:
    writer = edges.write.mode("overwrite").format(form)
    writer = writer.option("header", True) if form == "csv" else writer
    (writer.partitionBy("slice") if by_slice else writer).save(path)


def write_labels(labels: DataFrame, path: str) -> None:
    """Labels in one folder per slice, ordered by node within a file."""
    labels.repartition("slice").sortWithinPartitions("slice", "node").write.mode("overwrite").partitionBy("slice").parquet(path)


def write_supra(edges: DataFrame, table: str, buckets: int) -> None:
    """A table bucketed and sorted by the receiving end, so that repeated products need not move it."""
    edges.write.mode("overwrite").bucketBy(buckets, "b").sortBy("b").saveAsTable(table)


def to_triplets(edges: DataFrame) -> DataFrame:
    """Row, column and value from 1, both orientations, as a matrix-market body."""
    return edges.select((F.col("a") + 1).alias("row"), (F.col("b") + 1).alias("col"), F.col("weight").alias("value"))
