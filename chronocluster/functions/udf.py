"""Arrow-batched functions for what columns cannot say; nothing runs row by row."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf

from ..session import ship


@pandas_udf(T.ArrayType(T.DoubleType()))
def adjacency_spectrum(src: pd.Series, dst: pd.Series, weight: pd.Series) -> list[float]:
    """Eigenvalues, largest first, of the graph of one group; for groups that fit a task."""
    ids, inverse = np.unique(np.concatenate([src, dst]), return_inverse=True)
    m = np.zeros((len(ids), len(ids)))
    n = len(src)
    np.add.at(m, (inverse[:n], inverse[n:]), weight)
    np.add.at(m, (inverse[n:], inverse[:n]), weight)
    return np.linalg.eigvalsh(m)[::-1].tolist()


def slice_spectra(edges: DataFrame) -> DataFrame:
    """slice, spectrum of each snapshot."""
    ship(edges.sparkSession)
    return edges.groupBy("slice").agg(adjacency_spectrum("src", "dst", "weight").alias("spectrum"))


@udtf(returnType=T.StructType([T.StructField("run", T.IntegerType())]))
class WindowsOf:
    """The overlapping runs of slices that hold a slice: windows_of(slice - first, width, stride)."""

    def eval(self, at: int, width: int, stride: int) -> Iterator[tuple[int]]:
        for run in range(max(0, -(-(at - width + 1) // stride)), at // stride + 1):
            yield (run,)


def register_windows(spark: SparkSession) -> None:
    ship(spark)
    spark.udtf.register("windows_of", WindowsOf)


def cosine(a: str, b: str):
    """Cosine of two array columns by built-in folds."""
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)
    return F.try_divide(dot(a, b), F.sqrt(dot(a, a)) * F.sqrt(dot(b, b)))
