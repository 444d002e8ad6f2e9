"""Helpers that several text operators share."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..session import cut, ship

#: Bytes of text that one call of a batch kernel holds at most, besides a single longer text.
KERNEL_BYTES = 2 << 20
#: Rows that travel to Python at once, at most: 10,000 long texts would fill an executor's memory.
BATCH_ROWS = 500


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Write df to the shared folder and read it again, so that lost executors cost no lineage."""
    return cut(df, name)


#: Word hashes that one worker keeps.
KEPT_WORDS = 150_000


class WordHashes(dict):
    """64-bit hashes of words as bytes, worked out when a word is first asked for and then kept, a bounded number of them."""

    def __init__(self):
        import xxhash

        super().__init__()
        self.hash = xxhash.xxh3_64_intdigest

    def __missing__(self, word: bytes) -> int:
        h = self[word] = self.hash(word)
        return h

    def of(self, words: list[bytes]) -> np.ndarray:
        if len(self) > KEPT_WORDS:
            self.clear()
        return np.fromiter(map(self.__getitem__, words), dtype=np.uint64, count=len(words))


def ready_workers(spark: SparkSession) -> None:
    """Lower the session's rows per Arrow batch, a setting that may change at any time, to BATCH_ROWS, and give workers the package."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    ship(spark)
    if not 0 < int(spark.conf.get(name)) <= BATCH_ROWS:
        spark.conf.set(name, str(BATCH_ROWS))


def slices(batch: pa.RecordBatch, column: str) -> Iterator[pa.RecordBatch]:
    """Cut a batch into pieces of at most KERNEL_BYTES of the given string column."""
    sizes = [len(x.as_py() or "") if x.is_valid else 0 for x in batch.column(column)] if batch.nbytes > KERNEL_BYTES else None
    if sizes is None:
        yield batch
        return
    start, held = 0, 0
    for i, n in enumerate(sizes):
        if held and held + n > KERNEL_BYTES:
            yield batch.slice(start, i - start)
            start, held = i, 0
        held += n
    if start < batch.num_rows:
        yield batch.slice(start)


def map_texts(
    df: DataFrame,
    keys: list[str],
    text: str,
    kernel: Callable[[], Callable[[list[str | None]], list[list]]],
    fields: list[tuple[str, str]],
    beside: str | None = None,
) -> DataFrame:
    """Apply a Python kernel to every whole text, batch by batch, without a shuffle.

    kernel() runs once in each task and returns a function from a list of texts (null stays None)
    to one list per field; with beside, the name of another string column, that function is given the
    list of its values too.  Only these columns and the keys travel to Python (the text once, if it is a
    key too), so other columns of df can have any name.
    """
    ready_workers(df.sparkSession)
    seen = text if text in keys else "__text"
    picked = df.select(*[F.col(f"`{k}`") for k in keys], *([] if text in keys else [F.col(f"`{text}`").alias(seen)]), *([F.col(f"`{beside}`").alias("__beside")] if beside else []))
    made = T.StructType([T.StructField(n, T._parse_datatype_string(t)) for n, t in fields])
    schema = T.StructType([*(T.StructField(f.name, f.dataType) for f in picked.schema.fields[: len(keys)]), *made.fields])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark.sql.pandas.types import to_arrow_schema

        arrow = to_arrow_schema(made)
        f = kernel()
        for whole in batches:
            for b in slices(whole, seen):
                made_columns = f(b.column(seen).to_pylist(), *([b.column("__beside").to_pylist()] if beside else []))
                arrays = [pa.array(c, type=x.type) for c, x in zip(made_columns, arrow, strict=True)]
                yield pa.RecordBatch.from_arrays([*(b.column(i) for i in range(len(keys))), *arrays], names=[*keys, *arrow.names])

    return picked.mapInArrow(run, schema)
