"""Planted partitions as a Python data source: spark.read.format('planted_partition').option('n', 1000)."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import lru_cache

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..session import ship

#: Draws of a task.
TASK_DRAWS = 100_000


class PlantedPartitionSource(DataSource):
    """Edges by the rule of chronocluster.generators, one partition for each slice.

    Options n, k, slices, c, lam, eta, seed; a slice's rows are made in one task, so large n belongs to planted_edges.
    With draws the draws 0 to draws - 1 are made instead, many tasks at once: their numbers come as id, and a pair
    as often as it is drawn.
    """

    @classmethod
    def name(cls) -> str:
        return "planted_partition"

    def schema(self) -> str:
        return ("id bigint, " if "draws" in self.options else "") + "slice int, src bigint, dst bigint, weight double"

    def reader(self, schema) -> DataSourceReader:
        return PlantedReader(self.options)


class PlantedReader(DataSourceReader):
    def __init__(self, options: dict[str, str]):
        from ..generators import PlantedPartition

        kinds = {"n": int, "k": int, "slices": int, "c": float, "lam": float, "eta": float, "seed": int}
        self.p = PlantedPartition(**{k: kind(options[k]) for k, kind in kinds.items() if k in options})
        self.draws = int(options["draws"]) if "draws" in options else None

    def partitions(self) -> list[InputPartition]:
        if self.draws is None:
            return [InputPartition((t, None)) for t in range(self.p.slices)]
        return [InputPartition((None, (at, min(at + TASK_DRAWS, self.draws)))) for at in range(0, max(1, self.draws), TASK_DRAWS)]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        p, (only, ids) = self.p, partition.value
        part = lambda text, i: int(hashlib.md5(text.encode()).hexdigest()[8 * i : 8 * i + 8], 16)

        @lru_cache(1 << 18)
        def label(node: int, t: int) -> int:
            for s in range(t, 0, -1):
                key = f"label:{p.seed}:{s}:{node}"
                if part(key, 0) >= int(p.eta * 2**32):
                    return part(key, 1) % p.k
            return node % p.k

        top, seen = max(p.c_in, p.c_out), set()
        for id_ in range(*ids) if ids else range(only, p.candidates * p.slices, p.slices):
            t, j = id_ % p.slices, id_ // p.slices
            key = f"edge:{p.seed}:{t}:{j}"
            u, v = part(key, 0) % p.n, part(key, 1) % p.n
            limit = int((p.c_in if label(u, t) == label(v, t) else p.c_out) / top * 2**32)
            pair = (min(u, v), max(u, v))
            if u == v or part(key, 2) >= limit:
                continue
            if ids:
                yield (id_, t, *pair, 1.0)
            elif pair not in seen:
                seen.add(pair)
                yield (t, *pair, 1.0)


def register(spark: SparkSession) -> None:
    ship(spark)
    spark.dataSource.register(PlantedPartitionSource)
