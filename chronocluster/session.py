"""What the engine reads from the session it is given; it never sets anything fixed at start."""

from __future__ import annotations

import os
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

#: Rows that a single task may hold in a kernel; larger inputs take the distributed path.
KERNEL_EDGES = 2_000_000


def conf(spark: SparkSession, name: str, default: str) -> str:
    return spark.conf.get(f"chronocluster.{name}", default)


def backend(spark: SparkSession, edges: int | None = None) -> str:
    """kernel or distributed, from chronocluster.backend (auto: by the number of edges)."""
    chosen = conf(spark, "backend", "auto")
    if chosen != "auto":
        return chosen
    return "kernel" if edges is not None and edges <= int(conf(spark, "kernel_edges", str(KERNEL_EDGES))) else "distributed"


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir; a folder under /tmp/checkpoints where that is unset and all tasks run on this machine."""
    there = spark.conf.get("spark.checkpoint.dir", None)
    if there is None:
        current = spark.sparkContext._jsc.sc().getCheckpointDir()
        if current.isDefined():
            return current.get()
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        there = "/tmp/checkpoints/chronocluster"
    return there


def scratch_dir(spark: SparkSession) -> str:
    """The folder that holds all intermediate tables of this application."""
    return f"{shared_dir(spark)}/{spark.sparkContext.applicationId}"


def cut(df: DataFrame, name: str = "state") -> DataFrame:
    """Write df to the shared folder and read it back: lineage ends there and survives lost executors."""
    path = f"{scratch_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    back = df.sparkSession.read.schema(df.schema).parquet(path)
    back._scratch = path
    return back


def _delete(spark: SparkSession, path: str) -> None:
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


def forget(df: DataFrame | None) -> None:
    """Delete the table behind a result of cut() that nothing will read again, as the state of an earlier round."""
    path = getattr(df, "_scratch", None)
    if path:
        _delete(df.sparkSession, path)


def clean_up(spark: SparkSession) -> None:
    """Delete every intermediate table of this application; frames that rest on them are lost."""
    _delete(spark, scratch_dir(spark))


_shipped: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Give Python workers this package, once for each application, unless their path has it already."""
    root = Path(__file__).resolve().parent
    if str(root.parent) in os.environ.get("PYTHONPATH", "").split(os.pathsep) or spark.sparkContext.applicationId in _shipped:
        return
    archive = Path(tempfile.mkdtemp()) / f"{root.name}.zip"  # the driver serves it to executors
    with zipfile.ZipFile(archive, "w") as z:
        for f in sorted(root.rglob("*.py")):
            z.write(f, f.relative_to(root.parent))
    spark.sparkContext.addPyFile(str(archive))
    _shipped.add(spark.sparkContext.applicationId)
