"""Streaming forms of the snapshot builders; each takes and returns a streaming DataFrame."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..session import cut, scratch_dir, ship
from ..temporal import TemporalGraph
from ..tracking import match_labels


def events_stream(spark: SparkSession, path: str, files: int = 1) -> DataFrame:
    """A folder or one file of events as a stream with a UTC timestamp; the schema comes from the files."""
    schema = spark.read.parquet(path).schema
    folder, _, name = path.rpartition("/")
    reader = spark.readStream.schema(schema).option("maxFilesPerTrigger", files)
    stream = reader.option("pathGlobFilter", name).parquet(folder) if name.endswith(".parquet") else reader.parquet(path)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling_edges(events: DataFrame, width: str = "1 day", late: str = "1 hour", kind: str = "event_type") -> DataFrame:
    """start, user_id, event_type, weight: the edges of closed windows between users and what they did; later rows are dropped."""
    return events.withWatermark("ts", late).groupBy(F.window("ts", width).alias("w"), "user_id", kind).agg(F.count("*").cast("double").alias("weight")).select(F.col("w.start").alias("start"), "user_id", kind, "weight")


def sliding_counts(events: DataFrame, width: str = "2 days", step: str = "1 day", late: str = "1 hour") -> DataFrame:
    """start, user_id, n: overlapping windows."""
    return events.withWatermark("ts", late).groupBy(F.window("ts", width, step).alias("w"), "user_id").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "user_id", "n")


def session_contacts(events: DataFrame, gap: str = "6 hours", late: str = "1 hour") -> DataFrame:
    """start, stop, user_id, n: runs of a user's events without a longer pause."""
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("stop"), "user_id", "n")


def dedup(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Each event_id once within the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def stream_contacts(left: DataFrame, right: DataFrame, within: str = "10 minutes", late: str = "1 hour") -> DataFrame:
    """src, dst, at: pairs of different users, the second at most so long after the first, with events of one type.

    Times fall into buckets of that width, a key of the join beside the type: a first event lies in its own bucket,
    a second one in its own and the one before, so that each meets what is near and not all of its type.
    """
    width = int(pd.Timedelta(within) / pd.Timedelta("1us"))
    bucket = lambda: F.floor(F.unix_micros("ts") / F.lit(width))
    a = left.withWatermark("ts", late).select(F.col("user_id").alias("src"), F.col("ts").alias("at"), F.col("event_type").alias("ka"), bucket().alias("ba"))
    b = right.withWatermark("ts", late).select(F.col("user_id").alias("dst"), F.col("ts").alias("then"), F.col("event_type").alias("kb"), F.explode(F.array(bucket(), bucket() - 1)).alias("bb"))
    near = F.expr(f"ka = kb AND ba = bb AND src < dst AND then >= at AND then <= at + INTERVAL {within}")
    return a.join(b, near).select("src", "dst", "at")


def running_degrees(events: DataFrame, late: str = "1 hour", forget_after: str = "30 days") -> DataFrame:
    """node, slice, seen, gap: a state per user of how often it was seen and in which hour last; a coupling follows where gap is not null.

    A user of whom nothing comes for forget_after, in the events' own time, is forgotten, so the state holds those of that span alone.
    """
    ship(events.sparkSession)
    rows = events.withWatermark("ts", late).select("ts", F.col("user_id").alias("node"), F.floor(F.unix_timestamp("ts") / 3600).alias("slice"))
    keep_ms = int(pd.Timedelta(forget_after) / pd.Timedelta("1ms"))

    def update(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        seen, last = state.get if state.exists else (0, -1)
        slices = sorted({int(s) for f in frames for s in f["slice"]})
        out = []
        for s in slices:
            if s > last:
                seen += 1
                out.append((key[0], s, seen, s - last if last >= 0 else None))
                last = s
        state.update((seen, last))
        state.setTimeoutTimestamp(max(last * 3_600_000, state.getCurrentWatermarkMs()) + keep_ms)
        yield pd.DataFrame(out, columns=["node", "slice", "seen", "gap"]).astype({"gap": "Int64"})

    return rows.groupBy("node").applyInPandasWithState(update, "node bigint, slice bigint, seen bigint, gap bigint", "seen bigint, last bigint", "append", GroupStateTimeout.EventTimeTimeout)


def run_counted(stream: DataFrame, prefix: str = "stream") -> tuple[DataFrame, int]:
    """Run a bounded stream to its end into files of the shared folder; these, and how many rows came too late for any operator.

    Windows still open are not written.  Operators that aggregate count rows after they are combined in a task.
    """
    spark = stream.sparkSession
    base = f"{scratch_dir(spark)}/{prefix}-{uuid.uuid4().hex}"
    query = stream.writeStream.format("parquet").option("path", f"{base}/rows").option("checkpointLocation", f"{base}/state").outputMode("append").trigger(availableNow=True).start()
    query.awaitTermination()
    late = sum(op.numRowsDroppedByWatermark for p in query.recentProgress for op in p.stateOperators)
    return spark.read.schema(stream.schema).parquet(f"{base}/rows"), late


def run_to_table(stream: DataFrame, prefix: str = "stream") -> DataFrame:
    """Run a bounded stream to its end into files of the shared folder and read these; windows still open are not written."""
    return run_counted(stream, prefix)[0]


def warm_communities(stream: DataFrame, method: Callable[[TemporalGraph, DataFrame | None], DataFrame], keep: int = 3, late: str = "1 hour", width: str = "1 day") -> DataFrame:
    """Communities over the last windows, anew with each batch of closed ones: batch, slice, node, community.

    The method sees the windows of the batch and of the keep - 1 ones before, and the labels to start from:
    those of the batch before, and for new windows a node's last one.  Its communities take the names
    of those before that they match best in the windows both have seen.
    """
    spark = stream.sparkSession
    base = f"{scratch_dir(spark)}/communities-{uuid.uuid4().hex}"
    edges = tumbling_edges(stream, width, late)
    seconds = spark.sql(f"SELECT CAST(unix_seconds(TIMESTAMP '1970-01-01' + INTERVAL {width}) - unix_seconds(TIMESTAMP '1970-01-01') AS INT)").first()[0]
    held: list[DataFrame] = []

    def step(batch: DataFrame, number: int) -> None:
        if batch.isEmpty():
            return
        kinds = F.xxhash64("event_type").bitwiseAND(F.lit(0xFFFF)) + F.lit(1 << 36)
        flat = batch.select(F.floor(F.unix_timestamp("start") / seconds).cast("int").alias("slice"), F.col("user_id").alias("src"), kinds.alias("dst"), "weight")
        flat.write.mode("append").parquet(f"{base}/edges")
        known = batch.sparkSession.read.schema(flat.schema).parquet(f"{base}/edges")
        first = flat.agg(F.min("slice")).first()[0]
        tg = TemporalGraph(known.filter(F.col("slice") > first - keep))
        before = held[0] if held else None
        labels = cut(method(tg, _start(tg.nodes, before)), "labels")
        if before is not None:
            at = lambda df: df.select("slice", F.struct("slice", "node").alias("node"), "community")
            same = match_labels(at(before), at(labels), "overlap").select(F.col("new").alias("community"), F.col("old").alias("name"))
            # What matches nothing keeps its own name, unless that was another's before.
            taken = before.select(F.col("community").alias("old_name")).distinct()
            named = labels.join(same, "community", "left").join(taken, F.col("community") == F.col("old_name"), "left")
            fresh = F.when(F.col("old_name").isNull(), F.col("community")).otherwise(-F.col("community") * 1024 - number % 1024 - 1)
            labels = cut(named.select("slice", "node", F.coalesce("name", fresh).alias("community")), "labels")
        labels.withColumn("batch", F.lit(number)).write.mode("append").parquet(f"{base}/labels")
        held[:] = [labels]

    query = edges.writeStream.foreachBatch(step).option("checkpointLocation", f"{base}/state").outputMode("append").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.parquet(f"{base}/labels")


def _start(nodes: DataFrame, before: DataFrame | None) -> DataFrame | None:
    """slice, node, community to start from: a temporal node's own label before, or its node's last one."""
    if before is None:
        return None
    last = before.groupBy("node").agg(F.max_by("community", "slice").alias("last"))
    own = before.withColumnRenamed("community", "own")
    return nodes.join(own, ["slice", "node"], "left").join(last, "node").select("slice", "node", F.coalesce("own", "last").alias("community"))
