"""Streams against the batch result of the rows that are in time."""

import re
from datetime import datetime, timedelta

import pytest
from pyspark.sql import functions as F

from chronocluster import streaming
from chronocluster.streaming.build import run_to_table

SCHEMA = "event_id bigint, ts timestamp, user_id bigint, event_type string"


def files(spark, path, batches):
    for i, rows in enumerate(batches):
        spark.createDataFrame(rows, SCHEMA).coalesce(1).write.parquet(f"{path}/in/{i}")
    import os
    import shutil

    os.makedirs(f"{path}/all")
    for i in range(len(batches)):
        part = next(f for f in sorted(os.listdir(f"{path}/in/{i}")) if f.endswith(".parquet"))
        shutil.copy(f"{path}/in/{i}/{part}", f"{path}/all/{i}.parquet")
        os.utime(f"{path}/all/{i}.parquet", (1_700_000_000 + i, 1_700_000_000 + i))
    return f"{path}/all"


def at(hours):
    return datetime(2024, 1, 1) + timedelta(hours=hours)


def test_late_rows_are_left_out(spark, tmp_path):
    batches = [[(1, at(1), 7, "a"), (2, at(2), 7, "a")], [(3, at(60), 8, "b")], [(7, at(60), 8, "b")], [(4, at(3), 7, "a"), (5, at(61), 8, "b")], [(6, at(130), 9, "a")]]
    stream = streaming.events_stream(spark, files(spark, tmp_path, batches))
    rows, late = streaming.run_counted(streaming.tumbling_edges(stream))
    rows = rows.collect()
    assert late == 1
    assert sorted((r.start, r.user_id, r.event_type, r.weight) for r in rows) == [(at(0), 7, "a", 2.0), (at(48), 8, "b", 3.0)]


def test_sessions_dedup_and_states(spark, tmp_path):
    batches = [[(1, at(1), 7, "a"), (1, at(1), 7, "a"), (2, at(2), 7, "a"), (3, at(20), 7, "a")], [(4, at(90), 7, "b")]]
    stream = streaming.events_stream(spark, files(spark, tmp_path, batches))
    sessions = run_to_table(streaming.session_contacts(stream)).orderBy("start").collect()
    assert [(r.start, r.n) for r in sessions] == [(at(1), 3), (at(20), 1)]
    assert run_to_table(streaming.dedup(stream)).count() == 4
    states = run_to_table(streaming.running_degrees(stream)).orderBy("slice").collect()
    assert [(r.seen, r.gap) for r in states] == [(1, None), (2, 1), (3, 18), (4, 70)]


def test_contacts(spark, tmp_path):
    rows = [(1, at(1), 7, "a"), (2, at(1) + timedelta(minutes=5), 8, "a"), (3, at(1) + timedelta(minutes=11), 9, "a"), (4, at(1), 9, "b")]
    stream = streaming.events_stream(spark, files(spark, tmp_path, [rows]))
    found = run_to_table(streaming.stream_contacts(stream, stream.select("*")).select("src", "dst")).collect()
    assert sorted(map(tuple, found)) == [(7, 8), (8, 9)]


@pytest.mark.parametrize("within", ["10 minutes", "7 seconds"])
def test_contacts_meet_across_buckets_and_not_by_type_alone(spark, tmp_path, within):
    """Events just before, at and just after the edges of buckets, against all pairs; the join has a key of time."""
    width = timedelta(**{within.split()[1]: int(within.split()[0])})
    steps = [timedelta(0), width / 2, width - timedelta(microseconds=1), width, width + timedelta(microseconds=1), width * 2, width * 2.5]
    rows = [(10 * i + j, at(1) + s + j * timedelta(microseconds=1), (i * 5 + j) % 6, "ab"[j % 2]) for i, s in enumerate(steps) for j in range(4)]
    stream = streaming.events_stream(spark, files(spark, tmp_path, [rows]))
    contacts = streaming.stream_contacts(stream, stream.select("*"), within)
    found = sorted((r.src, r.dst, r["at"]) for r in run_to_table(contacts).collect())
    assert found == sorted((a[2], b[2], a[1]) for a in rows for b in rows if a[3] == b[3] and a[2] < b[2] and a[1] <= b[1] <= a[1] + width)
    assert re.search(r"\bba#\d+L? = bb#\d+", contacts._jdf.queryExecution().analyzed().toString())


def test_users_are_forgotten(spark, tmp_path):
    """After a long silence a user starts anew; one who comes again in time goes on."""
    batches = [[(1, at(1), 7, "a"), (2, at(1), 8, "a")], [(3, at(40), 8, "a")], [(4, at(80), 8, "a")], [(5, at(81), 8, "a")], [(6, at(120), 7, "a"), (7, at(120), 8, "a")]]
    stream = streaming.events_stream(spark, files(spark, tmp_path, batches))
    rows = run_to_table(streaming.running_degrees(stream, forget_after="2 days")).collect()
    first = min(r.slice for r in rows) - 1
    assert sorted((r.node, r.slice - first, r.seen) for r in rows) == [(7, 1, 1), (7, 120, 1), (8, 1, 1), (8, 40, 2), (8, 80, 3), (8, 81, 4), (8, 120, 5)]


def test_warm_communities(spark, tmp_path):
    from chronocluster import plans

    batches = [[(10 * d + i, at(24 * d + i), i % 3, "ab"[i % 2]) for i in range(6)] for d in range(5)]
    stream = streaming.events_stream(spark, files(spark, tmp_path, batches))
    starts = []

    def method(tg, start):
        starts.append(None if start is None else {(r.slice, r.node) for r in start.filter("community is not null").collect()})
        return plans.leiden(tg, 1.0, backend_name="kernel", start=start)

    labels = streaming.warm_communities(stream, method, keep=2)
    per = labels.groupBy("batch", "slice", "node").count()
    assert per.filter(F.col("count") > 1).isEmpty() and labels.select("slice").distinct().count() >= 3
    assert starts[0] is None and all(starts[1:])
    # The two groups of users and types stay what they are, so names go on from batch to batch.
    assert labels.groupBy("node").agg(F.countDistinct("community").alias("names")).agg(F.avg("names")).first()[0] < 1.5
