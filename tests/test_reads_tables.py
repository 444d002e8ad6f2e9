"""Queries work on the given tables."""

import duckdb
import pytest

from chronocluster import catalog


SCALARS = [("detectability", ["lineitem"]), ("cheeger_bounds", ["lineitem"]), ("sql_functions", ["lineitem"])]
PLANTED = [(x, ["customer", "lineitem"]) for x in ("sbm_edges", "properties_sbm", "properties_sbm_nodes", "properties_sbm_edges", "properties_sbm_snapshots")] + [("sbm_labels", ["customer"])]


@pytest.mark.parametrize("name, tables", SCALARS + PLANTED)
def test_query_reads_its_tables(spark, sf, name, tables):
    plan = catalog.QUERIES[name](spark, sf)._jdf.queryExecution().toString()
    assert all(f"{sf}/{t}.parquet" in plan for t in tables)


def test_dealt_customers_are_drawn_as_in_sql(spark, sf):
    """The graph whose classes estimate_k counts: its nodes stay as many, each draw counts."""
    table = catalog._CELLS
    con = duckdb.connect()
    for t in ("customer", "lineitem"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    edges = table.edges(spark, sf)
    plan = edges._jdf.queryExecution().toString()
    assert all(f"{sf}/{t}.parquet" in plan for t in ("customer", "lineitem"))
    rows = sorted(map(tuple, edges.select("slice", "src", "dst", "weight").collect()))
    assert rows == sorted(con.execute(f"SELECT slice, src, dst, weight FROM {table.edges_sql}").fetchall())
    assert max(r[2] for r in rows) < table.cells and max(r[3] for r in rows) > 1


def test_planted_source_draws_only_events_among_users(spark, sf, tmp_path, monkeypatch):
    """A table with gaps in both ids, over several tasks of the source; and the source without a table."""
    catalog.load(spark, sf, "events").filter("event_id % 3 <> 1 and user_id % 5 <> 2").write.parquet(f"{tmp_path}/events.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{tmp_path}/events.parquet/*.parquet'")
    monkeypatch.setattr(catalog.planted_source, "TASK_DRAWS", 150)
    found = catalog.QUERIES["planted_source"](spark, str(tmp_path))
    assert any("/events.parquet/" in f for f in found.inputFiles())
    want = con.execute(catalog.SQL["planted_source"]).fetchall()
    assert sorted(map(tuple, found.select("slice", "src", "dst", "weight").collect())) == sorted(want) and want
    p = catalog.PlantedPartition(60, 3, 3, 6.0, 0.5, 0.9, seed=4)
    alone = spark.read.format("planted_partition").options(n="60", k="3", slices="3", c="6.0", lam="0.5", eta="0.9", seed="4").load()
    assert sorted(map(tuple, alone.collect())) == sorted(con.execute(f"SELECT slice, src, dst, weight FROM {catalog.edges_sql(p)}").fetchall())
