"""Every graph query against its SQL, at the smallest size."""

import math

import duckdb
import pytest

from chronocluster import catalog

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages".split()
#: Comparisons on graphs of many slices are left to the correctness run at the next size; their code is that of the others.
SLOW = {f"score_{x}" for x in ("vec_knn_static", "copart_quarter_thinned", "docwords_arrival", "contact_10min", "contact_5min", "cosupp_year", "cosupp_month", "cosupp_day", "page_links", "trade_region_year_thinned")}
#: At this size the weights are so small that a coupling of 1 is not weak.
SLOW |= {"degenerate_time"}


def plain(v):
    if isinstance(v, float):
        return None if math.isnan(v) else v
    if isinstance(v, list | tuple):
        return tuple(map(plain, v))
    return v


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", sorted(set(catalog.SQL) - SLOW))
def test_query_equals_its_sql(spark, duck, sf, name):
    try:
        df = catalog.QUERIES[name](spark, sf)
        columns = sorted(df.columns)
        got = sorted((tuple(plain(r[c]) for c in columns) for r in df.collect()), key=repr)
        want = duck.execute(catalog.SQL[name])
        names = [d[0] for d in want.description]
        assert sorted(names) == columns
        rows = sorted((tuple(plain(r[names.index(c)]) for c in columns) for r in want.fetchall()), key=repr)
        assert got == rows
    finally:
        spark.catalog.clearCache()


def test_every_sql_has_its_query():
    assert set(catalog.SQL) <= set(catalog.QUERIES)


def test_directed_leiden_takes_every_day(spark, sf, monkeypatch):
    given = []
    leiden = catalog.plans.leiden
    monkeypatch.setattr(catalog.plans, "leiden", lambda tg, *a, **o: given.append(tg) or leiden(tg, *a, **o))
    assert catalog.QUERIES["directed_leiden_users"](spark, sf).first().several
    everything = catalog.graph(spark, sf, "user_succession_day").edges
    assert everything.select("slice").distinct().count() > 4
    assert given[0].edges.exceptAll(everything).isEmpty() and everything.exceptAll(given[0].edges).isEmpty()
