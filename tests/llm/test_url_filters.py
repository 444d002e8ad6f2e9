from datetime import date

from chronocluster.llm import url_filters as uf


def test_intervals_and_verdicts(spark):
    log = [("Bad.org", "spam", "2024-01-05", "add"), ("bad.org", "spam", "2024-01-10", "remove"), ("bad.org", "spam", "2024-01-20", "add"), ("bad.org", "spam", "2024-01-22", "add"), ("x.bad.org", "adult", "2024-01-07", "add"), ("same.org", "spam", "2024-01-03", "add"), ("same.org", "spam", "2024-01-03", "remove"), (None, "spam", "2024-01-01", "add"), ("late.org", "spam", None, "add")]
    entries = spark.createDataFrame(log, "domain string, rule string, day string, action string")
    got = sorted(uf.intervals(entries).collect())
    assert [(r.domain, str(r.since), str(r.until)) for r in got] == [("bad.org", "2024-01-05", "2024-01-10"), ("bad.org", "2024-01-20", "None"), ("x.bad.org", "2024-01-07", "None")]
    captures = [(1, "http://x.bad.org/a", "2024-01-06"), (2, "https://user@X.BAD.org:80/?q", "2024-01-08"), (3, "http://bad.org", "2024-01-10"), (4, "http://notbad.org/", "2024-01-06"), (5, None, "2024-01-06"), (6, "no url", "2024-01-06"), (7, "http://bad.org./", "2024-02-01"), (8, "http://same.org", "2024-02-01"), (9, "http://bad.org", None), (1, "http://x.bad.org/a", "2024-01-06")]
    df = spark.createDataFrame(captures, "page_id bigint, url string, fetched string").withColumnRenamed("page_id", "rule")
    out = sorted(uf.check(df.withColumnRenamed("rule", "page_id"), entries, ["page_id"]).collect(), key=lambda r: r.page_id)
    assert [(r.page_id, r.blocked, r.n_rules, r.domain) for r in out] == [(1, True, 1, "bad.org"), (1, True, 1, "bad.org"), (2, True, 2, "x.bad.org"), (3, False, 0, None), (4, False, 0, None), (5, False, 0, None), (6, False, 0, None), (7, True, 1, "bad.org"), (8, False, 0, None), (9, False, 0, None)]
    assert out[-3].since == date(2024, 1, 20)
    assert uf.check(df.withColumnRenamed("rule", "page_id").limit(0), entries, ["page_id"]).count() == 0
    assert uf.check(df.withColumnRenamed("rule", "page_id"), entries.limit(0), ["page_id"]).filter("blocked").count() == 0


def test_query_equals_its_sql(spark, sf):
    import duckdb

    from chronocluster.llm import registry

    duckdb.sql(f"CREATE OR REPLACE VIEW pages AS SELECT * FROM '{sf}/pages.parquet'")
    want = duckdb.sql(registry.oracle_sql()["op10_url_filters"])
    names = want.columns
    assert sorted(map(repr, want.fetchall())) == sorted(repr(tuple(r[c] for c in names)) for r in registry.op10_url_filters(spark, sf).collect())
