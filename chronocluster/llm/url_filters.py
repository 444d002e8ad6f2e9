"""URL filtering by a temporal list join.

A list is a log of dated entries that add a domain or take it off.  Each entry holds until the
domain's next one, so the log becomes validity intervals, and an as-of join checks a capture's host and
its parent domains against the entries active on the day it was fetched.  Captures are first reduced
to distinct pairs of host and day, so a host with many captures meets the list once a day.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

HOST = r"^[A-Za-z][A-Za-z0-9+.\-]*://(?:[^/?#@]*@)?([^/?#:@]*)"


def host_of(url: Column) -> Column:
    """The lower-case host of an absolute URL, without a last dot; null if there is none."""
    host = F.regexp_replace(F.lower(F.regexp_extract(url, HOST, 1)), r"\.+$", "")
    return F.when(host != "", host)


def intervals(entries: DataFrame, domain: str = "domain", day: str = "day", action: str = "action", rule: str = "rule") -> DataFrame:
    """domain, rule, since, until (exclusive, null for open) of each stretch in which a rule is on the list.

    Of several entries for a domain and rule on one day a removal wins; an entry that repeats the
    state before it changes nothing; entries without a domain or a day are ignored.
    """
    rows = entries.select(F.lower(F.col(domain)).alias("domain"), F.coalesce(F.col(rule), F.lit("")).alias("rule"), F.col(day).cast("date").alias("since"), (F.col(action) == "add").alias("on"))
    daily = rows.filter("domain is not null and since is not null").groupBy("domain", "rule", "since").agg(F.min(F.coalesce("on", F.lit(False))).alias("on"))
    order = Window.partitionBy("domain", "rule").orderBy("since")
    turns = daily.withColumn("was", F.lag("on", 1, False).over(order)).filter(F.col("on") != F.col("was"))
    return turns.withColumn("until", F.lead("since").over(order)).filter("on").select("domain", "rule", "since", "until")


def check(captures: DataFrame, entries: DataFrame, keys: list[str], url: str = "url", fetched: str = "fetched") -> DataFrame:
    """Per capture: keys, host, fetched, blocked, n_rules, and the rule and domain that block it (the longest listed since the latest day).

    A capture without a host or a day is not blocked; repeated rows each give a row.
    """
    rows = captures.select(*(F.col(f"`{k}`") for k in keys), host_of(F.col(f"`{url}`")).alias("host"), F.col(f"`{fetched}`").cast("date").alias("fetched"))
    asked = rows.select("host", "fetched").filter("host is not null and fetched is not null").distinct()
    labels = F.split("host", r"\.")
    domains = asked.select("host", "fetched", F.explode(F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))).alias("domain"))
    hits = domains.join(intervals(entries), "domain").filter((F.col("since") <= F.col("fetched")) & (F.col("until").isNull() | (F.col("fetched") < F.col("until"))))
    best = F.max(F.struct(F.length("domain").alias("size"), "since", "rule", "domain"))
    verdicts = hits.groupBy("host", "fetched").agg(F.count("*").alias("n_rules"), best.alias("best"))
    return rows.join(verdicts, ["host", "fetched"], "left").select(
        *keys, "host", "fetched", F.col("n_rules").isNotNull().alias("blocked"), F.coalesce("n_rules", F.lit(0)).alias("n_rules"), F.col("best.rule").alias("rule"), F.col("best.domain").alias("domain"), F.col("best.since").alias("since")
    )


# A list and fetch days for tables that have none, by rule.

#: The first day, and days over which fetches and entries are spread.
FIRST_DAY, DAYS = "2024-01-01", 360


def _digit(text: Column, part: int) -> Column:
    """A number below 4096 from the md5 of a text."""
    return F.conv(F.substring(F.md5(text.cast("binary")), 1 + 3 * part, 3), 16, 10).cast("int")


def fetched_pages(pages: DataFrame) -> DataFrame:
    """Page page_id was fetched page_id * 7 mod DAYS days after FIRST_DAY."""
    return pages.select("page_id", "url", F.date_add(F.lit(FIRST_DAY).cast("date"), (F.col("page_id") * 7 % DAYS).cast("int")).alias("fetched"))


def derived_list(pages: DataFrame) -> DataFrame:
    """A third of the hosts, or their parent if they begin with m. or blog., is listed on one day; half of these leave the list later and a quarter come back."""
    hosts = pages.select(F.regexp_replace(host_of(F.col("url")), r"^(m|blog)\.", "").alias("domain")).filter("domain is not null").distinct()
    listed = hosts.filter(_digit(F.col("domain"), 0) % 3 == 0).withColumn("at", _digit(F.col("domain"), 1) % 200).withColumn("stay", 1 + _digit(F.col("domain"), 2) % 90)
    rule = F.element_at(F.array(F.lit("adult"), F.lit("malware"), F.lit("spam")), 1 + _digit(F.col("domain"), 3) % 3)
    kind = _digit(F.col("domain"), 4) % 4
    turns = F.array(F.struct(F.lit("add").alias("action"), F.col("at").alias("at")), F.struct(F.lit("remove").alias("action"), (F.col("at") + F.col("stay")).alias("at")), F.struct(F.lit("add").alias("action"), (F.col("at") + 2 * F.col("stay")).alias("at")))
    entries = listed.select("domain", rule.alias("rule"), F.explode(F.slice(turns, F.lit(1), F.when(kind < 2, 1).when(kind == 2, 2).otherwise(3))).alias("e"))
    return entries.select("domain", "rule", F.date_add(F.lit(FIRST_DAY).cast("date"), F.col("e.at")).alias("day"), F.col("e.action").alias("action"))


def oracle_sql() -> str:
    """The same for DuckDB over ``pages``."""
    digit = lambda part: f"('0x' || substr(md5(domain), {1 + 3 * part}, 3))::INT"
    return f"""
WITH captures AS (
  SELECT page_id, nullif(regexp_replace(lower(regexp_extract(url, '{HOST}', 1)), '\\.+$', ''), '') AS host,
         DATE '{FIRST_DAY}' + (page_id * 7 % {DAYS})::INT AS fetched
  FROM pages),
hosts AS (SELECT DISTINCT regexp_replace(host, '^(m|blog)\\.', '') AS domain FROM captures WHERE host IS NOT NULL),
listed AS (
  SELECT domain, {digit(1)} % 200 AS start, 1 + {digit(2)} % 90 AS stay, {digit(4)} % 4 AS kind,
         (['adult', 'malware', 'spam'])[1 + {digit(3)} % 3] AS rule
  FROM hosts WHERE {digit(0)} % 3 = 0),
entries AS (
  SELECT domain, rule, start AS day, true AS listed FROM listed
  UNION ALL SELECT domain, rule, start + stay, false FROM listed WHERE kind >= 2
  UNION ALL SELECT domain, rule, start + 2 * stay, true FROM listed WHERE kind = 3),
stretches AS (
  SELECT domain, rule, listed, DATE '{FIRST_DAY}' + day::INT AS since,
         DATE '{FIRST_DAY}' + lead(day) OVER (PARTITION BY domain, rule ORDER BY day)::INT AS until
  FROM entries),
hits AS (
  SELECT c.host, c.fetched, s.*
  FROM (SELECT DISTINCT host, fetched FROM captures WHERE host IS NOT NULL) c
  JOIN stretches s ON (c.host = s.domain OR suffix(c.host, '.' || s.domain))
   AND s.listed AND s.since <= c.fetched AND (s.until IS NULL OR c.fetched < s.until)),
verdicts AS (
  SELECT host, fetched, count(*) AS n_rules,
         max(row(length(domain), since, rule, domain)) AS best
  FROM hits GROUP BY host, fetched)
SELECT c.page_id, c.host, c.fetched, v.n_rules IS NOT NULL AS blocked, coalesce(v.n_rules, 0) AS n_rules,
       v.best[3] AS rule, v.best[4] AS domain, v.best[2] AS since
FROM captures c LEFT JOIN verdicts v ON c.host = v.host AND c.fetched = v.fetched
"""
