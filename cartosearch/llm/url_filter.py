"""URL filters with a temporal list join.

A list is a log of dated entries: a domain is added to or removed from a list on a day. Each entry holds until
the next one for the same list and domain, which makes validity intervals; an as-of join asks, for every
capture, which intervals of the domains above its host were open when it was fetched.

Null or malformed URL: no host, never matched. Null fetch time: matched by no entry. Entries of one list, domain
and day: a removal wins. Captures that repeat page_id, url and fetch time are one row with their number.
Hosts are compared in lower case, without user, port and a trailing dot. Empty lists match nothing.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: The names that the query's list log is about, with the list that each is on.
NAMES = {"cheap-pills": "spam", "spam-farm": "spam", "casino-win": "gambling", "free-bets": "gambling", "ads-track": "trackers", "adult-x": "adult"}
#: The log: every name is listed under three top domains from the start; one is cleared for a while, one for good.
ENTRIES = [(kind, f"{name}.example.{top}", "add", "2024-01-01") for name, kind in NAMES.items() for top in ("com", "net", "org")] + [
    ("trackers", "ads-track.example.com", "remove", "2024-06-01"),
    ("trackers", "ads-track.example.com", "add", "2024-07-15"),
    ("gambling", "free-bets.example.org", "remove", "2024-10-01"),
    ("trackers", "tionsh.example.net", "add", "2024-11-15"),
]
#: Parts of a key of one label.
SALTS = 256
HOST = r"(?i)^[a-z][a-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]+)"


def entries(spark: SparkSession, rows: list[tuple] | None = None) -> DataFrame:
    return spark.createDataFrame(ENTRIES if rows is None else rows, "list string, domain string, action string, day string").withColumn("day", F.to_date("day"))


def intervals(log: DataFrame) -> DataFrame:
    """list, domain, open day and (exclusive, nullable) end of every time that a domain is on a list."""
    once = log.filter("day is not null and domain is not null").groupBy("list", F.lower("domain").alias("domain"), "day").agg(F.max(F.when(F.col("action") == "remove", 1).otherwise(0)).alias("off"))
    along = Window.partitionBy("list", "domain").orderBy("day")
    # Only changes of state start or end an interval.
    changed = once.withColumn("was", F.coalesce(F.lag("off").over(along), F.lit(1))).filter("off != was")
    return changed.withColumn("until", F.lead("day").over(along)).filter("off = 0").select("list", "domain", F.col("day").alias("since"), "until")


def host(url: Column) -> Column:
    return F.nullif(F.rtrim(F.lower(F.regexp_extract(url, HOST, 1)), F.lit(".")), F.lit(""))


def captures(pages: DataFrame) -> DataFrame:
    """page_id, url and a fetch day: the tables have none, so pages are fetched through 2024 by page_id."""
    return pages.select("page_id", "url", F.date_add(F.lit("2024-01-01").cast("date"), F.pmod("page_id", F.lit(366)).cast("int")).alias("fetched"))


def listed_hosts(pages: DataFrame) -> DataFrame:
    """A log that grows with the table: one host in four goes on a list, on a day and for a time that its digest names;
    some come back. list, domain, action, day."""
    digest = F.md5("host")
    number = lambda at, n: F.conv(F.substring(digest, at, n), 16, 10).cast("int")
    hosts = pages.select(host(F.col("url")).alias("host")).filter("host IS NOT NULL").distinct()
    chosen = hosts.filter(number(1, 1) < 4).select("host", F.concat(F.lit("watch-"), F.substring(digest, 2, 1)).alias("list"), (number(3, 2)).alias("a"), (number(5, 2) + 1).alias("b"), number(7, 1).alias("back"))
    day = lambda n: F.date_add(F.lit("2024-01-01").cast("date"), n)
    steps = F.array(
        F.struct(F.lit("add").alias("action"), day(F.col("a")).alias("day")),
        F.struct(F.lit("remove").alias("action"), day(F.col("a") + F.col("b")).alias("day")),
        F.struct(F.when(F.col("back") < 8, F.lit("add")).alias("action"), day(F.col("a") + F.col("b") + 30).alias("day")),
    )
    return chosen.select("list", F.col("host").alias("domain"), F.explode(steps).alias("step")).select("list", "domain", "step.action", "step.day").filter("action IS NOT NULL")


def match(fetched: DataFrame, log: DataFrame) -> DataFrame:
    """page_id, url, fetched, host, captures, n_hits, lists and blocked, one row per distinct capture.

    Lists meet distinct hosts, not captures: the intervals of all domains above a host are gathered once per host, and each
    capture tests those of its host. A domain of one label stands above a large share of all hosts, so rows of such keys
    are salted; those of a popular host are left to the skew handling of the join, which adds no exchange.
    """
    once = fetched.groupBy("page_id", "url", "fetched").agg(F.count(F.lit(1)).alias("captures")).withColumn("host", host(F.col("url")))
    labels = F.split("host", r"\.")
    hosts = fetched.select(host(F.col("url")).alias("host")).filter("host IS NOT NULL").distinct()
    # One row per domain above the host; hosts have few labels.
    above = hosts.select("host", F.explode(F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))).alias("domain"))
    single = ~F.contains("domain", F.lit("."))
    salted = above.withColumn("salt", F.when(single, F.pmod(F.xxhash64("host"), F.lit(SALTS))).otherwise(F.lit(0).cast("long")))
    open_ = intervals(log).withColumn("salt", F.explode(F.when(single, F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long"))).otherwise(F.array(F.lit(0).cast("long")))))
    listed = salted.join(open_, ["domain", "salt"]).groupBy(F.col("host").alias("_host")).agg(F.collect_list(F.struct("list", "domain", "since", "until")).alias("spans"))
    active = F.filter("spans", lambda x: (x["since"] <= F.col("fetched")) & (x["until"].isNull() | (F.col("fetched") < x["until"])))
    joined = once.join(listed, F.col("host") == F.col("_host"), "left").withColumn("active", F.coalesce(active, F.array().cast("array<struct<list:string,domain:string,since:date,until:date>>")))
    lists = F.array_join(F.array_sort(F.array_distinct(F.transform("active", lambda x: x["list"]))), ",")
    out = joined.select("page_id", "url", "fetched", "host", "captures", F.size("active").cast("long").alias("n_hits"), lists.alias("lists"))
    return out.withColumn("blocked", F.col("n_hits") > 0)


def sql() -> str:
    """The query over pages in SQL."""
    values = ", ".join(f"('{a}', '{b}', '{c}', DATE '{d}')" for a, b, c, d in ENTRIES)
    number = lambda at, n: f"CAST('0x' || substr(md5(host), {at}, {n}) AS INTEGER)"
    return rf"""
WITH fetches AS (SELECT page_id, url, CAST(DATE '2024-01-01' + CAST(page_id % 366 AS INTEGER) AS DATE) AS fetched FROM pages),
once AS (SELECT page_id, url, fetched, count(*) AS captures, nullif(lower(regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://([^/?#:]+)', 1)), '') AS host FROM fetches GROUP BY page_id, url, fetched),
chosen AS (SELECT DISTINCT host, 'watch-' || substr(md5(host), 2, 1) AS list, {number(3, 2)} AS a, {number(5, 2)} + 1 AS b, {number(7, 1)} AS back FROM once WHERE host IS NOT NULL AND {number(1, 1)} < 4),
log(list, domain, action, day) AS (SELECT * FROM (VALUES {values}) v
  UNION ALL SELECT list, host, 'add', CAST(DATE '2024-01-01' + a AS DATE) FROM chosen
  UNION ALL SELECT list, host, 'remove', CAST(DATE '2024-01-01' + (a + b) AS DATE) FROM chosen
  UNION ALL SELECT list, host, 'add', CAST(DATE '2024-01-01' + (a + b + 30) AS DATE) FROM chosen WHERE back < 8),
spans AS (SELECT list, domain, action, day AS since, lead(day) OVER (PARTITION BY list, domain ORDER BY day) AS until FROM log)
SELECT o.page_id, o.url, o.fetched, o.host, o.captures, count(s.list) AS n_hits, coalesce(string_agg(DISTINCT s.list, ',' ORDER BY s.list), '') AS lists, count(s.list) > 0 AS blocked
FROM once o LEFT JOIN spans s ON s.action = 'add' AND (o.host = s.domain OR ends_with(o.host, '.' || s.domain))
  AND s.since <= o.fetched AND (s.until IS NULL OR o.fetched < s.until)
GROUP BY o.page_id, o.url, o.fetched, o.host, o.captures
"""
