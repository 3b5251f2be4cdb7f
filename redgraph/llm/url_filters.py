"""URL filters as a temporal join with dated lists.

List entries are dated events: a rule (a host or a parent domain) is added to or removed from a list.
Each event holds until the next one of the same list and rule, which turns the entries into validity
intervals; a capture is then judged by the entries that were active when it was fetched.

The as-of join works on distinct (rule, time) pairs: the hosts of a page table name their own rules and
those of their parent domains, and all hosts below a domain ask for it once per fetch time.  Time is cut
into stretches of ``STRETCH_DAYS`` and intervals into the stretches that they overlap, so rule and stretch
are the key of the join and a time meets only intervals of its own stretch.  A host takes the verdicts
of its rules at its times by equi-joins with one row per rule and time.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from redgraph.session import staged

STRETCH_DAYS = 32
_HOST = r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:@]+)"


def host_of(url: Column) -> Column:
    """Lower-case host without user, port and final dot; null if there is none or it exceeds 253 characters."""
    host = F.regexp_replace(F.lower(F.regexp_extract(url, _HOST, 1)), r"\.$", "")
    return F.when((F.length(host) > 0) & (F.length(host) <= 253), host)


def validity(entries: DataFrame) -> DataFrame:
    """``list, rule, valid_from, valid_to`` (null: still valid) from ``list, rule, action, since``.

    Actions are ``add`` and ``remove``; of events at one time an addition counts last.  Other actions,
    and entries with a null rule or time, are ignored; a null list is a list of its own.
    """
    order = Window.partitionBy("list", "rule").orderBy("since", F.desc("action"))
    known = entries.where(F.col("action").isin("add", "remove") & F.col("rule").isNotNull() & F.col("since").isNotNull()).select("list", F.lower("rule").alias("rule"), "action", "since")
    spans = known.withColumn("valid_to", F.lead("since").over(order))
    return spans.where("action = 'add' AND (valid_to IS NULL OR valid_to > since)").select("list", "rule", F.col("since").alias("valid_from"), "valid_to")


def stretch(time: Column, kind: str) -> Column:
    """The stretch of a date or timestamp, or of a number of days."""
    days = F.unix_date(time.cast("date")) if kind == "date" or kind.startswith("timestamp") else time
    return F.floor(days / STRETCH_DAYS).cast("long")


def judge(captures: DataFrame, entries: DataFrame, *, url_col: str = "url", time_col: str = "fetched") -> DataFrame:
    """All columns of ``captures`` plus ``host, blocked, n_active, lists, rule`` (the longest active one).

    A null or unreadable URL or a null time matches nothing.  Equal captures are judged alike.  Column
    names of ``captures`` that clash with the new ones are replaced.
    """
    new = ["host", "blocked", "n_active", "lists", "rule"]
    kept = [c for c in captures.columns if c not in new]
    rows = captures.select(*kept).withColumn("host", host_of(F.col(url_col)))
    pairs = rows.select("host", F.col(time_col).alias("__time")).where("host IS NOT NULL AND __time IS NOT NULL").distinct()
    labels = F.split("host", r"\.")
    suffixes = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda k: F.array_join(F.slice(labels, k, F.size(labels) - k + 1), "."))
    asked = pairs.select("host", "__time", F.explode(suffixes).alias("rule"))
    times = staged(asked.select("rule", "__time").distinct().withColumn("part", stretch(F.col("__time"), dict(captures.dtypes)[time_col])), "url-times")
    low, high = times.agg(F.min("part"), F.max("part")).first()
    kind = dict(entries.dtypes)["since"]
    low, high = (F.lit(0 if x is None else x).cast("long") for x in (low, high))
    spans = validity(entries).withColumn("from", F.greatest(stretch(F.col("valid_from"), kind), low)).withColumn("to", F.least(F.coalesce(stretch(F.col("valid_to"), kind), high), high))
    spans = spans.where(F.col("from") <= F.col("to")).withColumn("part", F.explode(F.sequence("from", "to"))).select("rule", "part", "list", "valid_from", "valid_to")
    now = times.join(spans, ["rule", "part"]).where("valid_from <= __time AND (valid_to IS NULL OR __time < valid_to)")
    active = now.groupBy("rule", "__time").agg(F.count(F.lit(1)).alias("n"), F.collect_set("list").alias("lists"))
    found = asked.join(active, ["rule", "__time"])
    verdict = found.groupBy("host", "__time").agg(F.sum("n").alias("n_active"), F.array_join(F.array_sort(F.array_distinct(F.flatten(F.collect_list("lists")))), ",").alias("lists"), F.max(F.struct(F.length("rule").alias("n"), F.col("rule").alias("rule")))["rule"].alias("rule"))
    out = rows.join(verdict.withColumnRenamed("host", "__host"), (F.col("host") == F.col("__host")) & (F.col(time_col) == F.col("__time")), "left")
    return out.select(*kept, "host", F.col("n_active").isNotNull().alias("blocked"), F.coalesce("n_active", F.lit(0).cast("long")).alias("n_active"), F.coalesce("lists", F.lit("")).alias("lists"), "rule")


def _digest(x: Column) -> Column:
    return F.conv(F.substring(F.md5(x), 1, 8), 16, 10).cast("long")


def sample_entries(pages: DataFrame) -> DataFrame:
    """Dated entries for the hosts of ``pages`` and their parent domains, fixed by a digest of each rule."""
    host = host_of(F.col("url"))
    rules = pages.select(F.explode(F.array(host, F.regexp_replace(host, r"^[^.]+\.", ""))).alias("rule")).where("rule IS NOT NULL").distinct().withColumn("x", _digest(F.col("rule")))
    day = lambda n: F.date_add(F.lit("2024-01-01").cast("date"), n.cast("int"))
    added = F.col("x") % 300
    removed = added + 20 + F.floor(F.col("x") / 256) % 100
    again = removed + 15 + F.floor(F.col("x") / 65536) % 60
    events = F.array(
        F.when(F.col("x") % 3 != 0, F.struct(F.lit("add").alias("action"), day(added).alias("since"))),
        F.when((F.col("x") % 3 != 0) & (F.col("x") % 2 == 0), F.struct(F.lit("remove").alias("action"), day(removed).alias("since"))),
        F.when((F.col("x") % 3 != 0) & (F.col("x") % 10 == 0), F.struct(F.lit("add").alias("action"), day(again).alias("since"))),
    )
    return rules.select("rule", F.when(F.col("x") % 7 < 3, "malware").when(F.col("x") % 7 < 5, "adult").otherwise("spam").alias("list"), F.explode(events).alias("e")).where("e IS NOT NULL").select("list", "rule", "e.action", "e.since")


def op6_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url")
    fetched = F.date_add(F.lit("2024-01-01").cast("date"), (_digest(F.concat(F.lit("fetch:"), F.col("page_id").cast("string"))) % 366).cast("int"))
    found = judge(pages.withColumn("fetched", fetched), sample_entries(pages))
    return found.select("page_id", F.col("fetched").cast("string").alias("fetched"), "host", "blocked", "n_active", "lists", "rule")


SQL = r"""
WITH p AS (SELECT page_id, nullif(regexp_replace(lower(regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:@]+)', 1)), '\.$', ''), '') AS host,
           DATE '2024-01-01' + CAST(('0x' || substr(md5('fetch:' || CAST(page_id AS VARCHAR)), 1, 8))::BIGINT % 366 AS INTEGER) AS fetched FROM pages),
rules AS (SELECT DISTINCT unnest([host, regexp_replace(host, '^[^.]+\.', '')]) AS rule FROM p WHERE host IS NOT NULL),
x AS (SELECT rule, ('0x' || substr(md5(rule), 1, 8))::BIGINT AS x FROM rules),
y AS (SELECT *, CASE WHEN x % 7 < 3 THEN 'malware' WHEN x % 7 < 5 THEN 'adult' ELSE 'spam' END AS list, x % 300 AS a, x % 300 + 20 + (x // 256) % 100 AS b, x % 300 + 35 + (x // 256) % 100 + (x // 65536) % 60 AS c FROM x WHERE x % 3 <> 0),
span AS (SELECT list, rule, DATE '2024-01-01' + CAST(a AS INTEGER) AS f, CASE WHEN x % 2 = 0 THEN DATE '2024-01-01' + CAST(b AS INTEGER) END AS t FROM y
         UNION ALL SELECT list, rule, DATE '2024-01-01' + CAST(c AS INTEGER), NULL FROM y WHERE x % 10 = 0),
hit AS (SELECT page_id, list, rule FROM p JOIN span ON (p.host = rule OR p.host LIKE '%.' || rule) AND f <= fetched AND (t IS NULL OR fetched < t)),
v AS (SELECT page_id, count(*) AS n, string_agg(DISTINCT list, ',' ORDER BY list) AS lists, arg_max(rule, length(rule)) AS rule FROM hit GROUP BY page_id)
SELECT page_id, CAST(fetched AS VARCHAR) AS fetched, host, v.n IS NOT NULL AS blocked, CAST(coalesce(v.n, 0) AS BIGINT) AS n_active, coalesce(lists, '') AS lists, v.rule AS rule FROM p LEFT JOIN v USING (page_id)
"""
