"""URL filters by a temporal list join.

A list holds dated entries: (key, action, listed_at).  A key is a domain (``example.net``), which covers its
subdomains, or a host and first path segment (``example.net/de``), which covers that host and its subdomains
below that segment.  Entries of one key become validity intervals, each lasting until the next; every capture is
judged by the entries active when it was fetched, the most specific key first: ``block`` blocks it, ``allow``
lets it through.

Captures are first reduced to distinct (host, segment, time); their candidate keys, as many as the host has
labels, meet the intervals in an equi-join, and only the combinations that meet something return to the rows.
Small sides are broadcast after they were counted; larger ones are shuffled.

Edge cases: a null or unreadable URL has no host and is allowed; a null fetch time meets no interval; of
entries with one key and time, ``block`` holds; entries with a null key, time or unknown action are ignored;
repeated captures each get their row; an empty list allows everything; keys compare in lower case and a
leading ``www.`` of hosts is kept (a domain entry covers it as a subdomain).
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

MAX_BROADCAST_ROWS = 500_000

HOST = r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:@]+)"
SEGMENT = r"^[A-Za-z][A-Za-z0-9+.-]*://[^/?#]*/([^/?#]+)"


def intervals(entries: DataFrame) -> DataFrame:
    """key, action, valid_from, valid_to (null: open) from dated entries."""
    known = entries.where(F.col("key").isNotNull() & F.col("listed_at").isNotNull() & F.col("action").isin("block", "allow"))
    one = known.groupBy(F.lower("key").alias("key"), "listed_at").agg(F.max("action").alias("action"))
    order = W.Window.partitionBy("key").orderBy("listed_at")
    return one.select("key", "action", F.col("listed_at").alias("valid_from"), F.lead("listed_at").over(order).alias("valid_to"))


def candidate_keys(host: F.Column, segment: F.Column) -> F.Column:
    """Structs (rank, key) for a host: each suffix of its labels, alone and with the path segment."""
    labels = F.split(host, r"\.")
    suffixes = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda k: F.struct(F.size(labels) - k + 1, F.array_join(F.slice(labels, k, F.size(labels)), ".")))
    alone = F.transform(suffixes, lambda s: F.struct((2 * s["col1"]).alias("rank"), s["col2"].alias("key")))
    deep = F.transform(suffixes, lambda s: F.struct((2 * s["col1"] + 1).alias("rank"), F.concat_ws("/", s["col2"], segment).alias("key")))
    return F.when(segment != "", F.concat(alone, deep)).otherwise(alone)


def bounded(df: DataFrame, most: int) -> DataFrame:
    """``df`` with a broadcast hint if it has at most ``most`` rows."""
    return F.broadcast(df) if df.limit(most + 1).count() <= most else df


def judge(captures: DataFrame, entries: DataFrame, url: str = "url", fetched_at: str = "fetched_at", max_broadcast_rows: int = MAX_BROADCAST_ROWS) -> DataFrame:
    """``captures`` with url_host, matched_key, matched_since and blocked."""
    text = F.coalesce(F.col(url), F.lit(""))
    rows = captures.drop("url_host", "matched_key", "matched_since", "blocked").withColumn("url_host", F.lower(F.regexp_extract(text, HOST, 1)))
    rows = rows.withColumn("url_segment_", F.lower(F.regexp_extract(text, SEGMENT, 1)))
    asked = rows.where("url_host != ''").select("url_host", "url_segment_", F.col(fetched_at).alias("at_")).where("at_ is not null").distinct()
    keys = asked.select("*", F.explode(candidate_keys(F.col("url_host"), F.col("url_segment_"))).alias("c")).select("url_host", "url_segment_", "at_", "c.rank", "c.key")
    valid = bounded(intervals(entries), max_broadcast_rows)
    met = keys.join(valid, (keys["key"] == valid["key"]) & (F.col("at_") >= F.col("valid_from")) & (F.col("valid_to").isNull() | (F.col("at_") < F.col("valid_to"))))
    best = met.groupBy("url_host", "url_segment_", "at_").agg(F.max_by(F.struct(keys["key"].alias("key"), F.col("valid_from"), F.col("action")), "rank").alias("m"))
    best = bounded(best.select(F.col("url_host").alias("h_"), F.col("url_segment_").alias("s_"), F.col("at_").alias("t_"), "m"), max_broadcast_rows)
    on = (F.col("url_host") == F.col("h_")) & (F.col("url_segment_") == F.col("s_")) & (F.col(fetched_at) == F.col("t_"))
    kept = [*(c for c in rows.columns if c != "url_segment_")]
    return rows.join(best, on, "left").select(
        *kept, F.col("m.key").alias("matched_key"), F.col("m.valid_from").alias("matched_since"), F.coalesce(F.col("m.action") == "block", F.lit(False)).alias("blocked")
    )


#: The list of the registered query.  Fixed values.
ENTRIES = [
    ("cheap-pills.example.net", "block", "2024-02-01"),
    ("cheap-pills.example.net", "allow", "2024-08-15"),
    ("cheap-pills.example.net", "block", "2024-10-01"),
    ("spam-farm.example.org", "block", "2024-01-01"),
    ("www.spam-farm.example.org", "allow", "2024-06-01"),
    ("tionsh.example.net/de", "block", "2024-03-01"),
    ("tionsh.example.net", "allow", "2024-04-01"),
    ("example.com/es", "block", "2024-05-01"),
    ("example.com/es", "allow", "2024-11-01"),
    ("blog.ththth.example.org", "block", "2024-07-01"),
]

#: Captures carry no date here; the query takes a day of 2024 from the page's number.
FETCHED = "date_add(DATE'2024-01-01', cast(pmod(page_id * 37, 366) as int))"


def report(spark, pages: DataFrame) -> DataFrame:
    entries = spark.createDataFrame(ENTRIES, "key string, action string, listed_at string").withColumn("listed_at", F.to_date("listed_at"))
    captures = pages.select("page_id", "url", F.expr(FETCHED).alias("fetched_at"))
    found = judge(captures, entries)
    return found.select("page_id", "url", F.col("fetched_at").cast("string").alias("fetched_at"), "url_host", "matched_key", F.col("matched_since").cast("string").alias("matched_since"), "blocked")


def sql() -> str:
    values = ", ".join(f"('{k}', '{a}', DATE '{d}')" for k, a, d in ENTRIES)
    return f"""
WITH e(key, action, valid_from) AS (VALUES {values}),
iv AS (SELECT *, lead(valid_from) OVER (PARTITION BY key ORDER BY valid_from) AS valid_to FROM e),
c AS (SELECT page_id, url, DATE '2024-01-01' + CAST(((page_id * 37) % 366 + 366) % 366 AS INTEGER) AS fetched_at,
             lower(regexp_extract(coalesce(url, ''), '{HOST}', 1)) AS host, lower(regexp_extract(coalesce(url, ''), '{SEGMENT}', 1)) AS seg,
             row_number() OVER () AS rid FROM pages),
m AS (SELECT c.rid, iv.key, iv.valid_from, iv.action,
             row_number() OVER (PARTITION BY c.rid ORDER BY len(string_split(split_part(iv.key, '/', 1), '.')) DESC, position('/' IN iv.key) > 0 DESC) AS rn
      FROM c JOIN iv ON (host = split_part(iv.key, '/', 1) OR ends_with(host, '.' || split_part(iv.key, '/', 1)))
                    AND (split_part(iv.key, '/', 2) = '' OR split_part(iv.key, '/', 2) = seg)
                    AND fetched_at >= valid_from AND (valid_to IS NULL OR fetched_at < valid_to))
SELECT page_id, url, CAST(CAST(fetched_at AS DATE) AS VARCHAR) AS fetched_at, host AS url_host, m.key AS matched_key, CAST(m.valid_from AS VARCHAR) AS matched_since,
       coalesce(m.action = 'block', false) AS blocked
FROM c LEFT JOIN m ON c.rid = m.rid AND m.rn = 1"""
