"""URL filters by a temporal list join (DataFrame functions only).

A list's history is a table of dated entries (list_key, day, action 'add' or 'remove'). Entries become
validity intervals ``[from_day, to_day)``, and an as-of join decides every capture by the entries that
were active on its fetch day. A key is a host, a parent domain, or host/first path segment.

Each capture looks up its few keys by an equi-join; the interval test is the residual. A hot host is one
hot key on the captures' side of a sort-merge join, which adaptive execution splits, or meets a broadcast
where Spark has measured the intervals as small.

Defined cases: a null or unparsable URL has no key and is allowed; several entries of one key and day act
as one, and 'add' wins; 'remove' without an earlier 'add' has no effect; entries with a null key or day
are ignored; rows that repeat a capture keep their own verdicts; empty tables give empty results.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def host_of(url: Column) -> Column:
    """Lower-case host without user and port; empty where there is none."""
    return F.lower(F.regexp_extract(F.coalesce(url, F.lit("")), r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]+)", 1))


def keys_of(url: Column) -> Column:
    """Host, its parent domains of two or more labels, and host/first path segment."""
    host = host_of(url)
    labels = F.split(host, r"\.")
    n = F.size(labels)
    parents = F.transform(
        F.sequence(F.lit(1), F.greatest(F.lit(1), n - 1)), lambda i: F.array_join(F.slice(labels, i, n), ".")
    )
    segment = F.regexp_extract(F.coalesce(url, F.lit("")), r"^[^/]*//[^/?#]*/([^/?#]+)", 1)
    paths = F.when(segment != "", F.array(F.concat(host, F.lit("/"), segment))).otherwise(F.array().cast("array<string>"))
    return F.when(host == "", F.array().cast("array<string>")).otherwise(F.array_distinct(F.concat(parents, paths)))


def validity_intervals(entries: DataFrame) -> DataFrame:
    """``entries``: list_key, day, action. Returns list_key, from_day, to_day (null: still active)."""
    days = entries.where("list_key is not null and day is not null").groupBy("list_key", "day")
    days = days.agg(F.max((F.col("action") == "add").cast("int")).alias("on"))
    later = Window.partitionBy("list_key").orderBy("day")
    days = days.withColumn("was", F.lag("on", 1, 0).over(later)).where("`on` <> was")  # changes of state only
    days = days.withColumn("to_day", F.lead("day").over(later))
    return days.where("`on` = 1").select("list_key", F.col("day").alias("from_day"), "to_day")


def judge_urls(captures: DataFrame, entries: DataFrame, id_col: str = "page_id", url_col: str = "url", day_col: str = "fetch_day") -> DataFrame:
    """One row per capture: id, url, fetch_day, host, n_active, blocked, matched_key (the longest, then by code point), since_day."""
    seen = captures.select(F.col(id_col).alias("id"), F.col(url_col).alias("url"), F.col(day_col).alias("fetch_day"))
    spans = validity_intervals(entries)
    asked = seen.select("id", "url", "fetch_day", F.explode(keys_of(F.col("url"))).alias("list_key")).distinct()
    hits = asked.join(spans, "list_key").where("from_day <= fetch_day and (to_day is null or fetch_day < to_day)")
    best = F.max(F.struct(F.length("list_key").alias("n"), F.col("list_key").alias("k"), F.col("from_day").alias("d")))
    hits = hits.groupBy("id", "url", "fetch_day").agg(F.count(F.lit(1)).alias("n_active"), best.alias("best"))
    c, h = seen.alias("c"), hits.alias("h")
    same = F.col("c.id").eqNullSafe(F.col("h.id")) & F.col("c.url").eqNullSafe(F.col("h.url")) & F.col("c.fetch_day").eqNullSafe(F.col("h.fetch_day"))
    return c.join(h, same, "left").select(
        F.col("c.id").alias(id_col),
        F.col("c.url").alias("url"),
        F.col("c.fetch_day").alias("fetch_day"),
        host_of(F.col("c.url")).alias("host"),
        F.coalesce("n_active", F.lit(0)).cast("long").alias("n_active"),
        F.col("n_active").isNotNull().alias("blocked"),
        F.col("best.k").alias("matched_key"),
        F.col("best.d").alias("since_day"),
    )
