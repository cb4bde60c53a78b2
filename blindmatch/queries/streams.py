"""Queries of streams; each runs over all available files and is compared with the batch answer."""

from __future__ import annotations

from pyspark.sql import functions as F

from blindmatch.operators import clustering
from blindmatch.plans.lineage import shared_path
from blindmatch.queries import workloads as W
from blindmatch.queries.registry import query
from blindmatch.sources import roster as R
from blindmatch.sources.tables import load
from blindmatch.streaming import arrival

_TS = "strftime(w, '%Y-%m-%d %H:%M:%S')"


def _typed(s, d):
    """Event time has to be a timestamp with the session's zone."""
    return load(s, d, "events", "event_id", "ts", "user_id", "event_type").withColumn("ts", F.col("ts").cast("timestamp"))


def _events(s, d):
    """``events`` as a stream of files. A last event far ahead closes all windows in append mode."""
    e = _typed(s, d)
    path = shared_path(s, "events")
    last = e.agg(F.lit(-1).cast("long").alias("event_id"), (F.max("ts") + F.expr("interval 30 days")).alias("ts"), F.lit(-1).cast("long").alias("user_id"), F.lit("end").alias("event_type"))
    e.coalesce(1).write.parquet(path)
    last.coalesce(1).write.mode("append").parquet(path)
    return arrival.file_stream(s, path, e.schema, 1)


def _text(df, c="from_ts"):
    return df.where(F.col("n") > 0).withColumn(c, F.date_format(c, "yyyy-MM-dd HH:mm:ss"))


@query("stream_tumbling", f"SELECT {_TS} AS from_ts, event_type, count(*) AS n FROM (SELECT time_bucket(INTERVAL 1 DAY, ts) AS w, event_type FROM events) GROUP BY ALL")
def stream_tumbling(s, d):
    return _text(arrival.run_to_table(arrival.tumbling(_events(s, d), "1 day", "365 days"), "complete")).where("event_type <> 'end'")


@query("stream_sliding", f"SELECT {_TS} AS from_ts, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 12 HOUR, ts), time_bucket(INTERVAL 12 HOUR, ts) - INTERVAL 12 HOUR]) AS w FROM events) GROUP BY ALL")
def stream_sliding(s, d):
    out = arrival.run_to_table(arrival.sliding(_events(s, d).where("event_type <> 'end'"), "1 day", "12 hours", "365 days"), "complete")
    return _text(out)


@query("stream_session", """WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 12 HOUR THEN 0 ELSE 1 END AS fresh FROM events),
n AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS from_ts, count(*) AS n FROM n GROUP BY user_id, k""")
def stream_session(s, d):
    out = arrival.run_to_table(arrival.sessions(_events(s, d).where("event_type <> 'end'"), "12 hours", "365 days"), "complete")
    return _text(out)


@query("stream_late_rows", f"""WITH c AS (SELECT min(ts) + (max(ts) - min(ts)) / 2 AS middle FROM events)
SELECT {_TS} AS from_ts, count(*) AS n FROM (SELECT time_bucket(INTERVAL 1 DAY, ts) AS w FROM events, c WHERE ts >= middle) GROUP BY ALL""")
def stream_late_rows(s, d):
    """Events of the second half arrive first; those of the first half come behind the watermark and are dropped.

    A batch drops by the watermark that the batch before it had for eviction, so a batch without new rows lies between."""
    e = _typed(s, d)
    ends = e.agg(F.min("ts").alias("a"), F.max("ts").alias("b")).first()
    middle = ends.a + (ends.b - ends.a) / 2
    path = shared_path(s, "late")
    marker = e.limit(1).withColumn("ts", F.lit(ends.b)).withColumn("event_type", F.lit("marker"))
    for part in (e.where(F.col("ts") >= F.lit(middle)), marker, marker, e.where(F.col("ts") < F.lit(middle))):
        part.coalesce(1).write.mode("append").parquet(path)
    stream = arrival.file_stream(s, path, e.schema, 1).withWatermark("ts", "1 hour")
    day = F.window("ts", "1 day")
    counted = stream.groupBy(day).agg(F.sum((F.col("event_type") != "marker").cast("long")).alias("n"))
    out = arrival.run_to_table(counted.select(F.col("window.start").alias("from_ts"), "n"), "update", keep=["from_ts"])
    return _text(out)


@query("stream_dedup", "SELECT DISTINCT user_id, event_type FROM events")
def stream_dedup(s, d):
    e = _events(s, d).where("event_type <> 'end'").withWatermark("ts", "365 days")
    return arrival.run_to_table(e.dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type"))


@query("stream_static_join", "SELECT e.event_id, c.c_mktsegment FROM events e JOIN customer c ON e.user_id = c.c_custkey")
def stream_static_join(s, d):
    c = load(s, d, "customer", "c_custkey", "c_mktsegment")
    return arrival.run_to_table(_events(s, d).join(c, F.col("user_id") == F.col("c_custkey")).select("event_id", "c_mktsegment"))


@query("stream_join_interval", """SELECT v.event_id AS view_id, p.event_id AS purchase_id FROM events v JOIN events p
ON v.user_id = p.user_id AND v.event_type = 'view' AND p.event_type = 'purchase' AND p.ts > v.ts AND p.ts <= v.ts + INTERVAL 6 HOUR""")
def stream_join_interval(s, d):
    v = _events(s, d).where("event_type = 'view'").withWatermark("ts", "1 day").select(F.col("event_id").alias("view_id"), F.col("ts").alias("vts"), F.col("user_id").alias("vu"))
    p = _events(s, d).where("event_type = 'purchase'").withWatermark("ts", "1 day").select(F.col("event_id").alias("purchase_id"), F.col("ts").alias("pts"), F.col("user_id").alias("pu"))
    on = F.expr("vu = pu and pts > vts and pts <= vts + interval 6 hours")
    return arrival.run_to_table(v.join(p, on).select("view_id", "purchase_id"))


def _party_files(s, d, p=3):
    m = W.masked(W.parties(s, d, p, 20))
    path = shared_path(s, "parties")
    for i in range(1, p + 1):
        m.where(F.col("party") == i).coalesce(1).write.mode("append").parquet(path)
    return m, path


_SAME = f"WITH {R.sql_parties(3)} SELECT count(*) AS records, CAST(0 AS BIGINT) AS differ FROM parties"


def _against_batch(m, found):
    batch = clustering.cluster_early(m, ord=[1, 2, 3], mode="block")
    both = batch.join(found.select("rec_id", F.col("cluster_id").alias("other")), "rec_id")
    return both.agg(F.count(F.lit(1)).alias("records"), F.sum((F.col("cluster_id") != F.col("other")).cast("long")).alias("differ"))


@query("stream_party_arrival", _SAME)
def stream_party_arrival(s, d):
    m, path = _party_files(s, d)
    return _against_batch(m, arrival.cluster_arriving_parties(s, path, m.schema))


@query("stream_state_blocks", _SAME)
def stream_state_blocks(s, d):
    m, path = _party_files(s, d)
    stream = arrival.file_stream(s, path, m.schema).select("block", "party", "rec_id", "words")
    return _against_batch(m, arrival.run_to_table(arrival.cluster_arriving_records(stream)))
