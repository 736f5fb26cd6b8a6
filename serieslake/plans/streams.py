"""Stream queries run over what is there now; their final state equals a batch query."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from ..operators import baselines as B
from ..operators import search as Q
from ..session import cut, shared_folder
from ..sources import store
from ..streaming import series as ST
from . import collections as C
from .registry import Tables, query
from .similarity import _answers, _nearest, sql


def _fresh(t: Tables, what: str) -> str:
    return f"{shared_folder(t.spark)}/{what}-{uuid.uuid4()}"


def _events(t: Tables):
    # events.parquet is a single file or a folder; a stream reads folders, so its rows are put into one
    path = _fresh(t, "events")
    t.events.write.parquet(path)
    return ST.stream_events(t.spark, path)


def _table(t: Tables, df, mode: str = "complete"):
    return ST.run_to_table(df, f"stream_{uuid.uuid4().hex}", mode, _fresh(t, "stream"))


@query("SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL")
def st_tumbling(t: Tables):
    got = _table(t, ST.windowed(_events(t), "tumbling", "1 day"))
    return got.select(F.date_format("win.start", "yyyy-MM-dd").alias("day"), "event_type", "n", F.round("total", 4).alias("total"))


@query("SELECT strftime(h, '%Y-%m-%d %H') AS start, event_type, count(*) AS n FROM (SELECT event_type, unnest([time_bucket(INTERVAL 6 HOUR, ts), time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL 6 HOUR]) AS h FROM events) GROUP BY ALL")
def st_sliding(t: Tables):
    got = _table(t, ST.windowed(_events(t), "sliding", "12 hours", "6 hours"))
    return got.select(F.date_format("win.start", "yyyy-MM-dd HH").alias("start"), "event_type", "n")


@query("""SELECT user_id, count(*) AS sessions, CAST(max(n) AS BIGINT) AS most FROM (
  SELECT user_id, s, count(*) AS n FROM (SELECT user_id, sum(CASE WHEN gap IS NULL OR gap >= 86400000000 THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s
    FROM (SELECT user_id, ts, event_id, epoch_us(ts) - epoch_us(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)) AS gap FROM events)) GROUP BY ALL) GROUP BY user_id""")
def st_session(t: Tables):
    got = _table(t, ST.windowed(_events(t), "session", "24 hours", keys=("user_id",)))
    return got.groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.max("n").alias("most"))


@query("""SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, event_type, count(*) AS n FROM events
WHERE event_id % 10 <> 9 OR time_bucket(INTERVAL 1 DAY, ts) + INTERVAL 1 DAY > (SELECT max(ts) - INTERVAL 1 HOUR FROM events WHERE event_id % 10 <> 9)
GROUP BY ALL""")
def st_late_drop(t: Tables):
    """Every tenth event comes after all others: those of windows that the watermark has closed are dropped, the others count."""
    feed, out, at = (_fresh(t, what) for what in ("events", "windows", "stream"))
    late = F.col("event_id") % 10 == 9
    for part in (~late, late):
        t.events.where(part).write.mode("append").parquet(feed)
        got = ST.run_to_folder(ST.windowed(ST.stream_events(t.spark, feed), "tumbling", "1 day"), out, "update", at)
    return got.groupBy(F.date_format("win.start", "yyyy-MM-dd").alias("day"), "event_type").agg(F.max("n").alias("n"))


@query("""SELECT p.user_id, v.event_id AS first_id, p.event_id AS then_id FROM events v JOIN events p ON v.user_id = p.user_id
AND v.event_type = 'view' AND p.event_type = 'purchase' AND p.ts BETWEEN v.ts AND v.ts + INTERVAL 12 HOUR""")
def st_interval_join(t: Tables):
    """Purchases of a user within twelve hours after a view."""
    events = _events(t)
    got = ST.interval_join(events.where("event_type = 'view'"), events.where("event_type = 'purchase'"), "user_id", "12 hours")
    return _table(t, got, "append").select("user_id", "first_id", "then_id")


@query("SELECT DISTINCT event_type, user_id FROM events")
def st_dedup(t: Tables):
    return _table(t, _events(t).select("event_type", "user_id").dropDuplicates(), "append")


@query("SELECT strftime(time_bucket(INTERVAL 1 DAY, ts), '%Y-%m-%d') AS day, user_id, round(sum(CASE WHEN hour(ts) < 12 THEN coalesce(value, 0.0) ELSE 0 END), 4) AS am, round(sum(CASE WHEN hour(ts) >= 12 THEN coalesce(value, 0.0) ELSE 0 END), 4) AS pm FROM events GROUP BY ALL")
def st_window_series(t: Tables):
    """A user's days grow with the data, so they go to files, not into a table on the driver; a later batch's row counts."""
    out = ST.run_to_folder(ST.window_series(_events(t), "1 day", 2), _fresh(t, "windows"), "update", _fresh(t, "stream"))
    got = out.groupBy("start", "user_id").agg(F.max_by("values", "batch").alias("values"))
    v = F.col("values")
    return got.select(F.date_format("start", "yyyy-MM-dd").alias("day"), "user_id", F.round(F.get(v, F.lit(0)), 4).alias("am"), F.round(F.get(v, F.lit(1)), 4).alias("pm"))


@query("SELECT user_id, event_id AS series_id, round(list_sum(v), 4) AS total FROM (SELECT user_id, event_id, list(coalesce(value, 0.0)) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS 7 PRECEDING) AS v, row_number() OVER (PARTITION BY user_id ORDER BY ts DESC, event_id DESC) AS r FROM events) WHERE r = 1 AND len(v) = 8")
def st_ring_series(t: Tables):
    got = _table(t, ST.ring_series(_events(t), 8), "append")
    last = got.groupBy("user_id").agg(F.max_by("values", "series_id").alias("v"), F.max("series_id").alias("series_id"))
    return last.select("user_id", "series_id", F.round(F.aggregate("v", F.lit(0.0), lambda a, x: a + x), 4).alias("total"))


@query(sql("walk64", _nearest(1)))
def st_append_replay(t: Tables):
    """Two thirds of the index arrive as a stream; the same batch comes twice."""
    base, ask = C.parted(t, "walk64")
    path, feed = _fresh(t, "index"), _fresh(t, "feed")
    store.save(B.build(base.where("series_id % 3 = 0"), C.CONFIGS["walk64"], "level"), path)
    base.where("series_id % 3 <> 0").write.parquet(feed)
    stream = lambda: t.spark.readStream.schema(base.schema).parquet(feed)
    for _ in range(2):  # a second run without its checkpoint replays batch 0
        ST.append_stream(stream(), path, _fresh(t, "stream")).awaitTermination()
    return _answers(Q.nn1(store.load(t.spark, path), ask))


@query(sql("walk64", _nearest(1)))
def w13_standing_queries(t: Tables):
    ask = C.parted(t, "walk64")[1].withColumnRenamed("query_id", "series_id")
    feed, got = _fresh(t, "feed"), []
    ask.write.parquet(feed)
    stream = t.spark.readStream.schema(ask.schema).parquet(feed)
    ST.standing_queries(stream, C.index(t, "walk64"), got, _fresh(t, "stream")).awaitTermination()
    return cut(_answers(got[0]))
