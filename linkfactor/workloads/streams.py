"""Streams over the events table, each equal to its batch twin."""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import sources
from ..operators import smallrank
from ..runtime import generation, scratch
from ..streaming import events as st
from . import twins as S
from .model import as_side, columns_of, rounded
from .twins import REG, UNOBSERVED


def _text(name: str):
    """Window edges as text in UTC."""
    return F.date_format(F.col(f"w.{name}"), "yyyy-MM-dd HH:mm:ss").alias(f"w_{name}")


def _utc(s):
    s.conf.set("spark.sql.session.timeZone", "UTC")
    return s


def stream_tumbling(s, d):
    out = st.run_available(st.tumbling(st.event_stream(_utc(s), d)).withColumnRenamed("window", "w"), "complete")
    return out.select(_text("start"), "event_type", "n")


def stream_sliding(s, d):
    out = st.run_available(st.sliding(st.event_stream(_utc(s), d)).withColumnRenamed("window", "w"), "complete")
    return out.select(_text("start"), _text("end"), "n")


def stream_session(s, d):
    out = st.run_available(st.sessions(st.event_stream(_utc(s), d)).withColumnRenamed("session_window", "w"), "complete")
    return out.select("user_id", F.unix_micros("w.start").alias("start_us"), "n")


def stream_late_data(s, d):
    """Three files, the early days last: with a watermark of a day the windows of the last file are too late and dropped."""
    folder = scratch(_utc(s), "late")
    e = s.read.parquet(f"{d}/events.parquet")
    middle, end = "timestamp_ntz'2024-01-16 00:00:00'", "timestamp_ntz'2024-01-23 00:00:00'"
    for name, part in (("a", f"ts >= {middle} and ts < {end}"), ("b", f"ts >= {end}"), ("c", f"ts < {middle}")):
        e.where(part).coalesce(1).write.parquet(f"{folder}/{name}")
    schema = e.schema
    stream = st._typed(s.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{folder}/*"))
    daily = stream.withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return st.run_available(daily, "append").select(_text("start"), "n")


def stream_dedup(s, d):
    return st.run_available(st.deduplicated(st.event_stream(_utc(s), d)))


def stream_normal_system(s, d):
    h = columns_of(sources.events_as_observations(s, d))
    return rounded(st.run_available(st.normal_systems(st.event_stream(_utc(s), d), h), "complete").withColumnRenamed("row_id", "user_id"))


def stream_fold_in(s, d):
    """Users' vectors from their running systems against frozen columns."""
    h = generation(columns_of(sources.events_as_observations(s, d)), "frozen")
    change = st.fold_in_change(generation(smallrank.gram_columns(h), "gram"), REG, UNOBSERVED)
    return as_side(st.run_available(st.normal_systems(st.event_stream(_utc(s), d), h), "complete", change), "user_id", "w")


def stream_interval_join(s, d):
    e = st.event_stream(_utc(s), d)
    return st.run_available(st.interval_join(e.where("event_type = 'click'"), st.event_stream(s, d).where("event_type = 'purchase'")))


def stream_state(s, d):
    """Counts and sums per user kept by an own stateful operator; the last update of each user counts."""
    out = st.run_available(st.counts_with_state(st.event_stream(_utc(s), d)), "update")
    return rounded(out.groupBy("user_id").agg(F.max("n").alias("n"), F.max_by("total", "n").alias("total")), 4)


SQL = {
    "stream_tumbling": "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS w_start, event_type, count(*) AS n FROM events GROUP BY 1, 2",
    "stream_sliding": "WITH x AS (SELECT ts, date_trunc('day', ts) + CASE WHEN date_part('hour', ts) >= 12 THEN INTERVAL 12 HOUR ELSE INTERVAL 0 HOUR END AS half FROM events), y AS (SELECT half AS w FROM x UNION ALL SELECT half - INTERVAL 12 HOUR FROM x) SELECT strftime(w, '%Y-%m-%d %H:%M:%S') AS w_start, strftime(w + INTERVAL 24 HOUR, '%Y-%m-%d %H:%M:%S') AS w_end, count(*) AS n FROM y GROUP BY w",
    "stream_session": "WITH a AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 6 HOUR OR lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) IS NULL THEN 1 ELSE 0 END AS fresh, event_id FROM events), b AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS sess FROM a) SELECT user_id, epoch_us(min(ts)) AS start_us, count(*) AS n FROM b GROUP BY user_id, sess",
    "stream_late_data": "SELECT strftime(day, '%Y-%m-%d %H:%M:%S') AS w_start, n FROM (SELECT date_trunc('day', ts) AS day, count(*) AS n FROM events WHERE ts >= TIMESTAMP '2024-01-16 00:00:00' GROUP BY 1) WHERE day + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 1 DAY",
    "stream_dedup": "SELECT DISTINCT user_id, json_extract_string(props, '$.k')::bigint AS k FROM events",
    "stream_normal_system": f"WITH {S.E}, x AS (SELECT user_id AS row_id, json_extract_string(props, '$.k')::bigint AS col_id, 1.0::double AS y FROM events), {S.factors('h', 'e', 'col_id')}, {S.system('s', 'x', 'h')} SELECT row_id AS user_id, {S.rounded(['a00', 'a01', 'a11', 'b0', 'b1'])}, n FROM s",
    "stream_fold_in": f"WITH {S.E}, x AS (SELECT user_id AS row_id, json_extract_string(props, '$.k')::bigint AS col_id, 1.0::double AS y FROM events), {S.factors('h', 'e', 'col_id')}, {S.refit('w', 'x', 'h')} SELECT id AS user_id, round(f0, 6) + 0.0 AS w0, round(f1, 6) + 0.0 AS w1 FROM w",
    "stream_interval_join": "SELECT a.event_id AS left_id, b.event_id AS right_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR",
    "stream_state": "SELECT user_id, count(*) AS n, round(sum(value), 4) + 0.0 AS total FROM events GROUP BY user_id",
}
QUERIES = {k: globals()[k] for k in SQL}
