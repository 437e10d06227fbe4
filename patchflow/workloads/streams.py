"""Streaming workloads over all events; each has a batch twin in SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..sources import adapters as A
from ..streaming import flows
from ..streaming.gate import _drain, event_stream


def st_dedup_watermark(spark, d):
    """Every event twice in the stream, once behind the clean-up."""
    s = event_stream(spark, d)
    twice = s.select("event_id", "user_id", "ts").withColumn("again", F.explode(F.array(F.lit(0), F.lit(1))))
    return _drain(spark, flows.deduplicated(twice), "append").select("event_id", "user_id")


def join_stream_static(spark, d):
    meta = A.table(spark, d, "labels").select(F.col("doc_id").alias("user_id"), "quality")
    out = _drain(spark, flows.with_meta(event_stream(spark, d).select("event_id", "user_id"), meta, "user_id"), "append")
    return out.select("event_id", "user_id", F.coalesce("quality", F.lit(-1)).alias("quality"))


def join_stream_stream(spark, d):
    """Sign-ups as queries: events of the same half match in the six hours before."""
    s = event_stream(spark, d)
    video = F.col("user_id") % A.CLIPS
    q = s.filter("event_type = 'signup'").select(video.alias("q_video"), F.col("event_id").alias("q_id"), F.col("ts").alias("q_ts"))
    r = event_stream(spark, d).select(video.alias("video_id"), "event_id", "ts")
    return _drain(spark, flows.answers(q, r, 6 * 3600), "append")


def st_sliding_counts(spark, d):
    """Counts of six hours, each hour."""
    s = event_stream(spark, d).groupBy(F.window("ts", "6 hours", "1 hour")).agg(F.count("*").alias("n"))
    return _drain(spark, s, "complete").select(F.unix_timestamp("window.start").alias("window_start"), "n")


def st_timer_ttl(spark, d):
    """Each time a half match said nothing for six hours: its last row's time and the rows since the silence before."""
    rows = event_stream(spark, d).select((F.col("user_id") % A.CLIPS).alias("video_id"), "ts")
    return _drain(spark, flows.silent_sequences(rows, 6 * 3600), "append")


QUERIES = {f.__name__: f for f in (st_dedup_watermark, join_stream_static, join_stream_stream, st_sliding_counts, st_timer_ttl)}
SQL = {
    "st_dedup_watermark": "select event_id, user_id from events",
    "join_stream_static": "select event_id, user_id, coalesce(quality, -1) quality from events left join labels on doc_id = user_id",
    "join_stream_stream": "select q.event_id q_id, q.user_id % 16 q_video, r.event_id from events q join events r on q.user_id % 16 = r.user_id % 16 and r.ts < q.ts and r.ts >= q.ts - interval 6 hours where q.event_type = 'signup'",
    "st_sliding_counts": "select w window_start, count(*) n from (select unnest(range(floor(epoch(ts))::bigint // 3600 * 3600 - 5 * 3600, floor(epoch(ts))::bigint // 3600 * 3600 + 1, 3600)) w from events) group by 1",
    # a silence ends a segment; the last segment of a match is told if the watermark, a day behind, has passed its limit
    "st_timer_ttl": """with e as (select user_id % 16 video_id, epoch_us(ts) // 1000 ms from events), g as (select *, lead(ms) over w nx, row_number() over w r from e window w as (partition by video_id order by ms)),
      s as (select *, coalesce(sum((coalesce(nx - ms >= 21600000, false))::int) over (partition by video_id order by r rows between unbounded preceding and 1 preceding), 0) seg from g),
      t as (select video_id, seg, max(ms) last_ms, count(*) n, bool_or(nx is null) final from s group by 1, 2)
      select video_id, last_ms, n from t where not final or last_ms + 21600000 < (select max(ms) - 86400000 from e)""",
}
