"""Timed captions to causal speak/silent targets, and what a gate may see."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def to_gate(timeline: DataFrame, hz: int = 1) -> DataFrame:
    """(video_id, pos, t_s, target, response, prefix_end_s): speak at each segment start, silent elsewhere.

    Candidates stand every 1/hz seconds up to the last end; captions that start together make one
    target with the responses in segment order.  The prefix ends at the decision: no later row is used.
    """
    ends = timeline.groupBy("video_id").agg(F.max("end_s").alias("dur"))
    grid = ends.select("video_id", F.explode(F.sequence(F.lit(0), F.col("dur") * hz)).alias("pos")).withColumn("t_s", F.expr(f"pos div {hz}"))
    starts = timeline.groupBy("video_id", F.col("start_s").alias("t_s")).agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("seg_idx", "caption"))), lambda x: x["caption"]), "\n").alias("response"))
    first = grid.withColumn("pos", F.col("pos").cast("long")).join(starts, ["video_id", "t_s"], "left")
    speak = F.col("response").isNotNull() & (F.col("pos") % hz == 0)
    return first.select("video_id", "pos", "t_s", F.when(speak, "speak").otherwise("silent").alias("target"), F.when(speak, F.col("response")).otherwise("").alias("response"), F.col("t_s").alias("prefix_end_s"))


def bad_times(timeline: DataFrame, durations: DataFrame) -> DataFrame:
    """Segments that break 0 <= start < end <= duration."""
    return timeline.join(durations, "video_id", "left").filter(~((F.col("start_s") >= 0) & (F.col("start_s") < F.col("end_s")) & (F.col("end_s") <= F.col("duration_s"))))


def repeated_segments(timeline: DataFrame, share: float = 0.8) -> DataFrame:
    """Segments whose words mostly equal those of the segment before (set overlap of at least ``share``)."""
    w = Window.partitionBy("video_id").orderBy("seg_idx")
    words = F.array_distinct(F.split(F.lower("caption"), " "))
    t = timeline.withColumn("w", words).withColumn("b", F.lag("w").over(w)).filter("b is not null")
    overlap = F.size(F.array_intersect("w", "b")) / F.size(F.array_union("w", "b"))
    return t.select("video_id", "seg_idx", F.round(overlap, 6).alias("overlap")).filter(F.col("overlap") >= share)


def balance_silence(targets: DataFrame, guard: int, keep: float) -> DataFrame:
    """Drops silent positions more than ``guard`` away from any speak, but for an md5 share; speak rows all stay."""
    from .curate import bucket

    # a frame of a few positions: one that runs to the end of the sequence is built anew for every row
    w = Window.partitionBy("video_id").orderBy("pos").rangeBetween(-guard, guard)
    near = F.coalesce(F.max(F.col("speak") == 1).over(w), F.lit(False))
    return targets.withColumn("near", near).filter(F.col("near") | (bucket("video_id", "pos") < int(keep * 2**32)))


def latest_before(queries: DataFrame, rows: DataFrame, n: int) -> DataFrame:
    """As-of join: for each (video_id, t_s, query) the positions of the n latest rows at or before t_s.

    Union and a window of bounded memory instead of a range join: rows carry themselves to the queries.
    """
    both = queries.select("video_id", "t_s", F.lit(1).alias("kind"), F.col("query").alias("id")).unionByName(rows.select("video_id", "t_s", F.lit(0).alias("kind"), F.col("pos").cast("long").alias("id")))
    w = Window.partitionBy("video_id").orderBy("t_s", "kind", "id")
    seen = F.sum(F.when(F.col("kind") == 0, 1).otherwise(0)).over(w.rowsBetween(Window.unboundedPreceding, 0))
    return both.withColumn("seen", seen).filter("kind = 1").select("video_id", "t_s", F.col("id").alias("query"), F.greatest(F.col("seen") - n, F.lit(0)).alias("from_pos"), (F.col("seen") - 1).alias("to_pos"))
