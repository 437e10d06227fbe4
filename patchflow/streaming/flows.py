"""Streams around the gate: clean-up, joins, timers and restarts.

State is bounded everywhere: by the watermark (duplicates, joins) or by one entry per live sequence
(timers), which goes when the sequence has been silent for the limit.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..shipping import ship_package
from .gate import event_stream


def deduplicated(stream: DataFrame, keys: tuple[str, ...] = ("event_id",)) -> DataFrame:
    """The first row of each key inside the watermark; the stream must carry one."""
    return stream.dropDuplicatesWithinWatermark(list(keys))


def with_meta(stream: DataFrame, meta: DataFrame, on: str) -> DataFrame:
    """Stream-static join: rows without meta stay, with nulls."""
    return stream.join(meta, on, "left")


def answers(queries: DataFrame, rows: DataFrame, seconds: int) -> DataFrame:
    """Stream-stream join: rows of the same video in the ``seconds`` before a query.

    queries are (q_video, q_id, q_ts), rows (video_id, event_id, ts); both carry watermarks, and the time bound
    lets state go.
    """
    # a row stands in its stretch of ``seconds``, a query in its own and the one before: a pair meets once, and state is searched by video and stretch
    stretch = lambda ts: F.floor(F.unix_timestamp(ts) / int(seconds))
    asked = queries.withColumn("q_stretch", F.explode(F.array(stretch("q_ts"), stretch("q_ts") - 1)))
    near = F.expr(f"video_id = q_video and stretch = q_stretch and ts < q_ts and ts >= q_ts - interval {int(seconds)} seconds")
    return asked.join(rows.withColumn("stretch", stretch("ts")), near).select("q_id", "q_video", "event_id")


def silence_step(key, batches: Iterator, state, limit_ms: int):
    """Keeps the last time and the count of a sequence; a gap in the rows or a timeout emits both and starts anew."""
    import pandas as pd

    if state.hasTimedOut:
        last, n = state.get
        state.remove()
        yield pd.DataFrame({"video_id": [key[0]], "last_ms": [last], "n": [n]})
        return
    last, n = state.get if state.exists else (None, 0)
    times = sorted(t for b in batches for t in b["ms"].tolist())
    gaps = []
    for t in times:
        if last is not None and t - last >= limit_ms:  # the gap came in with the rows that end it
            gaps.append((key[0], last, n))
            n = 0
        last, n = t if last is None else max(last, t), n + 1
    state.update((last, n))
    # the engine refuses a time at or before the watermark: a late row's timer fires at the next batch
    state.setTimeoutTimestamp(max(last + limit_ms, state.getCurrentWatermarkMs() + 1))
    yield pd.DataFrame(gaps, columns=["video_id", "last_ms", "n"]).astype("int64")


def silent_sequences(rows: DataFrame, limit_s: int) -> DataFrame:
    """(video_id, last_ms, n) for each time a sequence said nothing for ``limit_s`` of event time; n rows since the last.

    ``rows`` are (video_id, ts) with a watermark on ts.
    """
    from pyspark.sql.streaming.state import GroupStateTimeout

    ship_package(rows.sparkSession)
    limit = limit_s * 1000

    def step(key, batches, state):
        yield from silence_step(key, batches, state, limit)

    timed = rows.withColumn("ms", F.unix_millis("ts"))
    return timed.groupBy("video_id").applyInPandasWithState(step, "video_id long, last_ms long, n long", "last_ms long, n long", "append", GroupStateTimeout.EventTimeTimeout)


def rate_tiles(spark: SparkSession, per_second: int) -> DataFrame:
    """An endless feed of tiles for load tests, from the rate source."""
    v = F.col("value")
    r = spark.readStream.format("rate").option("rowsPerSecond", per_second).load()
    return r.select((v % 16).alias("clip_id"), "timestamp", ((v / 16) % 4).cast("int").alias("row"), ((v / 64) % 5).cast("int").alias("col"), F.abs(F.xxhash64(v) % 10000).alias("residual"))


def to_files(stream: DataFrame, path: str, checkpoint: str) -> None:
    """All that is there to Parquet, exactly once over restarts: files and checkpoint belong together."""
    stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).outputMode("append").trigger(availableNow=True).start().awaitTermination()


def late_rows(batch: DataFrame, delay_s: int) -> DataFrame:
    """Batch twin of the watermark over (batch_no, ts): rows that windowed counts drop, by micro-batch.

    A row is late if it is older than the greatest time of earlier batches less the delay.
    """
    from pyspark.sql import Window

    seen = batch.groupBy("batch_no").agg(F.max("ts").alias("m"))
    before = seen.select("batch_no", F.max("m").over(Window.orderBy("batch_no").rowsBetween(Window.unboundedPreceding, -1)).alias("mark"))  # a row per batch
    late = F.col("ts") < F.col("mark") - F.make_dt_interval(secs=F.lit(float(delay_s)))
    return batch.join(before, "batch_no").groupBy("batch_no").agg(F.count_if(late).alias("late"), F.count("*").alias("n"))


__all__ = ["answers", "deduplicated", "event_stream", "late_rows", "rate_tiles", "silence_step", "silent_sequences", "to_files", "with_meta"]
