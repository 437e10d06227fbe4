"""Event stream and live gate.

The source casts ``timestamp_ntz`` to ``timestamp`` (watermarks need it).  The gate keeps the
last values of a sequence and the position in keyed state, so state is bounded by the number of
sequences; a sequence silent for the watermark's delay could be dropped by a timeout.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..shipping import ship_package
from ..shared import scratch_path
from ..sources import adapters as A

WEIGHTS = (4, 3, 2, 1)


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """events as a file stream with a watermark."""
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    # a stream reads folders: the table may be one file or a folder of files
    s = spark.readStream.schema(schema).parquet(f"{path}*")
    return s.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "1 day")


def gate_step(key, batches: Iterator, state, tau: int = 0):
    """One micro-batch of one sequence: fires on what strictly earlier rows leave in memory."""
    import pandas as pd

    pos, past = (state.get[0], list(state.get[1])) if state.exists else (0, [])
    rows = pd.concat(list(batches)).sort_values(["t_s", "event_id"])
    out = []
    for t, c in zip(rows["t_s"].tolist(), rows["c"].tolist()):
        memory = sum(w * x for w, x in zip(WEIGHTS, past))
        if memory >= tau:
            out.append((key[0], pos, t, memory))
        past = [c, *past][: len(WEIGHTS)]
        pos += 1
    state.update((pos, past))
    yield pd.DataFrame(out, columns=["video_id", "pos", "t_s", "memory"]).astype({"video_id": "int64", "pos": "int32", "t_s": "int64", "memory": "int64"})


def live_gate(stream: DataFrame, tau: int) -> DataFrame:
    """(video_id, pos, t_s, memory) of each decision to speak."""
    from pyspark.sql.streaming.state import GroupStateTimeout

    ship_package(stream.sparkSession)
    rows = stream.select((F.col("user_id") % A.CLIPS).alias("video_id"), "event_id", F.unix_timestamp("ts").alias("t_s"), A.cents("value").alias("c"))

    def step(key, batches, state):
        yield from gate_step(key, batches, state, tau)

    return rows.groupBy("video_id").applyInPandasWithState(step, "video_id long, pos int, t_s long, memory long", "pos int, past array<long>", "append", GroupStateTimeout.NoTimeout)


def _drain(spark: SparkSession, stream: DataFrame, mode: str) -> DataFrame:
    """Runs a stream over all that is there and returns the sink as a table.

    Appended rows go to files in the shared folder with their checkpoint beside them, so neither the driver's
    memory nor a lost executor matters; only complete aggregates, a row per group, go to the memory sink.
    """
    name = f"sink_{uuid.uuid4().hex}"
    if mode == "append":
        root = scratch_path(spark, name)
        w = stream.writeStream.format("parquet").option("path", f"{root}/rows").option("checkpointLocation", f"{root}/state").outputMode(mode)
    else:
        w = stream.writeStream.format("memory").queryName(name).outputMode(mode)
    w.trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{root}/rows") if mode == "append" else spark.table(name)


def run_available(spark: SparkSession, sf_dir: str, tau: int) -> DataFrame:
    return _drain(spark, live_gate(event_stream(spark, sf_dir), tau), "append")


def tumbling_available(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts per day and type by a watermarked window."""
    s = event_stream(spark, sf_dir).groupBy(F.window("ts", "1 day"), "event_type").count()
    return _drain(spark, s, "complete").select("event_type", F.unix_timestamp("window.start").alias("window_start"), F.col("count").alias("n"))
