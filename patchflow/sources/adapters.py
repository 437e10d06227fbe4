"""What stands for video, captions and gates in the given tables (pure projections and aggregates)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

EPOCH = 1704067200  # 2024-01-01, first day of the event stream
FRAME_SECONDS, FRAMES, CLIPS = 40500, 64, 16
GRID = (4, 5)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def cents(column) -> F.Column:
    return F.round(F.col(column).cast("double") * 100).cast("long")


def tile_facts_events(spark: SparkSession, sf_dir: str, frame_seconds: float = FRAME_SECONDS) -> DataFrame:
    """(clip_id, frame_idx, row, col, n, c) per event: the facts of a tile before they are summed; the clock's step may be finer."""
    types = table(spark, sf_dir, "events").select("event_type").distinct()
    order = types.select("event_type", (F.row_number().over(Window.orderBy("event_type")) - 1).cast("int").alias("col"))  # five names
    e = table(spark, sf_dir, "events").select("user_id", "ts", "event_type", cents("value").alias("c"), F.get_json_object("props", "$.k").cast("int").alias("k"))
    return e.join(F.broadcast(order), "event_type").select(
        (F.col("user_id") % CLIPS).alias("clip_id"),
        F.floor((F.unix_timestamp(F.col("ts").cast("timestamp")) - EPOCH) / frame_seconds).cast("int").alias("frame_idx"),
        F.expr("cast(k div 25 as int)").alias("row"),
        "col",
        F.lit(1).cast("long").alias("n"),
        "c",
    )


def tile_facts_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Suppliers as clips, months as frames; a larger feed of the same shape."""
    li = table(spark, sf_dir, "lineitem")
    return li.select(
        F.col("l_suppkey").alias("clip_id"),
        ((F.year("l_shipdate") - 1995) * 12 + F.month("l_shipdate") - 1).cast("int").alias("frame_idx"),
        (F.col("l_partkey") % 4).cast("int").alias("row"),
        (F.col("l_linenumber") - 1).cast("int").alias("col"),
        F.col("l_quantity").cast("long").alias("n"),
        cents("l_extendedprice").alias("c"),
    )


def tile_changes(facts: DataFrame, frames: int) -> DataFrame:
    """(clip_id, frame_idx, row, col, dn, dv): change of count and value against the frame before.

    A fact counts with plus in its frame and with minus in the next, so a tile that vanishes
    leaves a change and no self-join is needed; one exchange.
    """
    key = ["clip_id", "frame_idx", "row", "col"]
    after = facts.select("clip_id", (F.col("frame_idx") + 1).alias("frame_idx"), "row", "col", (-F.col("n")).alias("n"), (-F.col("c")).alias("c")).filter(F.col("frame_idx") < frames)
    return facts.unionByName(after).groupBy(*key).agg(F.sum("n").alias("dn"), F.sum("c").alias("dv"))


def frames_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each vector as an 8 x 8 luma raster; 64 vectors a clip."""
    e = table(spark, sf_dir, "embeddings")
    return e.select(
        F.expr("vec_id div 64").alias("clip_id"),
        (F.col("vec_id") % 64).cast("int").alias("frame_idx"),
        F.lit(8).alias("height"),
        F.lit(8).alias("width"),
        F.transform("embedding", lambda x: F.round(x.cast("double") * 1000).cast("int")).alias("pixels"),
    )


def timeline_conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(video_id, seg_idx, start_s, end_s, caption): assistant turns on the clock of reading time."""
    w = Window.partitionBy("conv_id").orderBy("turn")
    c = table(spark, sf_dir, "conversations").withColumn("cost", F.ceil(F.length("text") / 15).cast("long"))
    c = c.withColumn("end_s", F.sum("cost").over(w)).withColumn("start_s", F.col("end_s") - F.col("cost"))
    said = c.filter(F.col("role") == "assistant")
    return said.select(F.col("conv_id").alias("video_id"), (F.row_number().over(w) - 1).cast("int").alias("seg_idx"), "start_s", "end_s", F.col("text").alias("caption"))


def gate_events(spark: SparkSession, sf_dir: str, window: int = 4) -> DataFrame:
    """(video_id, pos, t_s, speak, memory, gap_s): truth and features from strictly earlier rows."""
    w = Window.partitionBy("video_id").orderBy("t_s", "event_id")
    e = table(spark, sf_dir, "events").select(
        (F.col("user_id") % CLIPS).alias("video_id"), "event_id", F.unix_timestamp(F.col("ts").cast("timestamp")).alias("t_s"), cents("value").alias("c"), ((F.col("event_type") == "purchase") & (cents("value") >= 10000)).cast("int").alias("speak")
    )
    past = sum((F.coalesce(F.lag("c", j).over(w), F.lit(0)) * (window + 1 - j) for j in range(1, window + 1)), F.lit(0).cast("long"))
    return e.select("video_id", (F.row_number().over(w) - 1).cast("int").alias("pos"), "t_s", "speak", past.alias("memory"), F.coalesce(F.col("t_s") - F.lag("t_s").over(w), F.lit(0)).alias("gap_s"))


def samples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Caption corpus: documents with labels where known."""
    d, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    return d.join(labels, "doc_id", "left").select(F.col("doc_id").alias("sample_id"), "text", F.col("source").alias("domain"), "lang", "n_chars", F.ceil(F.col("n_chars") / 15).cast("long").alias("duration_s"), "quality", "toxic")
