"""Motion and residual of patches by block matching against the frame before."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def patchify(frames: DataFrame, patch: int) -> DataFrame:
    """(clip_id, frame_idx, row, col, y, x, v): pixels with their tile."""
    p = frames.select("clip_id", "frame_idx", "width", F.posexplode("pixels").alias("i", "v"))
    y, x = F.expr("cast(i div width as int)"), (F.col("i") % F.col("width")).cast("int")
    return p.select("clip_id", "frame_idx", y.alias("y"), x.alias("x"), "v").withColumns({"row": F.expr(f"cast(y div {patch} as int)"), "col": F.expr(f"cast(x div {patch} as int)")})


def block_match(frames: DataFrame, patch: int, radius: int = 1) -> DataFrame:
    """(clip_id, frame_idx, row, col, mv_r, mv_c, motion, residual) against the frame before.

    The offset with the least sum of absolute differences wins; of equals the shortest, then by row and column.
    Only offsets that stay inside the frame count.  Motion is |mv_r| + |mv_c|, residual the squared difference.
    """
    pixels = patchify(frames, patch)
    moves = F.array(*[F.struct(F.lit(r).alias("mv_r"), F.lit(c).alias("mv_c")) for r in range(-radius, radius + 1) for c in range(-radius, radius + 1)])
    tried = pixels.filter("frame_idx > 0").withColumn("mv", F.explode(moves)).select("clip_id", "frame_idx", "row", "col", "mv.*", "v", (F.col("y") + F.col("mv.mv_r")).alias("y"), (F.col("x") + F.col("mv.mv_c")).alias("x"))
    before = pixels.select("clip_id", (F.col("frame_idx") + 1).alias("frame_idx"), "y", "x", F.col("v").alias("w"))
    pairs = tried.join(before, ["clip_id", "frame_idx", "y", "x"])
    d = (F.col("v") - F.col("w")).cast("long")
    cost = pairs.groupBy("clip_id", "frame_idx", "row", "col", "mv_r", "mv_c").agg(F.sum(F.abs(d)).alias("sad"), F.sum(d * d).alias("residual"), F.count("*").alias("n")).filter(F.col("n") == patch * patch)
    w = Window.partitionBy("clip_id", "frame_idx", "row", "col").orderBy("sad", F.abs("mv_r") + F.abs("mv_c"), "mv_r", "mv_c")
    best = cost.withColumn("r", F.row_number().over(w)).filter("r = 1")
    return best.select("clip_id", "frame_idx", "row", "col", "mv_r", "mv_c", (F.abs("mv_r") + F.abs("mv_c")).cast("int").alias("motion"), "residual")
