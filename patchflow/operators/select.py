"""Budgeted selection of tiles and the frame-sampling alternatives.

All work on narrow tables (clip_id, frame_idx, row, col, importance); ties break by frame, row, column.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

KEY = ("clip_id", "frame_idx", "row", "col")


def weighted(changes: DataFrame, alpha: int = 1000, beta: int = 1) -> DataFrame:
    """Importance from motion (change of count) and residual (change of value)."""
    return changes.select(*KEY, (alpha * F.abs("dn") + beta * F.abs("dv")).alias("importance"))


def code_length(imp: DataFrame, clip_tiles: int, levels: int = 8) -> DataFrame:
    """Importance as estimated bits: -log2 of the share of the tile's size class at its place.

    Tiles that a sparse feed leaves out are class 0; they are counted from the lattice size.  The
    model has places x levels rows and is broadcast.
    """
    symbol = F.least(F.lit(levels - 1), F.floor(F.log2(F.lit(1.0) + F.col("importance")))).cast("int")
    coded = imp.withColumn("symbol", symbol)
    clips = imp.select("clip_id").distinct().agg(F.count("*").alias("clips"))
    counts = coded.groupBy("row", "col", "symbol").count()
    stored = coded.groupBy("row", "col").agg(F.count("*").alias("stored"))
    model = counts.join(F.broadcast(stored), ["row", "col"]).crossJoin(F.broadcast(clips))
    size = F.col("clips") * clip_tiles
    seen = F.col("count") + F.when(F.col("symbol") == 0, size - F.col("stored")).otherwise(0)
    bits = model.select("row", "col", "symbol", F.round(-F.log2((seen + 1) / (size + levels)), 6).alias("bits"))
    return coded.join(F.broadcast(bits), ["row", "col", "symbol"]).select(*KEY, F.col("bits").alias("importance"))


def anchor_lattice(imp: DataFrame, gop: int, frames: int, rows: int, cols: int) -> DataFrame:
    """All tiles of anchor frames with importance zero: facts to be united with, so no join is needed."""
    clips = imp.select("clip_id").distinct()
    whole = clips.select("clip_id", F.explode(F.sequence(F.lit(0), F.lit(frames - 1), F.lit(gop))).alias("frame_idx"))
    whole = whole.select("clip_id", "frame_idx", F.explode(F.sequence(F.lit(0), F.lit(rows - 1))).alias("row"))
    return whole.select("clip_id", "frame_idx", "row", F.explode(F.sequence(F.lit(0), F.lit(cols - 1))).alias("col"), F.lit(0).cast(imp.schema["importance"].dataType).alias("importance"))


def anchor_zeros(facts: DataFrame, gop: int, frames: int, rows: int, cols: int) -> DataFrame:
    """Facts of size zero on every tile of anchor frames, to be united with ``facts`` before these are summed: the lattice costs no second aggregate."""
    clips = facts.select("clip_id").distinct()
    place = clips.select("clip_id", F.explode(F.sequence(F.lit(0), F.lit(frames - 1), F.lit(gop))).alias("frame_idx"))
    place = place.select("clip_id", "frame_idx", F.explode(F.sequence(F.lit(0), F.lit(rows - 1))).alias("row"))
    zero = F.lit(0).cast("long")
    return place.select("clip_id", "frame_idx", "row", F.explode(F.sequence(F.lit(0), F.lit(cols - 1))).alias("col"), zero.alias("n"), zero.alias("c"))


def topk_budget(imp: DataFrame, budget: int, gop: int = 16, frames: int = 64, grid: tuple[int, int] = (4, 5), complete: bool = False) -> DataFrame:
    """All anchor tiles, then the most important predicted ones, up to ``budget`` a clip.

    ``complete`` says that ``imp`` has every anchor tile already (``anchor_zeros``), so that one exchange by clip is all.

    Anchors over the budget are cut in frame order; with too few changing tiles the sequence is
    shorter, never filled with zeros.
    """
    is_anchor = F.col("frame_idx") % gop == 0
    if complete:
        return _ranked(imp.filter(is_anchor | (F.col("importance") > 0)).withColumn("is_anchor", is_anchor), budget)
    anchors = imp.filter(is_anchor).unionByName(anchor_lattice(imp, gop, frames, *grid)).groupBy(*KEY).agg(F.max("importance").alias("importance"))
    both = anchors.withColumn("is_anchor", F.lit(True)).unionByName(imp.filter(~is_anchor & (F.col("importance") > 0)).withColumn("is_anchor", F.lit(False)))
    return _ranked(both, budget)


def _ranked(both: DataFrame, budget: int) -> DataFrame:
    first = F.when(F.col("is_anchor"), F.lit(0)).otherwise(-F.col("importance"))
    w = Window.partitionBy("clip_id").orderBy(F.desc("is_anchor"), first, "frame_idx", "row", "col")
    return both.withColumn("rank_in_clip", F.row_number().over(w)).filter(F.col("rank_in_clip") <= budget)


def capped_by(imp: DataFrame, tokens: DataFrame, gop: int = 16, frames: int = 64, grid: tuple[int, int] = (4, 5), most: int = 1 << 30) -> DataFrame:
    """A second selector that may use no more tokens than the first did on the same clip; ``most`` is the first one's budget, which prunes before the join."""
    used = tokens.groupBy("clip_id").agg(F.count("*").alias("cap"))
    chosen = topk_budget(imp, most, gop, frames, grid)
    return chosen.join(used, "clip_id").filter(F.col("rank_in_clip") <= F.col("cap")).drop("cap")


def uniform_indices(n: int, frames: int) -> list[int]:
    """The frames of ``uniform_frames``; they are the same for every clip."""
    m = min(n, frames)
    return [((2 * i + 1) * frames) // (2 * m) for i in range(m)]


def uniform_frames(clips: DataFrame, n: int, frames: int) -> DataFrame:
    """n frames at the middles of n equal parts; all frames if there are fewer."""
    m = min(n, frames)
    return clips.select("clip_id", F.explode(F.sequence(F.lit(0), F.lit(m - 1))).alias("i")).select("clip_id", "i", F.expr(f"cast(((2 * i + 1) * {frames}) div (2 * {m}) as int)").alias("frame_idx"))


def collage(clips: DataFrame, n: int, frames: int, grid: tuple[int, int]) -> DataFrame:
    """The chosen frames stacked in one tall canvas."""
    rows, cols = grid
    tiles = uniform_frames(clips, n, frames).withColumn("row", F.explode(F.sequence(F.lit(0), F.lit(rows - 1)))).withColumn("col", F.explode(F.sequence(F.lit(0), F.lit(cols - 1))))
    return tiles.select("clip_id", "frame_idx", "row", "col", (F.col("i") * rows + F.col("row")).alias("canvas_row"))


def densest_segment(imp: DataFrame, seg_frames: int) -> DataFrame:
    """Of non-overlapping segments the one with the most importance; of equals the earliest."""
    per = imp.groupBy("clip_id", F.expr(f"cast(frame_idx div {seg_frames} as int)").alias("segment")).agg(F.sum("importance").alias("mass"))
    best = per.groupBy("clip_id").agg(F.max_by(F.struct("segment", "mass"), F.struct("mass", -F.col("segment"))).alias("b"))
    return best.select("clip_id", "b.segment", "b.mass")


def canvases(imp: DataFrame, n_canvas: int, frames: int, grid: tuple[int, int], slots: int, oversample: int = 8) -> DataFrame:
    """Salient tiles of adaptive time groups packed in at most ``n_canvas`` canvases of ``slots`` tiles.

    Groups cut the running sum of frame mass (importance and one) in equal parts.  The first frame of a
    group is whole if it fills at most half the slots; the rest are its most important tiles.
    """
    rows, cols = grid
    clips = imp.select("clip_id").distinct()
    source = uniform_frames(clips, n_canvas * oversample, frames).select("clip_id", "frame_idx")
    mass = source.join(imp.groupBy("clip_id", "frame_idx").agg(F.sum("importance").alias("m")), ["clip_id", "frame_idx"], "left").select("clip_id", "frame_idx", (F.coalesce("m", F.lit(0)) + 1).alias("m"))
    run, whole = Window.partitionBy("clip_id").orderBy("frame_idx"), Window.partitionBy("clip_id")
    grouped = mass.withColumns({"cum": F.sum("m").over(run), "total": F.sum("m").over(whole)}).select("clip_id", "frame_idx", F.expr(f"cast(least({n_canvas - 1}, ({n_canvas} * (cum - 1)) div total) as int)").alias("canvas_idx"))
    head = grouped.withColumn("is_anchor", F.col("frame_idx") == F.min("frame_idx").over(Window.partitionBy("clip_id", "canvas_idx")))
    lattice = head.filter("is_anchor").withColumn("row", F.explode(F.sequence(F.lit(0), F.lit(rows - 1)))).withColumn("col", F.explode(F.sequence(F.lit(0), F.lit(cols - 1)))).withColumn("importance", F.lit(0).cast("long"))
    found = imp.join(head, ["clip_id", "frame_idx"]).filter((F.col("importance") > 0) & ~F.col("is_anchor"))
    both = lattice.select("clip_id", "canvas_idx", "frame_idx", "row", "col", "importance", "is_anchor").unionByName(found.select("clip_id", "canvas_idx", "frame_idx", "row", "col", "importance", "is_anchor"))
    keep_anchor = rows * cols if rows * cols <= slots // 2 else slots // 2
    anchor_rank = F.row_number().over(Window.partitionBy("clip_id", "canvas_idx", "is_anchor").orderBy(F.desc("importance"), "frame_idx", "row", "col"))
    ranked = both.withColumn("r", anchor_rank).filter(~F.col("is_anchor") & (F.col("r") <= slots - keep_anchor) | F.col("is_anchor") & (F.col("r") <= keep_anchor))
    slot = F.row_number().over(Window.partitionBy("clip_id", "canvas_idx").orderBy("frame_idx", "row", "col")) - 1
    return ranked.withColumn("slot", slot).select("clip_id", "canvas_idx", "slot", "frame_idx", "row", "col", "importance")
