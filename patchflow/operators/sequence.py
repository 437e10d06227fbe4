"""What leaves the selector: other budgets and samplings, positions, padded batches, rolling windows.

Token tables are (clip_id, frame_idx, row, col, importance, is_anchor, rank_in_clip).
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import select

SELECTORS: dict[str, Callable[[DataFrame], DataFrame]] = {}


def register(name: str, make: Callable[[DataFrame], DataFrame]) -> None:
    """A selector turns changes of tiles into (clip_id, frame_idx, row, col, importance); any other stage takes it by name."""
    SELECTORS[name] = make


def importance_by(name: str, changes: DataFrame) -> DataFrame:
    if name not in SELECTORS:
        raise KeyError(f"no selector {name}; there are {sorted(SELECTORS)}")
    return SELECTORS[name](changes)


register("motion_residual", select.weighted)
register("residual", lambda changes: select.weighted(changes, alpha=0, beta=1))
register("motion", lambda changes: select.weighted(changes, alpha=1, beta=0))


def still_image(tiles: DataFrame, budget: int) -> DataFrame:
    """(clip_id, row, col, importance, token_pos): an image is a clip of one frame, so all tiles are anchors, in raster order up to the budget."""
    place = Window.partitionBy("clip_id").orderBy("row", "col")
    return tiles.withColumn("token_pos", F.row_number().over(place) - 1).filter(F.col("token_pos") < budget)


def densified(imp: DataFrame, frames: int, grid: tuple[int, int]) -> DataFrame:
    """Every tile of every frame, with importance zero where a sparse feed has none: zero rows in a union and one aggregate, no join."""
    return imp.unionByName(select.anchor_lattice(imp, 1, frames, *grid)).groupBy(*select.KEY).agg(F.max("importance").alias("importance"))


def with_overflow(imp: DataFrame, budget: int, on_overflow: str, gop: int, frames: int, grid: tuple[int, int]) -> DataFrame:
    """Budgeted selection with ``overflow``, whether the anchors alone pass the budget.

    ``truncate`` cuts them in frame order, ``keep`` keeps all of them (and nothing else), ``error`` refuses such a budget.
    """
    anchors = -(-frames // gop) * grid[0] * grid[1]  # the grid's, so known before any row is read
    if on_overflow not in ("truncate", "keep", "error"):
        raise ValueError(on_overflow)
    if on_overflow == "error" and anchors > budget:
        raise ValueError(f"{anchors} anchor tiles pass the budget of {budget}")
    return select.topk_budget(imp, max(budget, anchors) if on_overflow == "keep" else budget, gop, frames, grid).withColumn("overflow", F.lit(anchors > budget))


def scene_cuts(imp: DataFrame, clips: DataFrame, frames: int, gop: int, factor: int = 2) -> DataFrame:
    """(clip_id, frame_idx, why): anchors every ``gop`` frames, and where a frame's change is over ``factor`` times the clip's mean."""
    mass = imp.groupBy("clip_id", "frame_idx").agg(F.sum("importance").alias("m"))
    total = F.sum("m").over(Window.partitionBy("clip_id"))
    cuts = mass.withColumn("total", total).filter(F.col("m") * frames > factor * F.col("total")).filter(F.col("frame_idx") % gop != 0).select("clip_id", "frame_idx", F.lit("cut").alias("why"))
    regular = clips.select("clip_id", F.explode(F.sequence(F.lit(0), F.lit(frames - 1), F.lit(gop))).alias("frame_idx"), F.lit("gop").alias("why"))
    return regular.unionByName(cuts)


def by_fps(clips: DataFrame, frames: int, source_fps: int, fps: int, cap: int) -> DataFrame:
    """(clip_id, frame_idx) at ``fps``; where these are more than ``cap``, that many at even distances."""
    step = max(1, source_fps // fps)
    n = -(-frames // step)
    if n <= cap:
        return clips.select("clip_id", F.explode(F.sequence(F.lit(0), F.lit(frames - 1), F.lit(step))).alias("frame_idx"))
    return select.uniform_frames(clips, cap, frames).select("clip_id", "frame_idx")


def ratio_budget(imp: DataFrame, share: float, gop: int, frames: int, grid: tuple[int, int]) -> DataFrame:
    """Budgeted selection of a share of the dense grid."""
    return select.topk_budget(imp, int(share * frames * grid[0] * grid[1]), gop, frames, grid)


def bits_budget(bits: DataFrame, budget_bits: float) -> DataFrame:
    """Tokens in order of their bits (most first) until their sum reaches the budget; sums are in millionths, so equal everywhere."""
    w = Window.partitionBy("clip_id").orderBy(F.desc("importance"), "frame_idx", "row", "col")
    micro = F.round(F.col("importance") * 1000000).cast("long")
    before = F.coalesce(F.sum(micro).over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return bits.withColumns({"micro": micro, "before": before}).filter(F.col("before") < int(budget_bits * 1000000))


def rotary(tokens: DataFrame, dims: tuple[int, int, int] = (4, 6, 6), theta: float = 10000.0) -> DataFrame:
    """Adds ``angles``: for frame, row and column of the un-pruned grid, position times theta ** (-j / pairs) for each pair of channels."""
    parts = [F.array(*[F.col(c) * F.lit(theta ** (-j / (d // 2))) for j in range(d // 2)]) for c, d in zip(("frame_idx", "row", "col"), dims)]
    return tokens.withColumn("angles", F.concat(*parts))


def pack_sequences(tokens: DataFrame, batch: int, max_len: int | None = None) -> DataFrame:
    """(clip_id, batch_idx, tokens, valid_len, pad_len, mask): sequences in order of time, padded to the longest of their batch or to ``max_len``.

    Batches are ``batch`` consecutive clip ids, so the longest is found within a batch.
    """
    one = tokens.groupBy("clip_id").agg(F.array_sort(F.collect_list(F.struct("frame_idx", "row", "col"))).alias("tokens"))
    held = one.withColumns({"batch_idx": F.expr(f"clip_id div {batch}"), "valid_len": F.size("tokens")})
    longest = F.lit(max_len) if max_len else F.max("valid_len").over(Window.partitionBy("batch_idx"))
    padded = held.withColumn("pad_len", longest).withColumn("valid_len", F.least("valid_len", "pad_len"))
    mask = F.concat(F.array_repeat(F.lit(1), F.col("valid_len")), F.array_repeat(F.lit(0), F.col("pad_len") - F.col("valid_len")))
    return padded.withColumn("tokens", F.slice("tokens", F.lit(1), F.col("valid_len"))).withColumn("mask", mask)


def zero_filled(tokens: DataFrame, budget: int) -> DataFrame:
    """Sequences of exactly ``budget`` rows: what is missing is filled by rows of importance zero, marked ``is_pad``."""
    n = tokens.groupBy("clip_id").agg(F.count("*").cast("int").alias("n")).filter(F.col("n") < budget)
    nothing = [F.lit(None).cast(tokens.schema[c].dataType).alias(c) for c in ("frame_idx", "row", "col")]
    kind = tokens.schema["importance"].dataType
    pads = n.select("clip_id", F.explode(F.sequence(F.col("n") + 1, F.lit(budget))).alias("rank_in_clip"))
    pads = pads.select("clip_id", *nothing, F.lit(0).cast(kind).alias("importance"), F.lit(False).alias("is_anchor"), "rank_in_clip", F.lit(True).alias("is_pad"))
    return tokens.withColumn("is_pad", F.lit(False)).unionByName(pads)


def codec_windows(tokens: DataFrame, frames: int) -> DataFrame:
    """(clip_id, window_idx, anchors, updates): what a rolling reader gets of each window, whole anchors first, then sparse updates in order of time."""
    place = F.struct("frame_idx", "row", "col")
    gathered = [F.array_sort(F.collect_list(F.when(c, place))).alias(n) for n, c in (("anchors", F.col("is_anchor")), ("updates", ~F.col("is_anchor")))]
    return tokens.groupBy("clip_id", F.expr(f"cast(frame_idx div {frames} as int)").alias("window_idx")).agg(*gathered)


def gain_area(curve: DataFrame) -> DataFrame:
    """(area): trapezoids between two curves (n, a, b) over log2 n, divided by the width."""
    w = Window.orderBy("n")  # one row a budget
    d = F.col("a") - F.col("b")
    steps = curve.select(F.log2("n").alias("x"), d.alias("d"), F.lead(F.log2("n")).over(w).alias("x2"), F.lead(d).over(w).alias("d2"))
    return steps.agg(F.round(F.sum((F.col("x2") - F.col("x")) * (F.col("d") + F.col("d2")) / 2) / (F.max("x") - F.min("x")), 6).alias("area"))


def mixture_error(counts: DataFrame, targets: DataFrame) -> DataFrame:
    """(component, n, share, target, error) and the greatest error of all in ``worst``; components of either table count."""
    total = counts.agg(F.sum("n").alias("total"))
    both = counts.join(targets, "component", "full").crossJoin(F.broadcast(total))  # a row a component
    share = F.coalesce(F.col("n") / F.col("total"), F.lit(0.0))
    error = F.abs(share - F.coalesce("target", F.lit(0.0)))
    told = both.select("component", F.coalesce("n", F.lit(0)).alias("n"), F.round(share, 6).alias("share"), F.round("target", 6).alias("target"), F.round(error, 6).alias("error"))
    return told.crossJoin(F.broadcast(told.agg(F.max("error").alias("worst"))))
