"""Timing, ranking and grounding measures.  Integer sums until the last division."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def timing(scored: DataFrame) -> DataFrame:
    """Per sequence: trigger accuracy, harmonic balance of the two recalls, F1; rows (video_id, speak, fired)."""
    c = scored.groupBy("video_id").agg(
        F.count("*").alias("n"),
        F.count_if((F.col("speak") == 1) & (F.col("fired") == 1)).alias("tp"),
        F.count_if((F.col("speak") == 0) & (F.col("fired") == 1)).alias("fp"),
        F.count_if((F.col("speak") == 1) & (F.col("fired") == 0)).alias("fn"),
        F.count_if((F.col("speak") == 0) & (F.col("fired") == 0)).alias("tn"),
    )
    rs, rn = F.try_divide("tp", F.col("tp") + F.col("fn")), F.try_divide("tn", F.col("tn") + F.col("fp"))
    return c.select(
        "video_id",
        "n",
        F.round((F.col("tp") + F.col("tn")) / F.col("n"), 6).alias("trigger_acc"),
        F.round(F.coalesce(F.try_divide(2 * rs * rn, rs + rn), rs * 0.0), 6).alias("timing_balance"),
        F.round(F.try_divide(2 * F.col("tp"), 2 * F.col("tp") + F.col("fp") + F.col("fn")), 6).alias("f1"),
    )


def ranking(scored: DataFrame) -> DataFrame:
    """Per sequence: ROC-AUC with midranks and average precision with ties grouped; rows (video_id, speak, score).

    Counts per distinct score come first, so a window holds distinct scores only.
    """
    per = scored.groupBy("video_id", "score").agg(F.sum("speak").alias("p"), F.sum(1 - F.col("speak")).alias("q"))
    up, down, whole = (Window.partitionBy("video_id").orderBy("score").rowsBetween(Window.unboundedPreceding, -1), Window.partitionBy("video_id").orderBy(F.desc("score")), Window.partitionBy("video_id"))
    w = per.withColumns({"below": F.coalesce(F.sum("q").over(up), F.lit(0)), "hit": F.sum("p").over(down), "miss": F.sum("q").over(down), "all_p": F.sum("p").over(whole), "all_q": F.sum("q").over(whole)})
    return w.groupBy("video_id").agg(
        F.round(F.try_divide(F.sum(F.col("p") * (2 * F.col("below") + F.col("q"))), 2 * F.max("all_p") * F.max("all_q")), 6).alias("roc_auc"),
        F.round(F.sum(F.try_divide(F.col("p") * F.col("hit"), (F.col("hit") + F.col("miss")) * F.col("all_p"))), 6).alias("pr_auc"),
    )


def relaxed_hits(truth: DataFrame, fired: DataFrame, tol: int) -> DataFrame:
    """(video_id, positives, hits): true times with a prediction within ``tol`` seconds, by offsets and an equi-join."""
    wide = fired.select("video_id", F.explode(F.sequence(F.col("t_s") - tol, F.col("t_s") + tol)).alias("t_s")).distinct()
    t = truth.select("video_id", "t_s").distinct()
    return t.join(wide.withColumn("hit", F.lit(1)), ["video_id", "t_s"], "left").groupBy("video_id").agg(F.count("*").alias("positives"), F.count("hit").alias("hits"))


def span_overlap(a0, a1, b0, b1):
    """Temporal intersection over union."""
    inter = F.greatest(F.lit(0), F.least(a1, b1) - F.greatest(a0, b0))
    return F.try_divide(inter, (a1 - a0) + (b1 - b0) - inter)


def region_and_border(a: DataFrame, b: DataFrame) -> DataFrame:
    """Per (clip_id, frame_idx): J, the overlap of two tile sets, and F of their border tiles."""
    key = ["clip_id", "frame_idx", "row", "col"]

    def border(s):
        # a tile with all four neighbours in the set is inside; others are border
        steps = F.array(*[F.struct(F.lit(r).alias("r"), F.lit(c).alias("c")) for r, c in ((0, 1), (1, 0), (0, -1), (-1, 0))])
        near = s.select("clip_id", "frame_idx", F.explode(steps).alias("d"), "row", "col").select("clip_id", "frame_idx", (F.col("row") + F.col("d.r")).alias("row"), (F.col("col") + F.col("d.c")).alias("col"))
        inside = near.groupBy(*key).count().filter("count = 4").select(*key)
        return s.join(inside, key, "left_anti")

    def common(x, y, name):
        both = x.select(*key, F.lit(1).alias("x")).join(y.select(*key, F.lit(1).alias("y")), key, "full")
        return both.groupBy("clip_id", "frame_idx").agg(F.count("x").alias(f"{name}_a"), F.count("y").alias(f"{name}_b"), F.count_if(F.col("x").isNotNull() & F.col("y").isNotNull()).alias(f"{name}_ab"))

    out = common(a.select(*key), b.select(*key), "all").join(common(border(a.select(*key)), border(b.select(*key)), "edge"), ["clip_id", "frame_idx"])
    return out.select("clip_id", "frame_idx", F.round(F.col("all_ab") / (F.col("all_a") + F.col("all_b") - F.col("all_ab")), 6).alias("j"), F.round(F.coalesce(F.try_divide(2 * F.col("edge_ab"), F.col("edge_a") + F.col("edge_b")), F.lit(0.0)), 6).alias("f"))


def short_events(facts: DataFrame) -> DataFrame:
    """(clip_id, frame_idx, row, col): tiles that are active in one frame and in neither neighbour of it."""
    w = Window.partitionBy("clip_id", "row", "col").orderBy("frame_idx")
    busy = facts.select("clip_id", "frame_idx", "row", "col").distinct().withColumns({"before": F.lag("frame_idx").over(w), "after": F.lead("frame_idx").over(w)})
    alone = (F.coalesce("before", F.lit(-2)) < F.col("frame_idx") - 1) & (F.col("after").isNull() | (F.col("after") > F.col("frame_idx") + 1))
    return busy.filter(alone).select("clip_id", "frame_idx", "row", "col")


def event_recall(events: DataFrame, hits: dict) -> DataFrame:
    """One row: ``n_events`` and, under each name, the share of events for which its condition holds; no events, no share.

    All schemes are judged in one pass over the events, joined before with whatever the conditions need.
    """
    n = F.count("*")
    return events.agg(n.alias("n_events"), *[F.when(n > 0, F.round(F.count_if(c) / n, 6)).alias(k) for k, c in hits.items()])
