"""Balance and stage draws: durations, down-weights, interleaving, granularity, consistency."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .curate import bucket, stratum


def durations(samples: DataFrame, shares: dict[str, float], seed: int = 11) -> DataFrame:
    """Rows kept so that strata approach their target shares; no row is ever repeated.

    The stratum that is scarcest against its share keeps all rows and sets the scale; a stratum
    without a share goes.  Rows with a null duration fall in ``over`` like any long one.
    """
    s = samples.withColumn("stratum", stratum(F.col("duration_s")))
    target = F.element_at(F.create_map(*[x for k, v in shares.items() for x in (F.lit(k), F.lit(float(v)))]), F.col("stratum"))
    n = s.groupBy("stratum").agg(F.count("*").alias("n")).withColumn("share", F.coalesce(target, F.lit(0.0))).filter("share > 0")
    scale = n.agg(F.min(F.col("n") / F.col("share")).alias("scale"))
    rate = n.crossJoin(F.broadcast(scale)).select("stratum", (F.col("scale") * F.col("share") / F.col("n")).alias("rate"))  # six strata
    return s.join(F.broadcast(rate), "stratum").filter(bucket("sample_id", seed=seed) / F.lit(float(2**32)) < F.col("rate")).drop("rate")


def downweight(condition: Column, weight: float) -> Column:
    """The weight where the condition holds, 1 elsewhere (also where it is null)."""
    return F.when(condition, F.lit(float(weight))).otherwise(1.0)


def interleave(a: DataFrame, b: DataFrame, ratio: int, shards: int = 64) -> DataFrame:
    """(shard, pos, side, sample_id): ``ratio`` rows of a, then one of b, in each shard.

    Both sides are sharded by hash, so no global order is made; what one side has left follows at
    the end of a shard.
    """

    def placed(df, side, slot):
        s = df.select(bucket("sample_id", seed=3).alias("b"), "sample_id").withColumn("shard", (F.col("b") % shards).cast("int"))
        i = F.row_number().over(Window.partitionBy("shard").orderBy("b", "sample_id")) - 1
        return s.withColumn("i", i).select("shard", slot(F.col("i")).alias("slot"), F.lit(side).alias("side"), "sample_id")

    both = placed(a, "a", lambda i: F.floor(i / ratio) * (ratio + 1) + i % ratio).unionByName(placed(b, "b", lambda i: i.cast("long") * (ratio + 1) + ratio))
    return both.select("shard", (F.row_number().over(Window.partitionBy("shard").orderBy("slot", "side")) - 1).cast("int").alias("pos"), "side", "sample_id")


def granularity(meta: DataFrame, short: int = 180, step: int = 60) -> DataFrame:
    """(sample_id, part, start_s, end_s, parts): one caption for a short clip, segments that know each other for a long one."""
    whole = F.greatest(F.col("duration_s"), F.lit(0).cast("long"))
    starts = F.when(whole <= short, F.array(F.lit(0).cast("long"))).otherwise(F.sequence(F.lit(0).cast("long"), whole - 1, F.lit(step).cast("long")))
    p = meta.filter("duration_s is not null").select("sample_id", whole.alias("whole"), F.size(starts).alias("parts"), F.posexplode(starts).alias("part", "start_s"))
    return p.select("sample_id", "part", "start_s", F.when(F.col("parts") == 1, F.col("whole")).otherwise(F.least(F.col("start_s") + step, "whole")).alias("end_s"), "parts")


def unique_videos(uses: DataFrame) -> DataFrame:
    """Rows and distinct videos by representation and in all: (grouping) rollup of (kind, sample_id) uses."""
    return uses.rollup("kind").agg(F.count("*").alias("n"), F.countDistinct("sample_id").alias("videos"))


def stage_draw(pool: DataFrame, shares: dict[str, float], seed: int = 5) -> DataFrame:
    """(sample_id, component): disjoint parts of one md5 line, so a draw needs no sort and grows with the pool."""
    cut, low = F.lit(None).cast("string"), 0.0
    u = bucket("sample_id", seed=seed) / F.lit(float(2**32))
    for name, share in shares.items():
        cut = F.when((u >= low) & (u < low + share), name).otherwise(cut)
        low += share
    return pool.select("sample_id", cut.alias("component")).filter("component is not null")


def consistency(timeline: DataFrame, activity: DataFrame, width: int = 16) -> DataFrame:
    """(video_id, seg_idx, activity): what a video shows (``t_s``, ``amount``) while a caption runs.

    The range join is made equal by blocks of ``width`` seconds: a caption is listed once per block it touches.
    """
    blocks = F.sequence(F.floor(F.col("start_s") / width), F.floor(F.greatest(F.col("end_s") - 1, "start_s") / width))
    seg = timeline.select("video_id", "seg_idx", "start_s", "end_s", F.explode(blocks).alias("block"))
    act = activity.select("video_id", "t_s", "amount", F.floor(F.col("t_s") / width).alias("block"))
    met = seg.join(act.hint("merge"), ["video_id", "block"], "left")
    inside = (F.col("t_s") >= F.col("start_s")) & (F.col("t_s") < F.col("end_s"))
    return met.groupBy("video_id", "seg_idx").agg(F.coalesce(F.sum(F.when(inside, F.col("amount"))), F.lit(0)).cast("long").alias("activity"))


def supplement(pool: DataFrame, scores: DataFrame, threshold: float, extra: int, used: Column, seed: int = 13) -> DataFrame:
    """(sample_id, domain): up to ``extra`` unused rows, the first by md5 key, of each domain scored under the threshold.

    A domain without a score is not drawn from; the rank filter becomes a group limit, so no domain is gathered whole.
    """
    weak = scores.filter(F.col("score") < threshold).select("domain")
    w = Window.partitionBy("domain").orderBy(bucket("sample_id", seed=seed), "sample_id")
    spare = pool.filter(~used).join(weak, "domain", "left_semi").select("sample_id", "domain")
    return spare.withColumn("r", F.row_number().over(w)).filter(F.col("r") <= extra).select("sample_id", "domain")
