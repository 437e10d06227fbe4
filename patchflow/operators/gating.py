"""Gates: one format for timed sources, the check of causality, decisions, history, memory, operating curves.

Sequences are (video_id, pos, t_s, ...); every window runs within a sequence.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def in_order() -> Window:
    return Window.partitionBy("video_id").orderBy("pos")


def normalized(sources: dict[str, DataFrame]) -> DataFrame:
    """(source, video_id, start_s, end_s, kind, text) of timed tables: captions have an end and text, events are points in time."""
    parts = []
    for name, t in sources.items():
        start = F.col("start_s" if "start_s" in t.columns else "t_s").cast("long")
        end = F.col("end_s").cast("long") if "end_s" in t.columns else start
        text = F.col("caption") if "caption" in t.columns else F.lit("")
        parts.append(t.select(F.lit(name).alias("source"), F.col("video_id").cast("long").alias("video_id"), start.alias("start_s"), end.alias("end_s"), F.when(start < end, "span").otherwise("point").alias("kind"), text.alias("text")))
    return reduce(DataFrame.unionByName, parts)


def late_features(decisions: DataFrame, feature_t: Column) -> DataFrame:
    """(video_id, decisions, late): decisions that use a feature of a time after their own; none may."""
    return decisions.withColumn("_used", feature_t).groupBy("video_id").agg(F.count("*").alias("decisions"), F.count_if(F.col("_used") > F.col("t_s")).alias("late"))


def assert_causal(decisions: DataFrame, feature_t: Column) -> None:
    """Raises where any decision looks ahead."""
    found = late_features(decisions, feature_t).agg(F.sum("late")).first()[0] or 0
    if found:
        raise ValueError(f"{found} decisions use features later than themselves")


def argmax(silent: Column, speak: Column) -> Column:
    """1 where the logit of speaking is the greater one; equal logits stay silent."""
    return (speak > silent).cast("int")


def with_history(rows: DataFrame, k: int, weight: float, logit: Column) -> DataFrame:
    """Adds ``p_speak``: the logit less ``weight`` for each of the ``k`` gate tokens before that spoke (the true ones, as in teacher forcing)."""
    spoke = sum((F.coalesce(F.lag("speak", j).over(in_order()), F.lit(0)) for j in range(1, k + 1)), F.lit(0))
    return rows.withColumn("p_speak", 1 / (1 + F.exp(-(logit - weight * spoke))))


def accumulated(rows: DataFrame, value: str) -> DataFrame:
    """Adds what a memory that is never cleared holds before each position: sum and greatest of ``value`` and rows since the last speak."""
    past = in_order().rowsBetween(Window.unboundedPreceding, -1)
    since = F.col("pos") - F.coalesce(F.max(F.when(F.col("speak") == 1, F.col("pos"))).over(past), F.lit(-1))
    return rows.withColumns({"held": F.coalesce(F.sum(value).over(past), F.lit(0)), "most": F.coalesce(F.max(value).over(past), F.lit(0)), "since": since})


def logistic_fit(rows: DataFrame, features: list[str], label: str, weight: Column, rounds: int = 30) -> list[float]:
    """Intercept and slopes of the weighted logistic fit, by Newton steps halved where the loss would rise.

    Each step is one aggregate of a few sums over ``rows``, which should be stored: no function of a library runs in its plan.
    """
    import numpy as np

    first = rows.agg(F.sum(weight).alias("w"), *[f(x).cast("double").alias(f"{n}_{x}") for x in features for n, f in (("mean", F.avg), ("sd", F.stddev_samp))]).first()
    mean = [first[f"mean_{x}"] or 0.0 for x in features]
    scale = [first[f"sd_{x}"] or 1.0 for x in features]
    z = [F.lit(1.0), *[(F.col(x) - m) / s for x, m, s in zip(features, mean, scale)]]
    d = len(z)

    def sums(at):
        logit = sum((c * float(b) for c, b in zip(z[1:], at[1:])), F.lit(float(at[0])))
        p = 1 / (1 + F.exp(-logit))
        loss = F.greatest(logit, F.lit(0.0)) + F.log1p(F.exp(-F.abs(logit))) - F.col(label) * logit
        made = [weight * loss, *[weight * (p - F.col(label)) * c for c in z], *[weight * p * (1 - p) * z[i] * z[j] for i in range(d) for j in range(i, d)]]
        loss, *rest = rows.agg(*[F.sum(c).alias(f"s{i}") for i, c in enumerate(made)]).first()
        bend = np.zeros((d, d))
        bend[np.triu_indices(d)] = rest[d:]
        return loss, np.array(rest[:d]), bend + np.triu(bend, 1).T

    at = np.zeros(d)
    if first["w"]:
        loss, slope, bend = sums(at)
        step = -np.linalg.lstsq(bend, slope, rcond=None)[0]
        for _ in range(rounds):
            tried = sums(at + step)
            if tried[0] <= loss:
                done = loss - tried[0] <= 1e-12 * loss
                at, (loss, slope, bend) = at + step, tried
                if done:
                    break
                step = -np.linalg.lstsq(bend, slope, rcond=None)[0]
            else:
                step = step / 2
                if np.abs(step).max() < 1e-9:
                    break
    slopes = [b / s for b, s in zip(at[1:], scale)]
    return [float(at[0] - sum(b * m for b, m in zip(slopes, mean))), *map(float, slopes)]


def threshold_curve(rows: DataFrame, score: str, grid: list[int]) -> DataFrame:
    """(tau, tp, fp, fn, precision, recall) at each threshold: one aggregate by the number of thresholds reached, then sums over that many rows."""
    reached = sum(((F.col(score) >= t).cast("int") for t in grid), F.lit(0))
    steps = rows.groupBy(reached.alias("reached")).agg(F.sum("speak").alias("p"), F.sum(1 - F.col("speak")).alias("q"))
    levels = F.array(*[F.struct(F.lit(i + 1).alias("level"), F.lit(t).alias("tau")) for i, t in enumerate(sorted(grid))])
    each = steps.select("*", F.inline(levels))
    hit = F.col("reached") >= F.col("level")
    sums = each.groupBy("tau").agg(*[F.coalesce(F.sum(F.when(c, F.col(v))), F.lit(0)).alias(n) for n, c, v in (("tp", hit, "p"), ("fp", hit, "q"), ("fn", ~hit, "p"))])
    share = lambda a, b: F.round(F.try_divide(F.col(a).cast("double"), F.col(a) + F.col(b)), 6)
    return sums.select("tau", "tp", "fp", "fn", share("tp", "fp").alias("precision"), share("tp", "fn").alias("recall"))
