"""Proactive-streaming workloads: targets, memory, gates, timing measures."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import measures
from ..operators import gating, timeline
from ..shared import saved
from ..sources import adapters as A
from ..streaming import gate as live
from . import tokens

TAU = 150000


def gate_targets_conversations(spark, d):
    return timeline.to_gate(A.timeline_conversations(spark, d)).select("video_id", "pos", "target", F.length("response").cast("long").alias("response_chars"), "prefix_end_s")


def gate_targets_events(spark, d):
    return A.gate_events(spark, d).select("video_id", "pos", "t_s", "speak")


def gate_memory_events(spark, d):
    return A.gate_events(spark, d).select("video_id", "pos", "memory", "gap_s")


def gate_balance_events(spark, d):
    return timeline.balance_silence(A.gate_events(spark, d), 3, 0.25).groupBy("video_id").agg(F.count("*").alias("kept"), F.sum("speak").alias("speak"))


def _fired(spark, d):
    return A.gate_events(spark, d).withColumns({"score": F.col("memory"), "fired": (F.col("memory") >= TAU).cast("int")})


def gate_scores_events(spark, d):
    """Probability of the gate: a logistic function of the memory."""
    p = 1 / (1 + F.exp(-(F.col("memory") - TAU) / 50000.0))
    return A.gate_events(spark, d).select("video_id", "pos", F.round(p, 6).alias("p_speak"))


def gate_loss_events(spark, d):
    """Class-weighted cross-entropy with inverse-frequency weights."""
    p = 1 / (1 + F.exp(-(F.col("memory") - TAU) / 50000.0))
    s = A.gate_events(spark, d).withColumn("p", p)
    n = s.agg(F.count("*").alias("n"), F.sum("speak").alias("k"))
    weight = F.when(F.col("speak") == 1, F.col("n") / (2 * F.col("k"))).otherwise(F.col("n") / (2 * (F.col("n") - F.col("k"))))
    nll = -F.log(F.greatest(F.when(F.col("speak") == 1, F.col("p")).otherwise(1 - F.col("p")), F.lit(1e-12)))
    return s.crossJoin(F.broadcast(n)).agg(F.count("*").alias("n"), F.round(F.sum(weight * nll) / F.sum(weight), 6).alias("loss"))


def gate_fit_events(spark, d):
    """Logistic gate fitted with class weights on even videos, everything else frozen; rows of odd ones it fires on."""
    s = saved(A.gate_events(spark, d).select("video_id", "memory", "gap_s", "speak"), "gate")
    weight = F.when(F.col("speak") == 1, 20.0).otherwise(1.0)
    base, memory, gap = gating.logistic_fit(s.filter("video_id % 2 = 0"), ["memory", "gap_s"], "speak", weight)
    fired = base + F.col("memory") * memory + F.col("gap_s") * gap > 0
    return s.filter("video_id % 2 = 1").groupBy("video_id").agg(F.count("*").alias("n"), F.count_if(fired).alias("fired"))


def response_context_events(spark, d):
    """The four most recent positions at each decision to speak."""
    w = Window.partitionBy("video_id").orderBy("pos").rowsBetween(-3, 0)
    s = _fired(spark, d).withColumn("context", F.array_join(F.collect_list("pos").over(w), ","))
    return s.filter("fired = 1").select("video_id", "pos", "context")


def recent_window_answers(spark, d):
    """Each user turn answered from the four latest assistant segments before it."""
    t = A.timeline_conversations(spark, d).select("video_id", F.col("end_s").alias("t_s"), F.col("seg_idx").alias("pos"))
    w = Window.partitionBy("conv_id").orderBy("turn")
    q = A.table(spark, d, "conversations").withColumn("t_s", F.sum(F.ceil(F.length("text") / 15)).over(w).cast("long")).filter("role = 'user'")
    return timeline.latest_before(q.select(F.col("conv_id").alias("video_id"), "t_s", F.col("turn").alias("query")), t, 4)


def repeated_segments_conversations(spark, d):
    return timeline.repeated_segments(A.timeline_conversations(spark, d), 0.05)


def bad_times_conversations(spark, d):
    t = A.timeline_conversations(spark, d)
    dur = A.table(spark, d, "conversations").groupBy(F.col("conv_id").alias("video_id")).agg((F.max("turn") * 20).alias("duration_s"))
    return timeline.bad_times(t, dur).select("video_id", "seg_idx", "start_s", "end_s", "duration_s")


def timing_metrics_events(spark, d):
    """Macro means over sequences for the gate and five plain baselines."""
    s = _fired(spark, d)
    from ..operators.curate import bucket

    rules = {
        "gate": F.col("fired"),
        "silent": F.lit(0),
        "speak": F.lit(1),
        "periodic": (F.col("pos") % 30 == 0).cast("int"),
        "random": (bucket("video_id", "pos") % 100 < 3).cast("int"),
        "activity": (F.col("gap_s") <= 60).cast("int"),
    }
    out = None
    for name, fired in rules.items():
        m = measures.timing(s.withColumn("fired", fired)).agg(F.count("*").alias("sequences"), *[F.round(F.avg(c), 6).alias(c) for c in ("trigger_acc", "timing_balance", "f1")])
        part = m.select(F.lit(name).alias("method"), "sequences", "trigger_acc", "timing_balance", "f1")
        out = part if out is None else out.union(part)
    return out


def ranking_metrics_events(spark, d):
    return measures.ranking(_fired(spark, d))


def timing_relaxed_events(spark, d):
    s = _fired(spark, d)
    return measures.relaxed_hits(s.filter("speak = 1"), s.filter("fired = 1"), 60)


def timeline_iou_conversations(spark, d):
    """Each span against itself shifted by five seconds."""
    t = A.timeline_conversations(spark, d)
    iou = measures.span_overlap(F.col("start_s"), F.col("end_s"), F.col("start_s") + 5, F.col("end_s") + 5)
    s = t.withColumn("iou", F.coalesce(iou, F.lit(0.0)))
    return s.agg(F.count("*").alias("n"), F.round(F.avg("iou"), 6).alias("mean_iou"), *[F.count_if(F.col("iou") >= x).alias(f"at_{int(x * 10)}") for x in (0.3, 0.5, 0.7)])


def tile_mask_jf_events(spark, d):
    """Tokens of the two selectors as masks."""
    from ..operators import select
    a = saved(tokens.tokens_events(spark, d), "tokens")
    imp = saved(tokens.importance_events(spark, d), "importance")
    b = saved(select.capped_by(select.code_length(imp, A.FRAMES), a, tokens.GOP, A.FRAMES, A.GRID, tokens.BUDGET), "tokens")
    return measures.region_and_border(a, b)


def stream_gate_events(spark, d):
    """The live gate over a file stream; equals the batch rows that fire."""
    return live.run_available(spark, d, TAU)


def stream_tumbling_counts(spark, d):
    return live.tumbling_available(spark, d)


_F = (gate_targets_conversations, gate_targets_events, gate_memory_events, gate_balance_events, gate_scores_events, gate_loss_events, gate_fit_events, response_context_events, recent_window_answers, repeated_segments_conversations, bad_times_conversations, timing_metrics_events, ranking_metrics_events, timing_relaxed_events, timeline_iou_conversations, tile_mask_jf_events, stream_gate_events, stream_tumbling_counts)
QUERIES = {f.__name__: f for f in _F}

TL = """c as (select *, ceil(length(text) / 15.0)::bigint cost from conversations),
cc as (select *, sum(cost) over (partition by conv_id order by turn)::bigint e from c),
tl as (select conv_id video_id, (row_number() over (partition by conv_id order by turn) - 1)::int seg_idx, e - cost start_s, e end_s, text caption from cc where role = 'assistant')"""
GE = f"""ev as (select user_id % 16 video_id, event_id, floor(epoch(ts))::bigint t_s, round(value * 100)::bigint c, (event_type = 'purchase' and round(value * 100) >= 10000)::int speak from events),
g as (select video_id, (row_number() over w - 1)::int pos, t_s, speak, (coalesce(lag(c, 1) over w, 0) * 4 + coalesce(lag(c, 2) over w, 0) * 3 + coalesce(lag(c, 3) over w, 0) * 2 + coalesce(lag(c, 4) over w, 0))::bigint memory,
  coalesce(t_s - lag(t_s) over w, 0)::bigint gap_s from ev window w as (partition by video_id order by t_s, event_id)),
s as (select *, memory score, (memory >= {TAU})::int fired from g)"""
RULES = {"gate": "fired", "silent": "0", "speak": "1", "periodic": "(pos % 30 = 0)::int", "random": "(('0x' || substr(md5('42:' || video_id || ':' || pos), 1, 8))::bigint % 100 < 3)::int", "activity": "(gap_s <= 60)::int"}
TIMING = """select '{name}' "method", count(*) sequences, round(avg(acc), 6) trigger_acc, round(avg(bal), 6) timing_balance, round(avg(f1), 6) f1 from (
  select round((tp + tn) / n::double, 6) acc, round(case when tp + fn = 0 or tn + fp = 0 then null when tp = 0 and tn = 0 then 0 else 2 * (tp / (tp + fn)::double) * (tn / (tn + fp)::double) / (tp / (tp + fn)::double + tn / (tn + fp)::double) end, 6) bal,
    round(2 * tp / nullif(2 * tp + fp + fn, 0)::double, 6) f1 from (
  select video_id, count(*) n, count(*) filter (speak = 1 and fr = 1) tp, count(*) filter (speak = 0 and fr = 1) fp, count(*) filter (speak = 1 and fr = 0) fn, count(*) filter (speak = 0 and fr = 0) tn from (select *, {rule} fr from s) group by 1))"""
P = f"1 / (1 + exp(-(memory - {TAU}) / 50000.0::double))"
SQL = {
    "gate_targets_conversations": f"""with {TL}, grid as (select video_id, unnest(range(0, max(end_s) + 1)) pos from tl group by 1), st as (select video_id, start_s, string_agg(caption, chr(10) order by seg_idx) r from tl group by 1, 2)
      select grid.video_id, pos, case when r is not null then 'speak' else 'silent' end target, coalesce(length(r), 0)::bigint response_chars, pos prefix_end_s from grid left join st on st.video_id = grid.video_id and start_s = pos""",
    "gate_targets_events": f"with {GE} select video_id, pos, t_s, speak from g",
    "gate_memory_events": f"with {GE} select video_id, pos, memory, gap_s from g",
    "gate_balance_events": f"""with {GE}, n as (select *, last_value(case when speak = 1 then pos end ignore nulls) over (partition by video_id order by pos rows between unbounded preceding and current row) a,
      first_value(case when speak = 1 then pos end ignore nulls) over (partition by video_id order by pos rows between current row and unbounded following) b from g)
      select video_id, count(*) kept, sum(speak)::bigint speak from n where coalesce(pos - a, 1000000) <= 3 or coalesce(b - pos, 1000000) <= 3 or ('0x' || substr(md5('42:' || video_id || ':' || pos), 1, 8))::bigint < 1073741824 group by 1""",
    "gate_scores_events": f"with {GE} select video_id, pos, round({P}, 6) p_speak from g",
    "gate_loss_events": f"""with {GE}, w as (select speak, {P} p, count(*) over () n, sum(speak) over () k from g), x as (select case when speak = 1 then n / (2.0::double * k) else n / (2.0::double * (n - k)) end w, -ln(greatest(case when speak = 1 then p else 1 - p end, 1e-12::double)) l from w)
      select count(*) n, round(sum(w * l) / sum(w), 6) loss from x""",
    "response_context_events": f"with {GE} select video_id, pos, context from (select *, array_to_string(list(pos) over (partition by video_id order by pos rows between 3 preceding and current row), ',') context from s) where fired = 1",
    "recent_window_answers": f"""with {TL}, q as (select conv_id video_id, e t_s, turn from cc where role = 'user')
      select q.video_id, q.t_s, turn query, greatest(count(tl.seg_idx) - 4, 0)::bigint from_pos, (count(tl.seg_idx) - 1)::bigint to_pos from q left join tl on tl.video_id = q.video_id and tl.end_s <= q.t_s group by 1, 2, 3""",
    "repeated_segments_conversations": f"""with {TL}, x as (select video_id, seg_idx, w, lag(w) over (partition by video_id order by seg_idx) b from (select *, list_distinct(string_split(lower(caption), ' ')) w from tl)),
      y as (select video_id, seg_idx, round(len(list_intersect(w, b)) / len(list_distinct(list_concat(w, b)))::double, 6) overlap from x where b is not null) select * from y where overlap >= 0.05""",
    "bad_times_conversations": f"with {TL}, d as (select conv_id video_id, (max(turn) * 20)::bigint duration_s from conversations group by 1) select video_id, seg_idx, start_s, end_s, duration_s from tl left join d using (video_id) where not (start_s >= 0 and start_s < end_s and end_s <= duration_s)",
    "timing_metrics_events": f"with {GE} " + " union all ".join(TIMING.format(name=n, rule=r) for n, r in RULES.items()),
    "ranking_metrics_events": f"""with {GE}, p as (select video_id, score, sum(speak) p, sum(1 - speak) q from s group by 1, 2),
      w as (select *, coalesce(sum(q) over (partition by video_id order by score rows between unbounded preceding and 1 preceding), 0) below, sum(p) over d hit, sum(q) over d miss, sum(p) over (partition by video_id) pp, sum(q) over (partition by video_id) nn from p window d as (partition by video_id order by score desc))
      select video_id, round(sum(p * (2 * below + q))::double / nullif(2 * max(pp) * max(nn), 0), 6) roc_auc, round(sum((p * hit)::double / nullif((hit + miss) * pp, 0)), 6) pr_auc from w group by 1""",
    "timing_relaxed_events": f"""with {GE}, t as (select distinct video_id, t_s from s where speak = 1), f as (select distinct video_id, t_s from s where fired = 1)
      select t.video_id, count(*) positives, count(*) filter (exists (select 1 from f where f.video_id = t.video_id and f.t_s between t.t_s - 60 and t.t_s + 60)) hits from t group by 1""",
    "timeline_iou_conversations": f"""with {TL}, x as (select greatest(0, end_s - start_s - 5)::double i, end_s - start_s l from tl), y as (select case when 2 * l - i > 0 then i / (2 * l - i) else 0 end v from x)
      select count(*) n, round(avg(v), 6) mean_iou, count(*) filter (v >= 0.3) at_3, count(*) filter (v >= 0.5) at_5, count(*) filter (v >= 0.7) at_7 from y""",
    "tile_mask_jf_events": f"""with {tokens.TOKENS_EVENTS} {tokens.CODED}, {tokens._ranked(16, 64, 4, 5, "lens", "0.0::double", "other")},
      m as (select 'a' s, clip_id, frame_idx, "row", col from tokens union all select 'b', clip_id, frame_idx, "row", col from other join (select clip_id, count(*) cap from tokens group by 1) using (clip_id) where rank_in_clip <= cap),
      e as (select * from m where (select count(*) from m n where n.s = m.s and n.clip_id = m.clip_id and n.frame_idx = m.frame_idx and abs(n."row" - m."row") + abs(n.col - m.col) = 1) < 4),
      j as (select clip_id, frame_idx, count(*) n, count(distinct ("row", col)) u from m group by 1, 2), f as (select clip_id, frame_idx, count(*) n, count(distinct ("row", col)) u from e group by 1, 2)
      select clip_id, frame_idx, round((j.n - j.u) / j.u::double, 6) j, round(coalesce(2 * (f.n - f.u) / nullif(f.n, 0)::double, 0), 6) f from j join f using (clip_id, frame_idx)""",
    "stream_gate_events": f"with {GE} select video_id, pos, t_s, memory from s where fired = 1",
    "stream_tumbling_counts": "select event_type, (floor(epoch(ts))::bigint // 86400 * 86400)::bigint window_start, count(*) n from events group by 1, 2",
}
