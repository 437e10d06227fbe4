"""Workloads on what leaves the selector, on gates' histories and curves, and on mixtures."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..operators import gating, select, sequence
from ..shared import saved
from ..sources import adapters as A
from . import gates, tokens
from .tokens import BUDGET, BUDGETS, GOP, UNIFORM

#: A clock eight times as fine, so that canvases of 64 source frames for each of 8 to 64 canvases exist.
FINE_FRAMES, FINE_SECONDS = 512, 5062.5
#: Tiles of a canvas in the curve: as many as a frame has, so that N canvases and N frames cost the same.
SLOTS = 20


def _changes(spark, d):
    return A.tile_changes(A.tile_facts_events(spark, d), A.FRAMES)


def _places(column):
    """Positions as text, in order."""
    return F.md5(F.array_join(F.transform(column, lambda t: F.concat_ws(":", t["frame_idx"], t["row"], t["col"])), ","))


def still_image_tokens_embeddings(spark, d):
    e = A.table(spark, d, "embeddings").select("vec_id", F.posexplode("embedding").alias("i", "v"))
    tiles = e.groupBy(F.col("vec_id").alias("clip_id"), F.expr("cast(i div 16 as int)").alias("row"), F.expr("cast((i % 8) div 2 as int)").alias("col"))
    return sequence.still_image(tiles.agg(F.sum(F.abs(F.round(F.col("v").cast("double") * 1000).cast("long"))).alias("importance")), 12)


def rotary_positions_events(spark, d):
    """Angles of kept tokens in the un-pruned grid, summed by clip."""
    made = sequence.rotary(tokens.tokens_events(spark, d))
    return made.groupBy("clip_id").agg(F.count("*").alias("tokens"), *[F.round(F.sum(F.get("angles", F.lit(j))), 4).alias(f"a{j}") for j in range(8)])


def padded_batches_events(spark, d):
    made = sequence.pack_sequences(tokens.tokens_events(spark, d), 4)
    return made.select("clip_id", "batch_idx", "valid_len", "pad_len", F.array_join("mask", "").alias("mask"), _places(F.col("tokens")).alias("places"))


def fixed_sequences_events(spark, d):
    """Sequences filled with zeros to 400 rows, and the same length by mask."""
    got = tokens.tokens_events(spark, d)
    filled = sequence.zero_filled(got, 400).groupBy("clip_id").agg(F.count("*").alias("rows"), F.count_if("is_pad").alias("pads"), F.sum("importance").alias("mass"), F.max("rank_in_clip").alias("last"))
    masked = sequence.pack_sequences(got, 4, 400).select("clip_id", "valid_len", "pad_len")
    return filled.join(masked, "clip_id")


def codec_windows_events(spark, d):
    made = sequence.codec_windows(tokens.tokens_events(spark, d), GOP)
    return made.select("clip_id", "window_idx", F.size("anchors").alias("n_anchors"), F.size("updates").alias("n_updates"), _places(F.concat("anchors", "updates")).alias("places"))


def ratio_budget_events(spark, d):
    out = None
    for percent in (10, 25, 50):
        kept = sequence.ratio_budget(tokens.importance_events(spark, d), percent / 100, GOP, A.FRAMES, A.GRID)
        part = kept.groupBy("clip_id").agg(F.lit(percent).alias("percent"), F.count("*").alias("tokens"), F.count_if("is_anchor").alias("anchors"), F.sum("importance").alias("mass"))
        out = part if out is None else out.union(part)
    return out


def bits_budget_events(spark, d):
    bits = select.code_length(tokens.importance_events(spark, d), A.FRAMES)
    return sequence.bits_budget(bits, 500).groupBy("clip_id").agg(F.count("*").alias("tokens"), F.sum("micro").alias("micro_bits"), F.sum("frame_idx").alias("frames"))


def scene_cuts_events(spark, d):
    imp = tokens.importance_events(spark, d)
    return sequence.scene_cuts(imp, imp.select("clip_id").distinct(), A.FRAMES, GOP)


def fps_frames_events(spark, d):
    clips = A.table(spark, d, "events").select((F.col("user_id") % A.CLIPS).alias("clip_id")).distinct()
    some = [sequence.by_fps(clips, A.FRAMES, 8, fps, 32).select(F.lit(fps).alias("fps"), "clip_id", "frame_idx") for fps in (1, 4, 8)]
    return some[0].union(some[1]).union(some[2])


def selector_registry_events(spark, d):
    """Each registered selector through the same budget."""
    changes, out = _changes(spark, d), None
    for name in ("motion", "motion_residual", "residual"):
        kept = select.topk_budget(sequence.importance_by(name, changes), BUDGET, GOP, A.FRAMES, A.GRID)
        part = kept.groupBy("clip_id").agg(F.count("*").alias("tokens"), F.sum("importance").alias("mass"), F.sum("frame_idx").alias("frames")).select(F.lit(name).alias("selector"), "clip_id", "tokens", "mass", "frames")
        out = part if out is None else out.union(part)
    return out


def budget_gain_events(spark, d):
    """Area between the two curves of ``budget_curve_events``."""
    return sequence.gain_area(tokens.budget_curve_events(spark, d).select("n", F.col("codec").alias("a"), F.col("uniform").alias("b")))


def _fine(spark, d):
    return select.weighted(A.tile_changes(A.tile_facts_events(spark, d, FINE_SECONDS), FINE_FRAMES))


def canvas_curve_events(spark, d):
    """Importance caught by N canvases of tiles chosen from 8 N frames, and by N whole frames, of 512."""
    imp, out = saved(_fine(spark, d), "importance"), None
    total = imp.agg(F.sum("importance").alias("total"))
    for n in BUDGETS:
        packed = select.canvases(imp, n, FINE_FRAMES, A.GRID, SLOTS).agg(F.sum("importance").alias("m"), F.count("*").alias("tokens"))
        flat = imp.filter(F.col("frame_idx").isin(select.uniform_indices(n, FINE_FRAMES))).agg(F.sum("importance").alias("u"))
        one = packed.crossJoin(flat).crossJoin(total)  # a row each
        part = one.select(F.lit(n).alias("n"), "tokens", F.round(F.coalesce(F.col("m") / F.col("total"), F.lit(0.0)), 6).alias("canvas"), F.round(F.coalesce(F.col("u") / F.col("total"), F.lit(0.0)), 6).alias("frames"))
        out = part if out is None else out.union(part)
    return out


def canvas_gain_events(spark, d):
    """Area between canvases and frames over N = 4 ... 64."""
    return sequence.gain_area(canvas_curve_events(spark, d).select("n", F.col("canvas").alias("a"), F.col("frames").alias("b")))


def _logit():
    return (F.col("memory") - gates.TAU) / 50000.0


def gate_argmax_events(spark, d):
    """The greater of two logits, beside the threshold of one half on the probability."""
    s = A.gate_events(spark, d).withColumns({"fired": gating.argmax(F.lit(0.0), _logit()), "half": (1 / (1 + F.exp(-_logit())) > 0.5).cast("int")})
    return s.groupBy("video_id").agg(F.count("*").alias("n"), F.sum("fired").alias("fired"), F.count_if(F.col("fired") != F.col("half")).alias("differ"))


def gate_history_events(spark, d):
    return gating.with_history(A.gate_events(spark, d), 3, 0.5, _logit()).select("video_id", "pos", F.round("p_speak", 6).alias("p_speak"))


def gate_accumulated_events(spark, d):
    return gating.accumulated(A.gate_events(spark, d), "gap_s").select("video_id", "pos", "held", "most", "since")


def threshold_curve_events(spark, d):
    return gating.threshold_curve(A.gate_events(spark, d), "memory", list(range(0, 400001, 50000)))


def unified_timelines(spark, d):
    spoken = A.gate_events(spark, d).filter("speak = 1")
    return gating.normalized({"captions": A.timeline_conversations(spark, d), "events": spoken}).select("source", "video_id", "start_s", "end_s", "kind", F.length("text").alias("chars"))


def causality_events(spark, d):
    """Decisions that use a later feature: of the gate's own features, and of a feature read one row ahead, planted here."""
    g = A.gate_events(spark, d)
    w = gating.in_order()
    own = gating.late_features(g, F.lag("t_s").over(w))
    leak = gating.late_features(g, F.lead("t_s").over(w)).select("video_id", F.col("late").alias("planted"))
    return own.join(leak, "video_id")


def mixture_error_documents(spark, d):
    """Languages of the corpus against an even mixture."""
    counts = A.table(spark, d, "documents").groupBy(F.col("lang").alias("component")).agg(F.count("*").alias("n"))
    even = counts.select("component", (1 / F.count("*").over(Window.partitionBy(F.lit(1)))).alias("target"))  # a row a language
    return sequence.mixture_error(counts, even)


def dense_lattice_events(spark, d):
    dense = sequence.densified(tokens.importance_events(spark, d), A.FRAMES, A.GRID)
    return dense.groupBy("clip_id", "frame_idx").agg(F.count("*").alias("tiles"), F.sum("importance").alias("mass"), F.count_if(F.col("importance") == 0).alias("still"))


def anchor_overflow_events(spark, d):
    """A budget of 60 where anchors are 80, cut and kept."""
    imp, out = tokens.importance_events(spark, d), None
    for how in ("truncate", "keep"):
        kept = sequence.with_overflow(imp, 60, how, GOP, A.FRAMES, A.GRID)
        part = kept.groupBy("clip_id").agg(F.lit(how).alias("how"), F.count("*").alias("tokens"), F.count_if("is_anchor").alias("anchors"), F.max("frame_idx").alias("last_frame"), F.bool_and("overflow").alias("overflow"))
        out = part if out is None else out.union(part)
    return out


_F = (
    still_image_tokens_embeddings, rotary_positions_events, padded_batches_events, fixed_sequences_events, codec_windows_events, ratio_budget_events, bits_budget_events,
    scene_cuts_events, fps_frames_events, selector_registry_events, budget_gain_events, canvas_curve_events, canvas_gain_events, gate_argmax_events, gate_history_events,
    gate_accumulated_events, threshold_curve_events, unified_timelines, causality_events, mixture_error_documents, dense_lattice_events, anchor_overflow_events,
)
QUERIES = {f.__name__: f for f in _F}

TOK = tokens.TOKENS_EVENTS
PLACE = """string_agg(concat_ws(':', frame_idx, "row", col), ',' order by {order})"""
AREA = "select round(sum((x2 - x) * (d + d2) / 2) / (max(x) - min(x)), 6) area from (select log2(n) x, {a} - {b} d, lead(log2(n)) over (order by n) x2, lead({a} - {b}) over (order by n) d2 from curve)"
ANGLES = ", ".join(f"round(sum({c} * {10000.0 ** (-j / p)!r}::double), 4) a{i}" for i, (c, j, p) in enumerate([("frame_idx", 0, 2), ("frame_idx", 1, 2), *[(c, j, 3) for c in ('"row"', "col") for j in range(3)]]))
FINE = tokens.IMP_EVENTS.replace("/ 40500", "/ 5062.5::double").replace("< 64)", "< 512)").replace("+ 1 < 64", "+ 1 < 512")


def _canvas_sql(n):
    m = min(8 * n, FINE_FRAMES)
    return f"""src{n} as (select clip_id, (((2 * i + 1) * 512) // (2 * {m}))::int frame_idx from clips, range({m}) i(i)),
      cum{n} as (select *, sum(m) over (partition by clip_id order by frame_idx) s, sum(m) over (partition by clip_id) total from (
        select clip_id, frame_idx, coalesce(m, 0) + 1 m from src{n} left join (select clip_id, frame_idx, sum(importance) m from imp group by 1, 2) using (clip_id, frame_idx))),
      head{n} as (select *, frame_idx = min(frame_idx) over (partition by clip_id, canvas_idx) is_anchor from (select clip_id, frame_idx, least({n - 1}, ({n} * (s - 1)) // total)::int canvas_idx from cum{n})),
      tiles{n} as (select clip_id, canvas_idx, frame_idx, r::int "row", c::int col, 0::bigint importance, is_anchor from head{n}, range(4) r(r), range(5) c(c) where is_anchor
        union all select clip_id, canvas_idx, frame_idx, "row", col, importance, is_anchor from imp join head{n} using (clip_id, frame_idx) where importance > 0 and not is_anchor),
      cut{n} as (select * from (select *, row_number() over (partition by clip_id, canvas_idx, is_anchor order by importance desc, frame_idx, "row", col) k from tiles{n}) where k <= {SLOTS // 2})"""


CURVE = f"with {FINE}, " + ", ".join(_canvas_sql(n) for n in BUDGETS) + ", curve as (" + " union all ".join(
    f"""select {n} n, (select count(*) from cut{n}) tokens, round((select sum(importance) from cut{n})::double / (select sum(importance) from imp), 6) canvas,
    round(coalesce((select sum(importance) from imp where frame_idx in (select (((2 * i + 1) * 512) // (2 * {n}))::int from range({n}) i(i))), 0)::double / (select sum(importance) from imp), 6) frames""" for n in BUDGETS) + ")"  # fmt: skip
Z = f"((memory - {gates.TAU}) / 50000.0::double)"
SQL = {
    "still_image_tokens_embeddings": """with t as (select vec_id clip_id, ((i - 1) // 16)::int "row", (((i - 1) % 8) // 2)::int col, sum(abs(round(embedding[i]::double * 1000)::bigint))::bigint importance from embeddings, range(1, 65) r(i) group by 1, 2, 3)
      select clip_id, "row", col, importance, ("row" * 4 + col)::int token_pos from t where "row" * 4 + col < 12""",
    "rotary_positions_events": f"with {TOK} select clip_id, count(*) tokens, {ANGLES} from tokens group by 1",
    "padded_batches_events": f"""with {TOK}, s as (select clip_id, clip_id // 4 batch_idx, count(*)::int valid_len, md5({PLACE.format(order='frame_idx, "row", col')}) places from tokens group by 1),
      l as (select *, max(valid_len) over (partition by batch_idx) pad_len from s) select clip_id, batch_idx, valid_len, pad_len, repeat('1', valid_len) || repeat('0', pad_len - valid_len) mask, places from l""",
    "fixed_sequences_events": f"""with {TOK} select clip_id, greatest(count(*), 400) "rows", greatest(400 - count(*), 0) pads, sum(importance)::bigint mass, greatest(max(rank_in_clip), 400)::int "last", count(*)::int valid_len, 400 pad_len from tokens group by 1""",
    "codec_windows_events": f"""with {TOK} select clip_id, (frame_idx // 16)::int window_idx, count(*) filter (is_anchor)::int n_anchors, count(*) filter (not is_anchor)::int n_updates, md5({PLACE.format(order='is_anchor desc, frame_idx, "row", col')}) places from tokens group by 1, 2""",
    "ratio_budget_events": f"with {tokens.RANKED_EVENTS} " + " union all ".join(f"select clip_id, {p} percent, count(*) tokens, count(*) filter (is_anchor) anchors, sum(importance)::bigint mass from ranked where rank_in_clip <= {1280 * p // 100} group by 1" for p in (10, 25, 50)),
    "bits_budget_events": f"""with {tokens.IMP_EVENTS} {tokens.CODED}, m as (select *, round(importance * 1000000)::bigint micro from lens),
      r as (select *, coalesce(sum(micro) over (partition by clip_id order by importance desc, frame_idx, "row", col rows between unbounded preceding and 1 preceding), 0) before from m)
      select clip_id, count(*) tokens, sum(micro)::bigint micro_bits, sum(frame_idx)::bigint frames from r where before < 500000000 group by 1""",
    "scene_cuts_events": f"""with {tokens.IMP_EVENTS}, mass as (select clip_id, frame_idx, sum(importance) m from imp group by 1, 2), t as (select *, sum(m) over (partition by clip_id) total from mass)
      select clip_id, (f * 16)::int frame_idx, 'gop' why from clips, range(4) r(f) union all select clip_id, frame_idx, 'cut' from t where m * 64 > 2 * total and frame_idx % 16 <> 0""",
    "fps_frames_events": f"""with c as (select distinct user_id % 16 clip_id from events) select 1 fps, clip_id, (i * 8)::int frame_idx from c, range(8) r(i) union all select 4, clip_id, (i * 2)::int from c, range(32) r(i)
      union all select 8, clip_id, {UNIFORM.format(n=32)} from c, range(32) r(i)""",
    "selector_registry_events": " union all ".join(
        f"select * from (with {tokens.IMP_EVENTS.replace('(1000 * abs(dn) + abs(dv))', w)}, {tokens._ranked(16, 64, 4, 5)} select '{name}' selector, clip_id, count(*) tokens, sum(importance)::bigint mass, sum(frame_idx)::bigint frames from ranked where rank_in_clip <= 320 group by 2)"
        for name, w in (("motion", "(abs(dn))"), ("motion_residual", "(1000 * abs(dn) + abs(dv))"), ("residual", "(abs(dv))"))),
    "budget_gain_events": f"with curve as ({tokens.SQL['budget_curve_events']}) " + AREA.format(a="codec", b="uniform"),
    "canvas_curve_events": CURVE + " select n, tokens, canvas, frames from curve",
    "canvas_gain_events": CURVE + " " + AREA.format(a="canvas", b="frames"),
    "gate_argmax_events": f"with {gates.GE} select video_id, count(*) n, count(*) filter ({Z} > 0) fired, count(*) filter (({Z} > 0) <> (1 / (1 + exp(-{Z})) > 0.5)) differ from g group by 1",
    "gate_history_events": f"""with {gates.GE}, h as (select *, coalesce(lag(speak, 1) over w, 0) + coalesce(lag(speak, 2) over w, 0) + coalesce(lag(speak, 3) over w, 0) k from g window w as (partition by video_id order by pos))
      select video_id, pos, round(1 / (1 + exp(-({Z} - 0.5::double * k))), 6) p_speak from h""",
    "gate_accumulated_events": f"""with {gates.GE} select video_id, pos, coalesce(sum(gap_s) over w, 0)::bigint held, coalesce(max(gap_s) over w, 0)::bigint "most", (pos - coalesce(max(case when speak = 1 then pos end) over w, -1))::int since
      from g window w as (partition by video_id order by pos rows between unbounded preceding and 1 preceding)""",
    "threshold_curve_events": f"""with {gates.GE}, x as (select (t * 50000)::int tau, count(*) filter (memory >= t * 50000 and speak = 1) tp, count(*) filter (memory >= t * 50000 and speak = 0) fp, count(*) filter (memory < t * 50000 and speak = 1) fn from g, range(9) r(t) group by 1)
      select tau, tp, fp, fn, round(tp / nullif(tp + fp, 0)::double, 6) "precision", round(tp / nullif(tp + fn, 0)::double, 6) recall from x""",
    "unified_timelines": f"""with {gates.TL}, {gates.GE} select 'captions' source, video_id, start_s, end_s, case when start_s < end_s then 'span' else 'point' end kind, length(caption)::int chars from tl
      union all select 'events', video_id, t_s, t_s, 'point', 0 from g where speak = 1""",
    "causality_events": f"""with {gates.GE}, x as (select video_id, t_s, lag(t_s) over w a, lead(t_s) over w b from g window w as (partition by video_id order by pos))
      select video_id, count(*) decisions, count(*) filter (a > t_s) late, count(*) filter (b > t_s) planted from x group by 1""",
    "dense_lattice_events": f"""with {tokens.IMP_EVENTS} select l.clip_id, f::int frame_idx, count(*) tiles, sum(coalesce(importance, 0))::bigint mass, count(*) filter (coalesce(importance, 0) = 0) still
      from (select clip_id, f, r, c from clips, range(64) f(f), range(4) r(r), range(5) c(c)) l left join imp i on i.clip_id = l.clip_id and i.frame_idx = f and i."row" = r and i.col = c group by 1, 2""",
    "anchor_overflow_events": f"with {tokens.RANKED_EVENTS} " + " union all ".join(f"select clip_id, '{how}' how, count(*) tokens, count(*) filter (is_anchor) anchors, max(frame_idx)::int last_frame, true overflow from ranked where rank_in_clip <= {n} group by 1" for how, n in (("truncate", 60), ("keep", 80))),
    "mixture_error_documents": """with c as (select lang component, count(*) n from documents group by 1), s as (select component, n, n / (sum(n) over ())::double share, 1 / (count(*) over ())::double target from c)
      select component, n, round(share, 6) share, round(target, 6) target, round(abs(share - target), 6) error, max(round(abs(share - target), 6)) over () worst from s""",
}
