"""Selection workloads: budgets, modes, canvases, selectors, motion."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import motion, select
from ..shared import saved
from ..sources import adapters as A

BUDGET, GOP = 320, 16


def importance_events(spark, d):
    return select.weighted(A.tile_changes(A.tile_facts_events(spark, d), A.FRAMES))


def importance_lineitem(spark, d):
    return select.weighted(A.tile_changes(A.tile_facts_lineitem(spark, d), 84), alpha=100, beta=1)


def _complete(facts, frames, gop, grid, alpha=1000):
    """Importance with all anchor tiles, from one aggregate of facts."""
    return select.weighted(A.tile_changes(facts.unionByName(select.anchor_zeros(facts, gop, frames, *grid)), frames), alpha)


def tokens_events(spark, d, budget=BUDGET):
    imp = _complete(A.tile_facts_events(spark, d), A.FRAMES, GOP, A.GRID)
    return select.topk_budget(imp, budget, GOP, A.FRAMES, A.GRID, complete=True)


def topk_budget_events(spark, d):
    return tokens_events(spark, d).select("clip_id", "frame_idx", "row", "col", "importance", "is_anchor", "rank_in_clip")


def topk_budget_lineitem(spark, d):
    imp = _complete(A.tile_facts_lineitem(spark, d), 84, 12, (4, 7), 100)
    out = select.topk_budget(imp, 588, 12, 84, (4, 7), complete=True)
    return out.select("clip_id", "frame_idx", "row", "col", "importance", "is_anchor", "rank_in_clip")


def selected_coords_checksum(spark, d):
    return tokens_events(spark, d).groupBy("clip_id").agg(F.count("*").alias("tokens"), F.sum("frame_idx").alias("frames"), F.sum(F.col("row") * 10 + F.col("col")).alias("places"))


def _clips(spark, d):
    return A.table(spark, d, "events").select((F.col("user_id") % A.CLIPS).alias("clip_id")).distinct()


def chunkwise_events(spark, d):
    tiles = select.collage(_clips(spark, d), 16, A.FRAMES, A.GRID)
    return tiles.select("clip_id", "frame_idx", "row", "col")


def collage_events(spark, d):
    return select.collage(_clips(spark, d), 16, A.FRAMES, A.GRID)


def uniform_frames_events(spark, d):
    out = None
    for n in (4, 8, 16, 32, 64):
        part = select.uniform_frames(_clips(spark, d), n, A.FRAMES).select(F.lit(n).alias("n"), "clip_id", "frame_idx")
        out = part if out is None else out.union(part)
    return out


def token_reduction_events(spark, d):
    dense = A.FRAMES * A.GRID[0] * A.GRID[1]
    return tokens_events(spark, d).groupBy("clip_id").agg(F.count("*").alias("kept"), F.round(1 - F.count("*") / F.lit(float(dense)), 6).alias("reduction"))


def code_length_importance_events(spark, d):
    return select.code_length(importance_events(spark, d), A.FRAMES)


def cross_selector_events(spark, d):
    imp = saved(importance_events(spark, d), "importance")
    a = saved(tokens_events(spark, d), "tokens")
    b = select.capped_by(select.code_length(imp, A.FRAMES), a, GOP, A.FRAMES, A.GRID, BUDGET)
    key = list(select.KEY)
    both = a.select(*key, F.lit(1).alias("a")).join(b.select(*key, F.lit(1).alias("b")), key, "full")
    return both.groupBy("clip_id").agg(F.count("a").alias("used_a"), F.count("b").alias("used_b"), F.count_if(F.col("a").isNotNull() & F.col("b").isNotNull()).alias("shared")).withColumn("jaccard", F.round(F.col("shared") / (F.col("used_a") + F.col("used_b") - F.col("shared")), 6))


def block_match_embeddings(spark, d):
    return motion.block_match(A.frames_embeddings(spark, d), patch=2)


def _canvas(n):
    def query(spark, d):
        out = select.canvases(importance_events(spark, d), n, A.FRAMES, A.GRID, slots=40)
        return out.groupBy("clip_id").agg(F.count_distinct("canvas_idx").alias("n_canvas"), F.count("*").alias("tokens"), F.sum("importance").alias("mass"), F.sum("frame_idx").alias("frames"), F.sum(F.col("slot") * (F.col("row") + 1)).alias("slots"))

    return query


BUDGETS = (4, 8, 16, 32, 64)


def budget_rows(one_row, *columns):
    """(n, columns ...): the columns c4, c8 ... of one row, one row a budget."""
    return one_row.select(F.inline(F.array(*[F.struct(F.lit(n).alias("n"), *[make(n).alias(name) for name, make in columns]) for n in BUDGETS])))


def budget_curve_events(spark, d):
    """Importance caught by the budgeted selection and by uniform frames of as many tokens, N = 4 ... 64 frames.

    Each side is one aggregate over all budgets, so the selection is ranked once.
    """
    imp = importance_events(spark, d)
    tiles = A.GRID[0] * A.GRID[1]
    ranked = tokens_events(spark, d, BUDGETS[-1] * tiles)
    mass = F.col("importance")
    codec = ranked.agg(*[F.sum(F.when(F.col("rank_in_clip") <= n * tiles, mass)).alias(f"codec{n}") for n in BUDGETS])
    flat = imp.agg(F.sum(mass).alias("total"), *[F.sum(F.when(F.col("frame_idx").isin(select.uniform_indices(n, A.FRAMES)), mass)).alias(f"uniform{n}") for n in BUDGETS])
    one = codec.crossJoin(flat)  # a row each
    return budget_rows(one, *[(side, lambda n, side=side: F.round(F.col(f"{side}{n}") / F.col("total"), 6)) for side in ("codec", "uniform")])


def densest_segment_lineitem(spark, d):
    return select.densest_segment(importance_lineitem(spark, d), 12)


QUERIES = {f.__name__: f for f in (topk_budget_events, topk_budget_lineitem, selected_coords_checksum, chunkwise_events, collage_events, uniform_frames_events, token_reduction_events, code_length_importance_events, cross_selector_events, block_match_embeddings, budget_curve_events, densest_segment_lineitem)}
QUERIES |= {f"canvas_tc{n}_events": _canvas(n) for n in (8, 16, 32)}

IMP_EVENTS = """
ord as (select event_type, (row_number() over (order by event_type) - 1)::int col from (select distinct event_type from events)),
facts as (select user_id % 16 clip_id, (floor((epoch(ts) - 1704067200) / 40500))::int frame_idx, ((props->>'$.k')::int // 25)::int "row", col, 1::bigint n, round(value * 100)::bigint c from events join ord using (event_type)),
change as (select clip_id, frame_idx, "row", col, sum(n)::bigint dn, sum(c)::bigint dv from (
  select * from facts union all select clip_id, frame_idx + 1, "row", col, -n, -c from facts where frame_idx + 1 < 64) group by all),
imp as (select clip_id, frame_idx, "row", col, (1000 * abs(dn) + abs(dv))::bigint importance from change),
clips as (select distinct clip_id from imp)
"""
IMP_LINEITEM = """
facts as (select l_suppkey clip_id, ((year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1)::int frame_idx, (l_partkey % 4)::int "row", (l_linenumber - 1)::int col, l_quantity::bigint n, round(l_extendedprice * 100)::bigint c from lineitem),
change as (select clip_id, frame_idx, "row", col, sum(n)::bigint dn, sum(c)::bigint dv from (
  select * from facts union all select clip_id, frame_idx + 1, "row", col, -n, -c from facts where frame_idx + 1 < 84) group by all),
imp as (select clip_id, frame_idx, "row", col, (100 * abs(dn) + abs(dv))::bigint importance from change),
clips as (select distinct clip_id from imp)
"""


def _ranked(gop, frames, rows, cols, imp="imp", zero="0::bigint", name="ranked"):
    return f"""{name} as (select *, (row_number() over (partition by clip_id order by is_anchor desc, case when is_anchor then 0 else -importance end, frame_idx, "row", col))::int rank_in_clip from (
  select clip_id, frame_idx, "row", col, max(importance) importance, true is_anchor from (
    select clip_id, frame_idx, "row", col, importance from {imp} where frame_idx % {gop} = 0 union all
    select clip_id, (f.f * {gop})::int, r.r::int, c.c::int, {zero} from clips, range({-(-frames // gop)}) f(f), range({rows}) r(r), range({cols}) c(c)) group by 1, 2, 3, 4
  union all select clip_id, frame_idx, "row", col, importance, false from {imp} where frame_idx % {gop} <> 0 and importance > 0))"""


RANKED_EVENTS = IMP_EVENTS + "," + _ranked(16, 64, 4, 5)
TOKENS_EVENTS = RANKED_EVENTS + ", tokens as (select * from ranked where rank_in_clip <= 320)"
CODED = """,
coded as (select *, least(7, floor(log2(1.0 + importance)))::int symbol from imp),
model as (select "row", col, symbol, round(-log2((count(*) + case when symbol = 0 then size - stored else 0 end + 1)::double / (size + 8)), 6) bits
  from coded join (select "row", col, count(*) stored, (select count(*) from clips) * 64 size from coded group by 1, 2) using ("row", col) group by "row", col, symbol, size, stored),
lens as (select clip_id, frame_idx, "row", col, bits importance from coded join model using ("row", col, symbol))"""
UNIFORM = "(((2 * i + 1) * 64) // (2 * {n}))::int"
SQL = {
    "topk_budget_events": f'with {TOKENS_EVENTS} select clip_id, frame_idx, "row", col, importance, is_anchor, rank_in_clip from tokens',
    "topk_budget_lineitem": f'with {IMP_LINEITEM}, {_ranked(12, 84, 4, 7)} select clip_id, frame_idx, "row", col, importance, is_anchor, rank_in_clip from ranked where rank_in_clip <= 588',
    "selected_coords_checksum": f'with {TOKENS_EVENTS} select clip_id, count(*) tokens, sum(frame_idx)::bigint frames, sum("row" * 10 + col)::bigint places from tokens group by 1',
    "chunkwise_events": f"""select clip_id, {UNIFORM.format(n=16)} frame_idx, r::int "row", c::int col from (select distinct user_id % 16 clip_id from events), range(16) i(i), range(4) r(r), range(5) c(c)""",
    "collage_events": f"""select clip_id, {UNIFORM.format(n=16)} frame_idx, r::int "row", c::int col, (i * 4 + r)::int canvas_row from (select distinct user_id % 16 clip_id from events), range(16) i(i), range(4) r(r), range(5) c(c)""",
    "uniform_frames_events": " union all ".join(f"select {n} n, clip_id, {UNIFORM.format(n=n)} frame_idx from (select distinct user_id % 16 clip_id from events), range({n}) i(i)" for n in (4, 8, 16, 32, 64)),
    "token_reduction_events": f"with {TOKENS_EVENTS} select clip_id, count(*) kept, round(1 - count(*) / 1280.0::double, 6) reduction from tokens group by 1",
    "code_length_importance_events": f'with {IMP_EVENTS} {CODED} select clip_id, frame_idx, "row", col, importance from lens',
    "cross_selector_events": f"""with {TOKENS_EVENTS} {CODED}, {_ranked(16, 64, 4, 5, "lens", "0.0::double", "other")},
      b as (select o.* from other o join (select clip_id, count(*) cap from tokens group by 1) using (clip_id) where rank_in_clip <= cap),
      x as (select coalesce(t.clip_id, b.clip_id) clip_id, t.clip_id is not null a, b.clip_id is not null b from tokens t full join b using (clip_id, frame_idx, "row", col))
      select clip_id, count(*) filter (a) used_a, count(*) filter (b) used_b, count(*) filter (a and b) shared, round(count(*) filter (a and b) / count(*)::double, 6) jaccard from x group by 1""",
    "block_match_embeddings": """with px as (select vec_id // 64 clip_id, (vec_id % 64)::int frame_idx, ((i - 1) // 8)::int y, ((i - 1) % 8)::int x, round(embedding[i]::double * 1000)::int v from embeddings, range(1, 65) t(i)),
      cost as (select a.clip_id, a.frame_idx, (a.y // 2)::int "row", (a.x // 2)::int col, r::int mv_r, c::int mv_c, sum(abs(a.v - b.v)) sad, sum((a.v - b.v)::bigint * (a.v - b.v))::bigint residual, count(*) n
        from px a, range(-1, 2) r(r), range(-1, 2) c(c), px b where b.clip_id = a.clip_id and b.frame_idx = a.frame_idx - 1 and b.y = a.y + r and b.x = a.x + c group by all having count(*) = 4)
      select clip_id, frame_idx, "row", col, mv_r, mv_c, (abs(mv_r) + abs(mv_c))::int motion, residual from (select *, row_number() over (partition by clip_id, frame_idx, "row", col order by sad, abs(mv_r) + abs(mv_c), mv_r, mv_c) k from cost) where k = 1""",
    "budget_curve_events": f"with {RANKED_EVENTS} " + " union all ".join(
        f"""select {n} n, round((select sum(importance) from ranked where rank_in_clip <= {n * 20})::double / (select sum(importance) from imp), 6) codec,
        round((select sum(importance) from imp where frame_idx in (select {UNIFORM.format(n=n)} from range({n}) i(i)))::double / (select sum(importance) from imp), 6) uniform""" for n in (4, 8, 16, 32, 64)),
    "densest_segment_lineitem": f"""with {IMP_LINEITEM} select clip_id, segment, mass from (select clip_id, segment, mass, row_number() over (partition by clip_id order by mass desc, segment) k from (
      select clip_id, (frame_idx // 12)::int segment, sum(importance)::bigint mass from imp group by 1, 2)) where k = 1""",
}
for _n in (8, 16, 32):
    _m = min(_n * 8, 64)
    SQL[f"canvas_tc{_n}_events"] = f"""with {IMP_EVENTS},
      src as (select clip_id, (((2 * i + 1) * 64) // (2 * {_m}))::int frame_idx from clips, range({_m}) i(i)),
      mass as (select clip_id, frame_idx, coalesce(m, 0) + 1 m from src left join (select clip_id, frame_idx, sum(importance) m from imp group by 1, 2) using (clip_id, frame_idx)),
      cum as (select *, sum(m) over (partition by clip_id order by frame_idx) s, sum(m) over (partition by clip_id) total from mass),
      grp as (select clip_id, frame_idx, least({_n - 1}, ({_n} * (s - 1)) // total)::int canvas_idx from cum),
      head as (select *, frame_idx = min(frame_idx) over (partition by clip_id, canvas_idx) is_anchor from grp),
      tiles as (select clip_id, canvas_idx, frame_idx, r::int "row", c::int col, 0::bigint importance, is_anchor from head, range(4) r(r), range(5) c(c) where is_anchor
        union all select clip_id, canvas_idx, frame_idx, "row", col, importance, is_anchor from imp join head using (clip_id, frame_idx) where importance > 0 and not is_anchor),
      cut as (select * from (select *, row_number() over (partition by clip_id, canvas_idx, is_anchor order by importance desc, frame_idx, "row", col) k from tiles) where k <= 20),
      slots as (select *, row_number() over (partition by clip_id, canvas_idx order by frame_idx, "row", col) - 1 slot from cut)
      select clip_id, count(distinct canvas_idx) n_canvas, count(*) tokens, sum(importance)::bigint mass, sum(frame_idx)::bigint frames, sum(slot * ("row" + 1))::bigint slots from slots group by 1"""
