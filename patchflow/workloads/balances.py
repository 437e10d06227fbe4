"""Balance and stage-draw workloads."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import balance
from ..plans.stages import STAGES
from ..sources import adapters as A
from .curation import B

SHARES = {"to30": 0.2, "to60": 0.3, "to180": 0.4, "gap": 0.1}


def duration_balance_documents(spark, d):
    return balance.durations(A.samples(spark, d), SHARES).select("sample_id", "stratum")


def downweight_documents(spark, d):
    """Rows whose caption never names a moment count a tenth, by language."""
    w = balance.downweight(~F.col("text").rlike(r"\d"), 0.1)
    return A.samples(spark, d).groupBy("lang").agg(F.round(F.sum(w), 6).alias("weight"), F.count("*").alias("n"))


def interleave_documents(spark, d):
    """Three labelled rows, then one unlabelled, in each shard."""
    s = A.samples(spark, d)
    return balance.interleave(s.filter("quality is null"), s.filter("quality is not null"), 3, 8)


def granularity_documents(spark, d):
    return balance.granularity(A.samples(spark, d))


def unique_videos_documents(spark, d):
    """A document used whole and in segments is one video."""
    s = A.samples(spark, d)
    uses = s.select(F.lit("clip").alias("kind"), "sample_id").unionByName(balance.granularity(s).filter("parts > 1").select(F.lit("segment").alias("kind"), "sample_id"))
    return balance.unique_videos(uses)


def _shares(stage: int) -> dict[str, float]:
    total = sum(STAGES[stage].values())
    return {k: v / total for k, v in STAGES[stage].items()}


def stage_sample_documents(spark, d):
    """Stage 4 drawn from the corpus in its published shares."""
    return balance.stage_draw(A.samples(spark, d), _shares(4))


def caption_consistency_conversations(spark, d):
    """Activity (characters said, at the second a turn ends) inside each caption's span."""
    t = A.timeline_conversations(spark, d)
    act = A.table(spark, d, "conversations").groupBy("conv_id", "turn").agg(F.sum(F.length("text")).cast("long").alias("amount"))
    return balance.consistency(t, act.select(F.col("conv_id").alias("video_id"), (F.col("turn") * 20).alias("t_s"), "amount"))


_F = (duration_balance_documents, downweight_documents, interleave_documents, granularity_documents, unique_videos_documents, stage_sample_documents, caption_consistency_conversations)
QUERIES = {f.__name__: f for f in _F}

_ST = "case when d <= 30 then 'to30' when d <= 60 then 'to60' when d <= 180 then 'to180' when d < 600 then 'gap' when d <= 900 then 'to900' else 'over' end"
_GR = """g as (select doc_id sample_id, d, case when d <= 180 then [0] else range(0, d, 60) end st from (select doc_id, ceil(n_chars / 15.0)::bigint d from documents)),
  p as (select sample_id, d, len(st)::int parts, unnest(range(0, len(st)))::int part, unnest(st)::bigint start_s from g)"""


def _cuts(shares: dict[str, float]) -> str:
    parts, low = [], 0.0
    for name, share in shares.items():
        parts.append(f"when u >= {low!r}::double and u < {low + share!r}::double then '{name}'")
        low += share
    return "case " + " ".join(parts) + " end"


SQL = {
    "duration_balance_documents": f"""with s as (select doc_id sample_id, {_ST} stratum, {B.format(seed=11, id='doc_id')} / 4294967296.0 u from (select doc_id, ceil(n_chars / 15.0)::bigint d from documents)),
      n as (select stratum, n, share from (select stratum, count(*) n from s group by 1) join (values {', '.join(f"('{k}', {v}::double)" for k, v in SHARES.items())}) v(stratum, share) using (stratum))
      select sample_id, stratum from s join n using (stratum) where u < (select min(n / share) from n) * share / n""",
    "downweight_documents": "select lang, round(sum(case when regexp_matches(text, '[0-9]') then 1.0::double else 0.1::double end), 6) weight, count(*) n from documents group by 1",
    "interleave_documents": f"""with s as (select doc_id sample_id, quality is not null lab, {B.format(seed=3, id='doc_id')} b from documents left join labels using (doc_id)),
      i as (select *, (b % 8)::int shard, row_number() over (partition by b % 8, lab order by b, sample_id) - 1 i from s)
      select shard, (row_number() over (partition by shard order by case when lab then i * 4 + 3 else i // 3 * 4 + i % 3 end, lab) - 1)::int pos, case when lab then 'b' else 'a' end side, sample_id from i""",
    "granularity_documents": f"with {_GR} select sample_id, part, start_s, case when parts = 1 then d else least(start_s + 60, d) end end_s, parts from p",
    "unique_videos_documents": f"with {_GR}, u as (select 'clip' kind, doc_id sample_id from documents union all select 'segment', sample_id from p where parts > 1) select kind, count(*) n, count(distinct sample_id) videos from u group by rollup (kind)",
    "stage_sample_documents": f"select * from (select sample_id, {_cuts(_shares(4))} component from (select doc_id sample_id, {B.format(seed=5, id='doc_id')} / 4294967296.0 u from documents)) where component is not null",
    "caption_consistency_conversations": """with c as (select *, sum(ceil(length(text) / 15.0)::bigint) over (partition by conv_id order by turn) e from conversations),
      t as (select conv_id video_id, (row_number() over (partition by conv_id order by turn) - 1)::int seg_idx, (e - ceil(length(text) / 15.0)::bigint)::bigint s, e::bigint e from c where role = 'assistant')
      select video_id, seg_idx, coalesce(sum(length(text)), 0)::bigint activity from t left join conversations on conv_id = video_id and turn * 20 >= s and turn * 20 < e group by 1, 2""",
}
