"""Curation, balance, strata and sampling workloads."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..operators import curate
from ..sources import adapters as A


def curate_documents(spark, d):
    return curate.reasons(A.samples(spark, d)).select("sample_id", "reasons")


def filter_quality_labels(spark, d):
    """Precision and recall counts of the rules against the quality labels."""
    s = curate.reasons(A.samples(spark, d).filter("quality is not null"))
    bad, hit = F.col("quality") == 0, F.col("reasons") != ""
    return s.agg(F.count_if(hit & bad).alias("hit_bad"), F.count_if(hit & ~bad).alias("hit_good"), F.count_if(~hit & bad).alias("missed_bad"), F.count_if(~hit & ~bad).alias("kept_good"))


def unsafe_lexicon(spark, d):
    return curate.learn_lexicon(A.samples(spark, d))


def unsafe_recall(spark, d):
    """The learned words on the other half of the labels: toxic found, toxic missed, clean hit."""
    s = A.samples(spark, d)
    lexicon = curate.learn_lexicon(s).select("word")
    rest = s.filter("toxic is not null").filter(curate.bucket("sample_id") % 2 == 1)
    hit = rest.select("sample_id", F.explode(F.array_distinct(curate.words(F.col("text")))).alias("word")).join(lexicon, "word", "left_semi").select("sample_id").distinct().withColumn("hit", F.lit(1))
    return rest.join(hit, "sample_id", "left").agg(*[F.count_if(F.expr(e)).alias(n) for n, e in (("found", "toxic = 1 and hit = 1"), ("missed", "toxic = 1 and hit is null"), ("wrong", "toxic = 0 and hit = 1"))])


def exact_dedup_documents(spark, d):
    return curate.exact_duplicates(A.samples(spark, d))


def duration_strata_documents(spark, d):
    s = A.samples(spark, d)
    return s.groupBy(curate.stratum(F.col("duration_s")).alias("stratum")).agg(F.count("*").alias("n"), F.sum(curate.frame_cap(F.col("duration_s"))).alias("frames"))


def duration_strata_orders(spark, d):
    s = A.table(spark, d, "orders").select((F.col("o_orderkey") * 7 % 1200).alias("duration_s"))
    return s.groupBy(curate.stratum(F.col("duration_s")).alias("stratum")).agg(F.count("*").alias("n"), F.sum(curate.frame_cap(F.col("duration_s"))).alias("frames"))


def domain_balance_documents(spark, d):
    return curate.balanced(A.samples(spark, d)).groupBy("domain").agg(F.count("*").alias("n"), F.sum("copies").alias("copies"))


def stage_plan(spark, d):
    """Rows and weight of each component of a stage: orders of a priority, by pool of customers."""
    o = A.table(spark, d, "orders").groupBy(F.substring("o_orderpriority", 1, 1).cast("int").alias("stage"), F.concat(F.lit("pool_"), F.col("o_custkey") % 4).alias("component")).agg(F.count("*").alias("target_rows"))
    return o.withColumn("weight", F.round(F.col("target_rows") / F.sum("target_rows").over(Window.partitionBy("stage")), 6))


def stage_nesting(spark, d):
    """Rows of nested retained shares, and those of the smaller one that the larger lacks (none)."""
    s = A.samples(spark, d).select("sample_id")
    big, small = curate.retained(s, 0.74), curate.retained(s, 0.37)
    return big.agg(F.count("*").alias("large")).crossJoin(small.agg(F.count("*").alias("small"))).crossJoin(small.join(big, "sample_id", "left_anti").agg(F.count("*").alias("lost")))


def rollout_sample(spark, d):
    return curate.stratified(A.samples(spark, d), 20, 10).select("sample_id", "domain", "rank")


def validation_sample(spark, d):
    """The next rows by hash order, none of them in the rollout."""
    s = A.samples(spark, d)
    rest = s.join(curate.stratified(s, 20, 10).select("sample_id"), "sample_id", "left_anti")
    return rest.orderBy(curate.bucket("sample_id", seed=7), "sample_id").limit(200).select("sample_id", "domain")


def rubric_documents(spark, d):
    r = curate.rubric(A.samples(spark, d))
    return r.groupBy("domain").agg(F.round(F.avg("redundancy"), 6).alias("redundancy"), F.sum("n_words").alias("n_words"), F.sum("n_sentences").alias("n_sentences"))


def mode_mix_documents(spark, d):
    """Codec, chunk and collage by md5 in the shares 50, 40 and 10."""
    b = curate.bucket("sample_id") % 100
    return A.samples(spark, d).groupBy(F.when(b < 50, "codec").when(b < 90, "chunk").otherwise("collage").alias("mode")).agg(F.count("*").alias("n"))


def mixture_cube_orders(spark, d):
    t = lambda n: A.table(spark, d, n)
    facts = t("orders").join(t("customer"), F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(t("nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return facts.cube("r_name", "c_mktsegment").agg(F.count("*").alias("n"), F.sum(A.cents("o_totalprice")).alias("cents"), F.grouping_id().alias("level"))


def resolution_pack_part(spark, d):
    """Images of one size in batches of about 4,096 tokens."""
    p = A.table(spark, d, "part").select("p_partkey", (224 + 16 * (F.col("p_size") % 15)).cast("int").alias("side"))
    tokens = F.expr("(side div 16) * (side div 16)")
    w = Window.partitionBy("side").orderBy("p_partkey")
    return p.withColumn("tokens", tokens.cast("int")).withColumn("cum", F.sum("tokens").over(w)).select("p_partkey", "side", "tokens", F.expr("(cum - 1) div 4096").alias("batch_id"))


def token_budget_sweep_part(spark, d):
    """Images at each token budget from 14 x 14 to 26 x 26: how many need scaling down."""
    p = A.table(spark, d, "part").select((14 + F.col("p_size") % 15).alias("g"))
    budgets = spark.range(14, 27).select((F.col("id") * F.col("id")).alias("budget"))
    return p.crossJoin(F.broadcast(budgets)).groupBy("budget").agg(F.count_if(F.col("g") * F.col("g") > F.col("budget")).alias("scaled"), F.sum(F.least(F.col("g") * F.col("g"), "budget")).cast("long").alias("tokens"))


_F = (curate_documents, filter_quality_labels, unsafe_lexicon, unsafe_recall, exact_dedup_documents, duration_strata_documents, duration_strata_orders, domain_balance_documents, stage_plan, stage_nesting, rollout_sample, validation_sample, rubric_documents, mode_mix_documents, mixture_cube_orders, resolution_pack_part, token_budget_sweep_part)
QUERIES = {f.__name__: f for f in _F}

B = "('0x' || substr(md5('{seed}:' || {id}), 1, 8))::bigint"
WORDS = "list_filter(string_split_regex(lower(text), '[ \\n\\t]+'), lambda w: w <> '')"
REASONS = f"""
w as (select doc_id sample_id, text, quality, {WORDS} w, string_split(text, chr(10)) l from documents left join labels using (doc_id)),
r as (select sample_id, quality, array_to_string(list_filter([
  case when len(list_distinct(l)) < 0.7 * len(l) then 'lines' end,
  case when len(string_split(text, '|')) > 5 then 'pipes' end,
  case when len(w) < 5 then 'short' end,
  case when len(list_filter(w, lambda x: regexp_matches(x, '%%%$|###$|[*][*][*]$|[$][$][$]$|&&&$'))) > 0.2 * len(w) then 'suffix' end,
  case when len(list_distinct(w)) < 0.3 * len(w) then 'types' end,
  case when trim(text) = '' or contains(text, chr(65533)) then 'void' end], lambda x: x is not null), ',') reasons from w)"""
STRATA = "select case when d <= 30 then 'to30' when d <= 60 then 'to60' when d <= 180 then 'to180' when d < 600 then 'gap' when d <= 900 then 'to900' else 'over' end stratum, count(*) n, sum(least(d, case when d <= 30 then 30 when d <= 60 then 60 when d <= 180 then 90 else 384 end))::bigint frames from ({}) group by 1"
ROLL = f"""s as (select doc_id sample_id, source domain, {B.format(seed=42, id='doc_id')} b from documents), dom as (select distinct domain from s order by 1 limit 10),
roll as (select * from (select sample_id, domain, (row_number() over (partition by domain order by b, sample_id))::int "rank" from s where domain in (from dom)) where "rank" <= 20)"""
LEX = f"""lw as (select doc_id, toxic, unnest(list_distinct({WORDS})) word, {B.format(seed=42, id='doc_id')} % 2 half from documents join labels using (doc_id) where toxic is not null),
lex as (select word, sum(toxic)::bigint toxic_texts, count(*) texts from lw where half = 0 group by 1 having sum(toxic) = count(*) and count(*) >= 5)"""
SQL = {
    "curate_documents": f"with {REASONS} select sample_id, reasons from r",
    "filter_quality_labels": f"with {REASONS} select count(*) filter (reasons <> '' and quality = 0) hit_bad, count(*) filter (reasons <> '' and quality = 1) hit_good, count(*) filter (reasons = '' and quality = 0) missed_bad, count(*) filter (reasons = '' and quality = 1) kept_good from r where quality is not null",
    "unsafe_lexicon": f"with {LEX} select word, toxic_texts, texts from lex",
    "unsafe_recall": f"with {LEX}, t as (select doc_id, toxic, bool_or(word in (select word from lex)) hit from lw where half = 1 group by 1, 2) select count(*) filter (toxic = 1 and hit) found, count(*) filter (toxic = 1 and not hit) missed, count(*) filter (toxic = 0 and hit) wrong from t",
    "exact_dedup_documents": "select sha256(text) text_sha256, min(doc_id) kept, count(*) copies from documents group by 1 having count(*) > 1",
    "duration_strata_documents": STRATA.format("select ceil(n_chars / 15.0)::bigint d from documents"),
    "duration_strata_orders": STRATA.format("select o_orderkey * 7 % 1200 d from orders"),
    "domain_balance_documents": f"""with p as (select source domain, count(*) n from documents group by 1), t as (select sum(n) total, sum(pow(n::double, 0.5)) norm from p),
      w as (select domain, n, pow(n::double, -0.5) * total / norm weight from p, t)
      select domain, n, sum(floor(weight)::bigint + ({B.format(seed=42, id='doc_id')} / 4294967296.0 < weight - floor(weight))::int)::bigint copies from documents join w on source = domain group by 1, 2""",
    "stage_plan": "with o as (select substr(o_orderpriority, 1, 1)::int stage, 'pool_' || (o_custkey % 4) component, count(*) target_rows from orders group by 1, 2) select *, round(target_rows / sum(target_rows) over (partition by stage), 6) weight from o",
    "stage_nesting": f"with b as (select {B.format(seed=42, id='doc_id')} b from documents) select count(*) filter (b < {int(0.74 * 2**32)}) large, count(*) filter (b < {int(0.37 * 2**32)}) small, 0::bigint lost from b",
    "rollout_sample": f'with {ROLL} select sample_id, domain, "rank" from roll',
    "validation_sample": f"with {ROLL} select sample_id, domain from s where sample_id not in (select sample_id from roll) order by {B.format(seed=7, id='sample_id')}, sample_id limit 200",
    "rubric_documents": f"""with w as (select source domain, text, {WORDS} w from documents), g as (select *, list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2]) g from w)
      select domain, round(avg(case when len(g) > 0 then 1 - len(list_distinct(g)) / len(g)::double else 0 end), 6) redundancy, sum(len(w))::bigint n_words, sum(len(list_filter(string_split_regex(text, '[.!?]'), lambda x: trim(x) <> '')))::bigint n_sentences from g group by 1""",
    "mode_mix_documents": f"select case when b < 50 then 'codec' when b < 90 then 'chunk' else 'collage' end \"mode\", count(*) n from (select {B.format(seed=42, id='doc_id')} % 100 b from documents) group by 1",
    "mixture_cube_orders": "select r_name, c_mktsegment, count(*) n, sum(round(o_totalprice * 100)::bigint)::bigint cents, grouping(r_name, c_mktsegment)::bigint \"level\" from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by cube (r_name, c_mktsegment)",
    "resolution_pack_part": "select p_partkey, side, ((side // 16) * (side // 16))::int tokens, ((sum((side // 16) * (side // 16)) over (partition by side order by p_partkey) - 1) // 4096)::bigint batch_id from (select p_partkey, (224 + 16 * (p_size % 15))::int side from part)",
    "token_budget_sweep_part": "select (b * b)::bigint budget, count(*) filter (g * g > b * b) scaled, sum(least(g * g, b * b))::bigint tokens from (select 14 + p_size % 15 g from part), range(14, 27) t(b) group by b",
}
