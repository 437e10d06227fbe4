"""Surrounding operators, one query each: scans, joins, aggregates, windows, sets, functions, UDFs.

Most are plain SQL over temporary views, which Spark and the oracle run alike; where the two
dialects differ the oracle has its own text.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..shared import scratch_path
from ..shipping import ship_package
from ..sources import adapters as A
from . import tokens

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
#: name -> SQL of both engines
SHARED = {
    "scan_projection_pruned": "select l_orderkey, l_partkey, l_quantity from lineitem where l_quantity >= 45 and l_returnflag = 'R'",
    "cents_and_flags": "select l_orderkey, l_linenumber, l_partkey, cast(round(l_extendedprice * 100) as bigint) as cents, case when l_discount > 0.05 then 1 else 0 end as discounted from lineitem",
    "filter_band_and_in": "select o_orderkey, o_orderpriority from orders where o_totalprice between 50000 and 150000 and o_orderstatus in ('F', 'O') and o_orderpriority like '1%'",
    "join_broadcast_dims": "select c_custkey, n_name, r_name from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey",
    "join_sortmerge_facts": "select /*+ merge(orders) */ o_orderpriority, count(*) as n, cast(sum(cast(round(l_extendedprice * 100) as bigint)) as bigint) as cents from lineitem join orders on l_orderkey = o_orderkey group by o_orderpriority",
    "join_shuffle_hash": "select /*+ shuffle_hash(customer) */ c_mktsegment, count(*) as n from orders join customer on o_custkey = c_custkey group by c_mktsegment",
    "join_left_outer_labels": "select d.doc_id, coalesce(quality, -1) as quality, coalesce(toxic, -1) as toxic from documents d left join labels l on d.doc_id = l.doc_id",
    "join_semi_kept": "select doc_id, lang from documents where exists (select 1 from labels where labels.doc_id = documents.doc_id and quality = 1)",
    "join_anti_holdout": "select doc_id, lang from documents where not exists (select 1 from labels where labels.doc_id = documents.doc_id)",
    "join_interval_tolerance": "select a.event_id as a, b.event_id as b from events a join events b on a.user_id = b.user_id and a.event_id < b.event_id and b.event_id - a.event_id <= 60",
    "agg_hash_bits": "select user_id % 16 as clip_id, count(*) as n, cast(sum(cast(round(value * 100) as bigint)) as bigint) as cents from events group by user_id % 16",
    "agg_distinct_clips": "select event_type, count(distinct user_id) as users from events group by event_type",
    "agg_conditional": "select user_id % 16 as clip_id, count(*) filter (where event_type = 'purchase') as purchases, count(*) filter (where value > 50) as large from events group by user_id % 16",
    "agg_rollup_domain": "select lang, source, count(*) as n, cast(sum(n_chars) as bigint) as chars from documents group by rollup (lang, source)",
    "agg_grouping_sets": "select lang, source, count(*) as n from documents group by grouping sets ((lang), (source), ())",
    "agg_two_level_macro": "select round(avg(share), 6) as macro from (select user_id % 16 as clip, avg(case when event_type = 'purchase' then 1.0E0 else 0.0E0 end) as share from events group by user_id % 16) t",
    "win_rank_ties": "select o_orderkey, cast(rank() over (partition by o_orderpriority order by o_orderdate) as int) as rk from orders",
    "win_dense_rank_best": "select p_partkey, cast(dense_rank() over (partition by p_brand order by p_size desc) as int) as rk from part",
    "win_ntile": "select o_orderkey, cast(ntile(10) over (partition by o_orderstatus order by o_totalprice, o_orderkey) as int) as tile from orders",
    "win_percent_rank": "select p_partkey, round(percent_rank() over (partition by p_type order by p_retailprice), 6) as pr from part",
    "win_lag_delta": "select event_id, event_id - lag(event_id) over (partition by user_id order by event_id) as gap from events",
    "win_lead_gap": "select event_id, lead(event_id) over (partition by user_id order by event_id) as next_id from events",
    "win_first_last": "select event_id, first_value(event_id) over (partition by user_id order by event_id rows between unbounded preceding and unbounded following) as first_id, last_value(event_id) over (partition by user_id order by event_id rows between unbounded preceding and unbounded following) as last_id from events",
    "win_running_sum_budget": "select conv_id, turn, cast(sum(length(text)) over (partition by conv_id order by turn rows between unbounded preceding and current row) as bigint) as chars from conversations",
    "win_rows_recent_n": "select conv_id, turn, cast(sum(length(text)) over (partition by conv_id order by turn rows between 3 preceding and current row) as bigint) as chars from conversations",
    "win_range_recent": "select event_id, count(*) over (partition by user_id order by event_id range between 600 preceding and current row) as recent from events",
    "sort_global_topk": "select l_orderkey, l_linenumber, l_partkey, l_extendedprice from lineitem order by l_extendedprice desc, l_orderkey, l_linenumber, l_partkey, l_suppkey, l_quantity limit 100",
    "topk_per_group": "select l_suppkey, l_orderkey, l_partkey from (select *, row_number() over (partition by l_suppkey order by l_extendedprice desc, l_orderkey, l_linenumber, l_partkey, l_quantity) as r from lineitem) t where r <= 3",
    "agg_cube_domain_duration": "select lang, source, count(*) as n, cast(sum(n_chars) as bigint) as chars, cast(grouping(lang) as int) as all_langs, cast(grouping(source) as int) as all_sources from documents group by cube (lang, source)",
    "join_theta_pareto": "select a.p_partkey from (select p_partkey, p_size, p_retailprice from part where p_size <= 3) a where not exists (select 1 from (select p_size, max(p_retailprice) as best from part group by p_size) b where b.p_size <= a.p_size and b.best > a.p_retailprice)",
    "join_theta_pareto_all_sizes": "select a.p_partkey from part a where not exists (select 1 from (select p_size, max(p_retailprice) as best from part group by p_size) b where b.p_size <= a.p_size and b.best > a.p_retailprice)",
    "join_asof_query": "select q_id, turn from (select event_id as q_id, is_query, max(case when is_query = 0 then event_id end) over (partition by clip order by event_id rows between unbounded preceding and current row) as turn from (select event_id, user_id % 16 as clip, case when event_type = 'signup' then 1 else 0 end as is_query from events) u) t where is_query = 1",
    "win_row_number_topk": "select clip, event_id from (select user_id % 16 as clip, event_id, row_number() over (partition by user_id % 16 order by value desc, event_id) as r from events) t where r <= 20",
    "set_union_byname": "select event_id as id, 'event' as kind from events union all select doc_id as id, 'text' as kind from documents",
    "set_intersect_selectors": "select user_id from events where event_type = 'purchase' intersect select user_id from events where event_type = 'click'",
    "limit_offset": "select c_custkey, c_acctbal from customer order by c_acctbal desc, c_custkey limit 20 offset 40",
    "set_union_distinct": "select lang from documents union select source from documents",
    "set_intersect": "select doc_id from documents intersect select doc_id from labels",
    "set_except_holdout": "select doc_id from documents except select doc_id from labels",
    "str_normalize": "select doc_id, cast(length(trim(replace(text, '  ', ' '))) as bigint) as n, upper(lang) as lang from documents",
    "str_edit_distance": "select p_partkey, cast(levenshtein(p_brand, p_type) as bigint) as d from part",
    "str_hash_key": "select doc_id, md5(text) as h from documents",
    "math_log2_bits": "select p_partkey, round(log2(p_size + 1.0E0), 6) as bits, round(sqrt(p_retailprice), 6) as root from part",
    "math_sigmoid": "select c_custkey, round(1 / (1 + exp(-c_acctbal / 1000.0E0)), 6) as p from customer",
    "math_iou": "select a.p_partkey as a, b.p_partkey as b, greatest(0, least(a.p_size, b.p_size) - abs(a.p_size - b.p_size)) as overlap from part a join part b on a.p_partkey + 1 = b.p_partkey",
}
#: name -> (Spark SQL, oracle SQL)
PAIRED = {
    "agg_min_by_dimension": ("select lang, min_by(doc_id, struct(n_chars, doc_id)) as shortest from documents group by lang", "select lang, arg_min(doc_id, (n_chars, doc_id)) shortest from documents group by 1"),
    "str_regex_count": ("select doc_id, cast(regexp_count(text, '[0-9]+') as bigint) as numbers from documents", "select doc_id, len(regexp_extract_all(text, '[0-9]+'))::bigint numbers from documents"),
    "date_epoch": ("select event_id, unix_timestamp(cast(ts as timestamp)) as t_s from events", "select event_id, floor(epoch(ts))::bigint t_s from events"),
    "arr_zip_distance": ("select vec_id, round(aggregate(zip_with(slice(embedding, 1, 32), slice(embedding, 33, 32), (a, b) -> (cast(a as double) - b) * (cast(a as double) - b)), 0D, (s, x) -> s + x), 5) as d2 from embeddings", "select vec_id, round(list_sum(list_transform(range(1, 33), lambda i: (embedding[i]::double - embedding[i + 32]) * (embedding[i]::double - embedding[i + 32]))), 5) d2 from embeddings"),
    "json_to_row": ("select event_id, to_json(named_struct('user_id', user_id, 'event_type', event_type)) as j from events", "select event_id, '{\"user_id\":' || user_id || ',\"event_type\":\"' || event_type || '\"}' j from events"),
    "map_rubric_get": ("select doc_id, map('chars', n_chars, 'bytes', cast(octet_length(text) as bigint))['bytes'] as bytes from documents", "select doc_id, strlen(text)::bigint bytes from documents"),
    "lateral_candidates": ("select c.conv_id, t.t_s from (select conv_id, max(turn) as last from conversations group by conv_id) c, lateral (select explode(sequence(0, c.last)) as t_s) t", "select conv_id, unnest(range(0, max(turn) + 1)) t_s from conversations group by conv_id"),
    "agg_max_by_segment": ("select c_mktsegment, max_by(c_custkey, struct(c_acctbal, -c_custkey)) as best from customer group by c_mktsegment", "select c_mktsegment, arg_max(c_custkey, (c_acctbal, -c_custkey)) best from customer group by 1"),
    "agg_percentile_exact": ("select event_type, round(percentile(value, 0.9), 6) as p90 from events group by event_type", "select event_type, round(quantile_cont(value, 0.9), 6) p90 from events group by 1"),
    "agg_sort_based": ("select conv_id, array_join(transform(array_sort(collect_list(struct(turn, role))), x -> x.role), ',') as roles from conversations group by conv_id", "select conv_id, string_agg(role, ',' order by turn) roles from conversations group by 1"),
    "agg_pivot": ("select lang, coalesce(s1, 0L) as s1, coalesce(s2, 0L) as s2 from (select lang, source from documents where source in ('src1', 'src2')) pivot (count(*) for source in ('src1' as s1, 'src2' as s2))", "select lang, count(*) filter (source = 'src1') s1, count(*) filter (source = 'src2') s2 from documents where source in ('src1', 'src2') group by 1"),
    "agg_unpivot": ("select * from (select p_partkey, p_size as size, cast(p_retailprice as int) as price from part) unpivot (v for k in (size, price))", "select p_partkey, 'size' k, p_size v from part union all select p_partkey, 'price', trunc(p_retailprice)::int from part"),
    "str_tokens": ("select doc_id, size(split(text, ' ')) as n, size(array_distinct(split(lower(text), ' '))) as kinds from documents", "select doc_id, len(string_split(text, ' '))::int n, len(list_distinct(string_split(lower(text), ' ')))::int kinds from documents"),
    "str_sentences": ("select doc_id, cast(regexp_count(text, '[.!?]') as bigint) as n from documents", "select doc_id, len(regexp_extract_all(text, '[.!?]')) n from documents"),
    "date_frame_bins": ("select event_id, cast(floor((unix_timestamp(cast(ts as timestamp)) - 1704067200) / 40500) as int) as frame from events", "select event_id, floor((epoch(ts) - 1704067200) / 40500)::int frame from events"),
    "date_month_index": ("select l_orderkey, l_linenumber, (year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1 as m from lineitem", "select l_orderkey, l_linenumber, ((year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1)::int m from lineitem"),
    "date_clock_overlay": ("select event_id, format_string('%02d:%02d', cast(event_id div 60 as int), cast(event_id % 60 as int)) as clock from events", "select event_id, printf('%02d:%02d', event_id // 60, event_id % 60) clock from events"),
    "arr_explode_pixels": ("select vec_id, cast(pos as int) as i, cast(round(cast(col as double) * 1000) as int) as v from embeddings lateral view posexplode(embedding) e as pos, col", "select vec_id, (i - 1)::int i, round(embedding[i]::double * 1000)::int v from embeddings, range(1, 65) t(i)"),
    "arr_dot": ("select vec_id, round(aggregate(transform(embedding, x -> cast(x as double) * cast(x as double)), 0D, (s, x) -> s + x), 6) as norm from embeddings", "select vec_id, round(list_sum(list_transform(embedding, lambda x: x::double * x::double)), 6) norm from embeddings"),
    "arr_slice_norm": ("select vec_id, round(aggregate(transform(slice(embedding, 1, 16), x -> abs(cast(x as double))), 0D, (s, x) -> s + x), 6) as l1 from embeddings", "select vec_id, round(list_sum(list_transform(embedding[1:16], lambda x: abs(x::double))), 6) l1 from embeddings"),
    "arr_sequence": ("select p_partkey, explode(sequence(1, p_size % 5 + 1)) as i from part", "select p_partkey, unnest(range(1, p_size % 5 + 2))::int i from part"),
    "json_props": ("select event_id, from_json(props, 'k int').k as k, get_json_object(props, '$.k') as s from events", "select event_id, (props->>'$.k')::int k, props->>'$.k' s from events"),
    "map_from_domains": ("select lang, element_at(m, 'src1') as n from (select lang, map_from_entries(collect_list(struct(source, n))) as m from (select lang, source, count(*) as n from documents group by lang, source) group by lang)", "select lang, max(n) filter (source = 'src1') n from (select lang, source, count(*) n from documents group by 1, 2) group by 1"),
    "sliding_counts": ("select event_type, unix_timestamp(w.start) as s, count(*) as n from (select event_type, window(cast(ts as timestamp), '2 days', '1 day') as w from events) group by event_type, w.start", "select event_type, (e // 86400 - d) * 86400 s, count(*) n from (select event_type, floor(epoch(ts))::bigint e from events), range(2) t(d) group by 1, 2"),
    "session_users": ("select user_id, unix_timestamp(w.start) as s, count(*) as n from (select user_id, session_window(cast(ts as timestamp), '6 hours') as w from events) group by user_id, w", "with g as (select user_id, ts, case when ts - lag(ts) over w < interval 6 hours then 0 else 1 end b from events window w as (partition by user_id order by ts, event_id)), r as (select *, sum(b) over (partition by user_id order by ts rows unbounded preceding) k from (select * from g order by user_id, ts)) select user_id, floor(epoch(min(ts)))::bigint s, count(*) n from r group by user_id, k"),
}


def _views(spark, d) -> None:
    for t in TABLES:
        A.table(spark, d, t).createOrReplaceTempView(t)


def _sql(text):
    def query(spark, d):
        _views(spark, d)
        return spark.sql(text)

    return query


def join_full_selectors(spark, d):
    """Tiles of two selectors side by side."""
    a = tokens.tokens_events(spark, d).select("clip_id", "frame_idx", "row", "col", F.col("rank_in_clip").alias("a"))
    b = tokens.chunkwise_events(spark, d).withColumn("b", F.lit(1))
    return a.join(b, ["clip_id", "frame_idx", "row", "col"], "full").groupBy("clip_id").agg(F.count("a").alias("a"), F.count("b").alias("b"), F.count("*").alias("n"))


def join_cross_budgets(spark, d):
    budgets = spark.createDataFrame([(n,) for n in (4, 8, 16, 32, 64)], "n int")
    return A.table(spark, d, "events").select((F.col("user_id") % 16).alias("clip_id")).distinct().crossJoin(F.broadcast(budgets)).withColumn("tokens", F.col("n") * 20)


def join_range_segments(spark, d):
    """Caption segments and the ten-second frames inside them: buckets make the range join an equi-join."""
    t = A.timeline_conversations(spark, d)
    frames = t.groupBy("video_id").agg(F.max("end_s").alias("e")).select("video_id", F.explode(F.sequence(F.lit(0).cast("long"), F.col("e"), F.lit(10).cast("long"))).alias("t_s"))
    wide = t.select("video_id", "seg_idx", "start_s", "end_s", F.explode(F.sequence(F.expr("start_s div 60"), F.expr("end_s div 60"))).alias("b"))
    return frames.withColumn("b", F.expr("t_s div 60")).join(wide, ["video_id", "b"]).filter("t_s >= start_s and t_s < end_s").groupBy("video_id", "seg_idx").agg(F.count("*").alias("frames"))


def _roundtrip(fmt):
    def query(spark, d):
        """Writes captions in the format and returns what is read back."""
        path = scratch_path(spark, f"roundtrip-{fmt}")
        t = A.timeline_conversations(spark, d).withColumn("caption", F.md5("caption"))
        t.write.option("header", "true").format(fmt).save(path)
        return spark.read.schema(t.schema).option("header", "true").format(fmt).load(path)

    return query


def udf_rubric_pandas(spark, d) -> DataFrame:
    """A pluggable scorer as a vectorised function: share of words that start in upper case."""
    @F.pandas_udf("double")
    def score(text: pd.Series) -> pd.Series:
        return text.fillna("").map(lambda t: sum(w[:1].isupper() for w in t.split()) / max(1, len(t.split())))

    return A.table(spark, d, "documents").groupBy("source").agg(F.round(F.avg(score("text")), 6).alias("score"))


def map_in_arrow_assign(spark, d) -> DataFrame:
    """Nearest center by blocks of matrix products, the form for wide vectors and many centers."""
    e = A.table(spark, d, "embeddings").select("vec_id", "label", "embedding")
    rows = e.groupBy("label").agg(F.min_by("embedding", "vec_id").alias("c")).orderBy("label").collect()  # a row per label
    centers = [r["c"] for r in rows]

    def run(batches):
        import numpy as np
        import pyarrow as pa

        c = np.array(centers, np.float64)
        for b in batches:
            if b.num_rows:
                x = b.column(2).flatten().to_numpy().reshape(b.num_rows, -1).astype(np.float64)
                near = (c * c).sum(1) - 2 * x @ c.T
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(near.argmin(1).astype(np.int32))], ["vec_id", "center"])

    ship_package(spark)
    return e.mapInArrow(run, "vec_id long, center int")


def agg_approx(spark, d) -> DataFrame:
    return A.table(spark, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("users"), F.percentile_approx("value", 0.5).alias("median"))


_F = (join_full_selectors, join_cross_budgets, join_range_segments, udf_rubric_pandas, map_in_arrow_assign, agg_approx)
QUERIES = {n: _sql(t) for n, t in SHARED.items()} | {n: _sql(s) for n, (s, _) in PAIRED.items()} | {f.__name__: f for f in _F} | {f"roundtrip_{f}": _roundtrip(f) for f in ("parquet", "json", "csv", "orc")}
SQL = dict(SHARED) | {n: o for n, (_, o) in PAIRED.items()} | {
    "join_cross_budgets": "select clip_id, n::int n, (n * 20)::int tokens from (select distinct user_id % 16 clip_id from events), (values (4), (8), (16), (32), (64)) t(n)",
    "join_range_segments": """with c as (select *, ceil(length(text) / 15.0)::bigint cost from conversations), cc as (select *, sum(cost) over (partition by conv_id order by turn)::bigint e from c),
      tl as (select conv_id video_id, (row_number() over (partition by conv_id order by turn) - 1)::int seg_idx, e - cost start_s, e end_s from cc where role = 'assistant'),
      f as (select video_id, unnest(range(0, max(end_s) + 1, 10)) t_s from tl group by 1)
      select f.video_id, seg_idx, count(*) frames from f join tl on tl.video_id = f.video_id and t_s >= start_s and t_s < end_s group by 1, 2""",
}
_TL = """with c as (select *, ceil(length(text) / 15.0)::bigint cost from conversations), cc as (select *, sum(cost) over (partition by conv_id order by turn)::bigint e from c)
  select conv_id video_id, (row_number() over (partition by conv_id order by turn) - 1)::int seg_idx, e - cost start_s, e end_s, md5(text) caption from cc where role = 'assistant'"""
SQL |= {f"roundtrip_{f}": _TL for f in ("parquet", "json", "csv", "orc")}
SQL["join_full_selectors"] = f"""with {tokens.TOKENS_EVENTS}, u as (select clip_id, {tokens.UNIFORM.format(n=16)} frame_idx, r::int "row", c::int col from clips, range(16) i(i), range(4) r(r), range(5) c(c))
  select clip_id, count(a) a, count(b) b, count(*) n from (select clip_id, frame_idx, "row", col, rank_in_clip a from tokens) full join (select *, 1 b from u) using (clip_id, frame_idx, "row", col) group by 1"""
SQL["udf_rubric_pandas"] = r"""with w as (select source, list_filter(regexp_split_to_array(coalesce(text, ''), '\s+'), lambda x: x <> '') w from documents),
  s as (select source, len(list_filter(w, lambda x: x[1] = upper(x[1]) and x[1] <> lower(x[1])))::double / greatest(1, len(w)) v from w) select source, round(avg(v), 6) score from s group by 1"""
SQL["map_in_arrow_assign"] = """with c as (select (row_number() over (order by label) - 1)::int center, v from (select label, arg_min(embedding, vec_id) v from embeddings group by 1)),
  d as (select vec_id, center, list_sum(list_transform(range(1, len(v) + 1), lambda i: v[i]::double * v[i]::double - 2 * embedding[i]::double * v[i]::double)) k from embeddings, c)
  select vec_id, center from (select *, row_number() over (partition by vec_id order by k, center) r from d) where r = 1"""
