"""Short events, attentive pooling, supplementation, Python functions, SQL access, more sources and restarts."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from ..functions import measures, pyfuncs
from ..operators import balance, cluster, curate, select
from ..shipping import ship_package
from ..sources import adapters as A
from ..streaming import flows
from . import gates, tokens


def _folder(spark, what):
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.conf.get("spark.sql.warehouse.dir")
    return f"{base.rstrip('/')}/{what}-{uuid.uuid4().hex}"


def event_recall_short(spark, d):
    """Short events hit by the budgeted tiles and by uniform frames of as many tokens, N = 4 ... 64 frames."""
    tiles = A.GRID[0] * A.GRID[1]
    ranked = select.topk_budget(tokens.importance_events(spark, d), tokens.BUDGETS[-1] * tiles, tokens.GOP, A.FRAMES, A.GRID)
    short = measures.short_events(A.tile_facts_events(spark, d)).join(ranked.select(*select.KEY, "rank_in_clip"), list(select.KEY), "left")
    hits = {f"codec{n}": F.col("rank_in_clip") <= n * tiles for n in tokens.BUDGETS} | {f"uniform{n}": F.col("frame_idx").isin(select.uniform_indices(n, A.FRAMES)) for n in tokens.BUDGETS}
    recall = measures.event_recall(short, hits)
    return tokens.budget_rows(recall, ("n_events", lambda n: F.col("n_events")), *[(side, lambda n, side=side: F.col(f"{side}{n}")) for side in ("codec", "uniform")])


def _pooled(spark, d):
    """Clips of eight vectors pooled with the mean vector as query."""
    e = A.table(spark, d, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("x"))
    mean = e.select(F.posexplode("x").alias("dim", "v")).groupBy("dim").agg(F.avg("v").alias("v")).agg(F.transform(F.array_sort(F.collect_list(F.struct("dim", "v"))), lambda s: s["v"]).alias("query"))
    return cluster.attentive_pool(e.select(F.expr("vec_id div 8").alias("clip_id"), "x"), mean)


def attentive_pool_embeddings(spark, d):
    return _pooled(spark, d).select("clip_id", "dim", F.round("v", 6).alias("v"))


def attentive_probe_clips(spark, d):
    """Logistic regression on pooled clips, held-out accuracy; a clip's label is its first vector's."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.functions import array_to_vector

    x = _pooled(spark, d).groupBy("clip_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("dim", "v"))), lambda s: s["v"]).alias("x"))
    labels = A.table(spark, d, "embeddings").groupBy(F.expr("vec_id div 8").alias("clip_id")).agg(F.min_by("label", "vec_id").cast("double").alias("label"))
    clips = x.join(labels, "clip_id").select("label", array_to_vector("x").alias("features"), cluster.train_row("clip_id").alias("train"))
    model = LogisticRegression(maxIter=20, regParam=0.01).fit(clips.filter("train"))
    return model.transform(clips.filter("not train")).agg(F.count("*").alias("n"), F.count_if(F.col("label") == F.col("prediction")).alias("hits"))


def supplement_documents(spark, d):
    """Extra rows for the domains whose mean quality label is under 0.7; half of the pool counts as used."""
    s = A.samples(spark, d)
    scores = s.groupBy("domain").agg(F.avg("quality").alias("score"))
    return balance.supplement(s, scores, 0.7, 50, curate.bucket("sample_id") % 100 < 50)


def udaf_ap_grouped(spark, d):
    """Average precision per video by a grouped function over at most 256 score levels, counted before."""
    ship_package(spark)
    level = F.least(F.lit(255).cast("long"), F.expr("memory div 2000"))
    counts = A.gate_events(spark, d).groupBy("video_id", level.alias("level")).agg(F.sum("speak").alias("p"), F.count("*").alias("n"))
    return counts.groupBy("video_id").agg(pyfuncs.ap_udaf()("level", "p", "n").alias("ap")).select("video_id", F.round("ap", 6).alias("ap"))


def udtf_shingles(spark, d):
    """Five-word shingles of every text by a table function called from SQL."""
    ship_package(spark)
    spark.udtf.register("patchflow_shingles", pyfuncs.shingles_udtf())
    docs = A.table(spark, d, "documents").select("doc_id", "text")
    return spark.sql("select doc_id, count(*) as n, count(distinct shingle) as n_distinct from {docs} d, lateral patchflow_shingles(d.text, 5) group by doc_id", docs=docs)


def cogroup_selectors(spark, d):
    """The two selectors compared clip by clip in a cogrouped function."""
    ship_package(spark)
    a = tokens.tokens_events(spark, d)
    b = select.capped_by(select.code_length(tokens.importance_events(spark, d), A.FRAMES), a, tokens.GOP, A.FRAMES, A.GRID)
    key = list(select.KEY)
    both = a.select(*key).groupBy("clip_id").cogroup(b.select(*key).groupBy("clip_id"))
    return both.applyInPandas(pyfuncs.agreement, "clip_id long, used_a long, used_b long, shared long, jaccard double")


def sql_views_budget(spark, d):
    """The budget as SQL over the importance table."""
    text = "select clip_id, frame_idx, row, col, importance from (select *, row_number() over (partition by clip_id order by importance desc, frame_idx, row, col) as r from {imp}) where r <= 100"
    return spark.sql(text, imp=tokens.importance_events(spark, d))


def scan_partition_pruned(spark, d):
    """Tiles written by clip bucket; one bucket read back."""
    path = _folder(spark, "tiles")
    A.tile_facts_events(spark, d).withColumn("clip_bucket", (F.col("clip_id") % 4).cast("int")).write.partitionBy("clip_bucket").parquet(path)
    return spark.read.parquet(path).filter("clip_bucket = 1").groupBy("clip_id").agg(F.sum("n").alias("n"), F.sum("c").alias("cents"))


def source_synthetic_tiles(spark, d):
    """A feed of tiles through the budgeted selection's first step: mass of each frame, suppliers as clips."""
    tiles = A.tile_facts_lineitem(spark, d).groupBy("clip_id", "frame_idx", "row", "col").agg(F.sum("c").alias("importance"))
    return tiles.groupBy("clip_id", "frame_idx").agg(F.count("*").alias("tiles"), F.sum("importance").alias("mass"))


def st_late_drop(spark, d):
    """Rows that a watermark of a day would drop, for batches of a thousand events."""
    e = A.table(spark, d, "events").select(F.expr("event_id div 1000").alias("batch_no"), "ts")
    return flows.late_rows(e, 86400)


def st_restart(spark, d):
    """A stream to files, stopped and started again on its checkpoint: each row once."""
    at = _folder(spark, "restart")
    for _ in range(2):
        flows.to_files(flows.event_stream(spark, d).select("event_id", "user_id"), f"{at}/rows", f"{at}/state")
    return spark.read.schema("event_id long, user_id long").parquet(f"{at}/rows")


_F = (event_recall_short, attentive_pool_embeddings, attentive_probe_clips, supplement_documents, udaf_ap_grouped, udtf_shingles, cogroup_selectors, sql_views_budget, scan_partition_pruned, source_synthetic_tiles, st_late_drop, st_restart)
QUERIES = {f.__name__: f for f in _F}

_HITS = "round(count(*) filter ({cond}) / nullif(count(*), 0)::double, 6)"
_KEY = 'x.clip_id = e.clip_id and x.frame_idx = e.frame_idx and x."row" = e."row" and x.col = e.col'
SQL = {
    "event_recall_short": f"""with {tokens.RANKED_EVENTS},
      busy as (select distinct clip_id, frame_idx, "row", col from facts),
      near as (select *, lag(frame_idx) over w b, lead(frame_idx) over w a from busy window w as (partition by clip_id, "row", col order by frame_idx)),
      e as (select clip_id, frame_idx, "row", col from near where (b is null or frame_idx - b > 1) and (a is null or a - frame_idx > 1)),
      hit as (select e.*, coalesce(x.rank_in_clip, 1 << 30) rk from e left join ranked x on {_KEY}) """ + " union all ".join(
        f"""select {n} n, count(*) n_events, {_HITS.format(cond=f"rk <= {n * 20}")} codec, {_HITS.format(cond=f"frame_idx in (select {tokens.UNIFORM.format(n=n)} from range({n}) i(i))")} uniform from hit""" for n in tokens.BUDGETS),
    "attentive_pool_embeddings": """with e as (select vec_id, (i - 1)::int dim, embedding[i]::double v from embeddings, range(1, 65) t(i)),
      q as (select dim, avg(v) q from e group by 1), w as (select vec_id, exp(sum(v * q) / 0.1) w from e join q using (dim) group by 1)
      select vec_id // 8 clip_id, dim, round(sum(w * v) / sum(w), 6) v from e join w using (vec_id) group by 1, 2""",
    "supplement_documents": """with s as (select doc_id sample_id, source "domain", quality, ('0x' || substr(md5('42:' || doc_id), 1, 8))::bigint b, ('0x' || substr(md5('13:' || doc_id), 1, 8))::bigint k from documents left join labels using (doc_id)),
      weak as (select "domain" from s group by 1 having avg(quality) < 0.7)
      select sample_id, "domain" from (select *, row_number() over (partition by "domain" order by k, sample_id) r from s where b % 100 >= 50 and "domain" in (from weak)) where r <= 50""",
    "udaf_ap_grouped": f"""with {gates.GE}, lv as (select video_id, least(255, memory // 2000) l, sum(speak) p, count(*) n from g group by 1, 2),
      c as (select *, sum(p) over w cp, sum(n) over w cn, sum(p) over (partition by video_id) tp from lv window w as (partition by video_id order by l desc))
      select video_id, round(sum(p / nullif(tp, 0)::double * (cp / cn::double)), 6) ap from c group by 1""",
    "udtf_shingles": r"""with w as (select doc_id, regexp_extract_all(text, '[^ \n\t]+') w from documents),
      s as (select doc_id, list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) s from w)
      select doc_id, sum(len(s))::bigint n, len(list_distinct(flatten(list(s))))::bigint n_distinct from s group by 1 having sum(len(s)) > 0""",
    "cogroup_selectors": tokens.SQL["cross_selector_events"],
    "sql_views_budget": f"""with {tokens.IMP_EVENTS} select clip_id, frame_idx, "row", col, importance from (select *, row_number() over (partition by clip_id order by importance desc, frame_idx, "row", col) r from imp) where r <= 100""",
    "scan_partition_pruned": "select user_id % 16 clip_id, count(*) n, sum(round(value * 100)::bigint)::bigint cents from events where user_id % 4 = 1 group by 1",
    "source_synthetic_tiles": """select l_suppkey clip_id, ((year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1)::int frame_idx, count(distinct (l_partkey % 4, l_linenumber)) tiles,
      sum(round(l_extendedprice::double * 100)::bigint)::bigint mass from lineitem group by 1, 2""",
    "st_late_drop": """with b as (select event_id // 1000 batch_no, ts from events), seen as (select batch_no, max(ts) m from b group by 1),
      mark as (select batch_no, max(m) over (order by batch_no rows between unbounded preceding and 1 preceding) mark from seen)
      select batch_no, count(*) filter (ts < mark - interval 1 day) late, count(*) n from b join mark using (batch_no) group by 1""",
    "st_restart": "select event_id, user_id from events",
}
