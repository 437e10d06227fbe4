"""Cluster and probe workloads on the embeddings."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import cluster
from ..sources import adapters as A


def _features(spark, d, dims=None):
    return A.table(spark, d, "embeddings").select(F.col("vec_id").alias("sample_id"), cluster.scaled(None, "embedding", dims).alias("q"), "label")


def _centers(spark, d):
    """First vector of each label."""
    e = A.table(spark, d, "embeddings").groupBy("label").agg(F.min_by("embedding", "vec_id").alias("embedding"))
    return e.select(F.col("label").alias("center_id"), cluster.scaled(None, "embedding").alias("p"))


def cluster_assign_embeddings(spark, d):
    return cluster.assign(_features(spark, d).select("sample_id", "q"), _centers(spark, d)).select("sample_id", "center_id", "d2")


def cluster_assign_two_embeddings(spark, d):
    return cluster.assign(_features(spark, d).select("sample_id", "q"), _centers(spark, d), 2).select("sample_id", "center_id", "d2", "rank")


def lloyd_step_embeddings(spark, d):
    return cluster.lloyd_step(_features(spark, d).select("sample_id", "q"), _centers(spark, d))


def discrimination_loss_embeddings(spark, d):
    e = A.table(spark, d, "embeddings")
    x = F.transform("embedding", lambda v: v.cast("double"))
    centers = e.groupBy("label").agg(F.min_by("embedding", "vec_id").alias("embedding")).select(F.col("label").alias("center_id"), x.alias("c"))
    own = e.select(F.col("vec_id").alias("sample_id"), F.col("label").alias("center_id"))
    return cluster.discrimination_loss(e.select(F.col("vec_id").alias("sample_id"), x.alias("x")), own, centers)


def centroid_probe_embeddings(spark, d):
    out = None
    for dims in (16, 32, 64):
        f = _features(spark, d, dims).withColumn("train", cluster.train_row("sample_id"))
        part = cluster.centroid_probe(f).select(F.lit(dims).alias("dims"), "n", "hits")
        out = part if out is None else out.union(part)
    return out


def linear_probe_embeddings(spark, d):
    """Logistic regression on frozen vectors, held-out accuracy."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.functions import array_to_vector

    e = A.table(spark, d, "embeddings").select("vec_id", F.col("label").cast("double").alias("label"), array_to_vector("embedding").alias("features"), cluster.train_row("vec_id").alias("train"))
    model = LogisticRegression(maxIter=20, regParam=0.01).fit(e.filter("train"))
    return model.transform(e.filter("not train")).agg(F.count("*").alias("n"), F.count_if(F.col("label") == F.col("prediction")).alias("hits"))


def kmeans_fit_embeddings(spark, d):
    """Clusters over the union of image and video vectors."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    e = A.table(spark, d, "embeddings").select("vec_id", array_to_vector("embedding").alias("features"))
    return KMeans(k=10, seed=42, maxIter=10).fit(e).transform(e).groupBy("prediction").agg(F.count("*").alias("n"))


QUERIES = {f.__name__: f for f in (cluster_assign_embeddings, cluster_assign_two_embeddings, lloyd_step_embeddings, discrimination_loss_embeddings, centroid_probe_embeddings, linear_probe_embeddings, kmeans_fit_embeddings)}
Q = "list_transform(embedding{cut}, lambda x: round(x::double * 1000000)::bigint)"
DIST = """
f as (select vec_id sample_id, label, {q} q from embeddings),
cen as (select label center_id, arg_min({q}, vec_id) p from embeddings group by 1),
dist as (select sample_id, center_id, list_sum(list_transform(range(1, len(q) + 1), lambda i: (q[i] - p[i]) * (q[i] - p[i])))::bigint d2 from f, cen),
near as (select *, (row_number() over (partition by sample_id order by d2, center_id))::int "rank" from dist)""".replace("{q}", Q.format(cut=""))
SQL = {
    "cluster_assign_embeddings": f'with {DIST} select sample_id, center_id, d2 from near where "rank" = 1',
    "cluster_assign_two_embeddings": f'with {DIST} select sample_id, center_id, d2, "rank" from near where "rank" <= 2',
    "lloyd_step_embeddings": f'with {DIST} select center_id, (i - 1)::int dim, sum(q[i])::bigint total, count(*) n from f join near using (sample_id), range(1, 65) t(i) where "rank" = 1 group by 1, 2',
    "discrimination_loss_embeddings": """with c as (select label center_id, arg_min(embedding, vec_id) c from embeddings group by 1),
      p as (select vec_id, label = center_id own, exp(list_sum(list_transform(range(1, 65), lambda i: embedding[i]::double * c[i]::double)) / 0.1) e from embeddings, c
        where label = center_id or ('0x' || substr(md5('42:' || vec_id || ':' || center_id), 1, 8))::bigint < 429496729),
      l as (select vec_id, ln(sum(e)) - ln(sum(e) filter (own)) loss from p group by 1) select count(*) n, round(avg(loss), 6) loss from l""",
    "centroid_probe_embeddings": " union all ".join(
        f"""select {n} dims, count(*) n, count(*) filter (label = guess) hits from (with f as (select vec_id, label, {Q.format(cut=f'[1:{n}]')} q, ('0x' || substr(md5('42:' || vec_id), 1, 8))::bigint % 100 < 80 train from embeddings),
        me as (select label l, i, round(avg(q[i]))::bigint v from f, range(1, {n + 1}) t(i) where train group by 1, 2),
        dd as (select vec_id, label, l, sum((q[i] - v) * (q[i] - v)) d2 from f, me where not train group by 1, 2, 3)
        select vec_id, label, arg_min(l, d2) guess from dd group by 1, 2)""" for n in (16, 32, 64)),
}
