"""Near-duplicate workloads: exact pairs, MinHash components, copies saved."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import neardup
from ..sources import adapters as A
from .curation import WORDS


def near_dup_pairs_documents(spark, d):
    """All pairs of different texts at 0.8 or more, exactly."""
    return neardup.pairs_exact(neardup.cut(neardup.classes(A.samples(spark, d)))).select("a", "b", F.round("jaccard", 6).alias("jaccard"))


def near_dup_components_documents(spark, d):
    return neardup.near_duplicates(A.samples(spark, d), exact=True)


def near_dup_kept(spark, d):
    """Texts before and after one of each component is kept, by language."""
    s = A.samples(spark, d)
    c = neardup.near_duplicates(s, exact=True).join(s.select("sample_id", "lang"), "sample_id")
    return c.groupBy("lang").agg(F.count("*").alias("n"), F.count_if(F.col("sample_id") == F.col("component_id")).alias("kept"))


QUERIES = {f.__name__: f for f in (near_dup_pairs_documents, near_dup_components_documents, near_dup_kept)}
_PAIRS = f"""t as (select doc_id, lang, {WORDS} w from documents),
  c as (select min(doc_id) rep, w from t where len(w) > 0 group by w),
  s as (select rep, list_distinct(case when len(w) >= 5 then list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) else [array_to_string(w, ' ')] end) s from c),
  e as (select rep, unnest(s) g from s), n as (select rep, len(s) n from s),
  common as (select x.rep a, y.rep b, count(*) k from e x join e y on x.g = y.g and x.rep < y.rep group by 1, 2),
  p as (select a, b, k / (na.n + nb.n - k)::double jaccard from common join n na on na.rep = a join n nb on nb.rep = b where k / (na.n + nb.n - k)::double >= 0.8)"""
_COMPONENTS = f"""with recursive {_PAIRS}, both_ways as (select a, b from p union all select b, a from p),
  reach(v, r) as (select rep, rep from c union select b, r from reach join both_ways on a = v),
  comp as (select v, min(r) component_id from reach group by v), links as (select a, count(*) links from both_ways group by a),
  m as (select doc_id sample_id, lang, coalesce(rep, doc_id) class_id from t left join c using (w))"""
SQL = {
    "near_dup_pairs_documents": f"with {_PAIRS} select a, b, round(jaccard, 6) jaccard from p",
    "near_dup_components_documents": f"{_COMPONENTS} select sample_id, class_id, coalesce(links, 0)::bigint links, coalesce(component_id, class_id) component_id from m left join comp on v = class_id left join links on a = class_id",
    "near_dup_kept": f"{_COMPONENTS} select lang, count(*) n, count(*) filter (sample_id = coalesce(component_id, class_id)) kept from m left join comp on v = class_id group by 1",
}
