"""Closed-loop workloads: edit log, frozen recipe over the corpus, before and after."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import curate, loop
from ..sources import adapters as A
from . import curation

#: A recipe on the way of ``recipe_loop``, of the rules that SQL can state too (no back references).
FROZEN = loop.Recipe(("no_fragments", "no_markup"), True)


def _batches(spark, d):
    s = A.samples(spark, d)
    rollout = curate.stratified(s, 100, 10)
    rest = s.join(rollout.select("sample_id"), "sample_id", "left_anti")
    return rollout, rest.orderBy(curate.bucket("sample_id", seed=7), "sample_id").limit(200)


def recipe_loop(spark, d):
    """Ten rounds over ten domains of 100 rows, verified on 200 others: the edit log."""
    _, log = loop.optimize(*_batches(spark, d))
    return spark.createDataFrame(log, "round int, dimension string, before string, candidate string, score_before double, score_after double, verdict string")


def recipe_apply_documents(spark, d):
    """The frozen recipe over every document: characters before and after."""
    s = A.samples(spark, d).select("sample_id", "text", F.length("text").cast("long").alias("chars_before"))
    return loop.apply(s, FROZEN).select("sample_id", "chars_before", F.length("text").cast("long").alias("chars_after"))


def recipe_delta_documents(spark, d):
    """Dimension means of the corpus before and after the frozen recipe, with the difference."""
    s = A.samples(spark, d).select("text")
    both = loop.score(s).withColumn("when", F.lit("before")).unionByName(loop.score(loop.apply(s, FROZEN)).withColumn("when", F.lit("after")))
    means = both.groupBy("when").agg(*[F.avg(k).alias(k) for k in loop.DIMENSIONS])
    long = means.unpivot("when", list(loop.DIMENSIONS), "dimension", "value")
    p = long.groupBy("dimension").pivot("when", ["before", "after"]).agg(F.first("value"))
    return p.select("dimension", F.round("before", 6).alias("before"), F.round("after", 6).alias("after"), F.round(F.col("after") - F.col("before"), 6).alias("delta"))


QUERIES = {f.__name__: f for f in (recipe_loop, recipe_apply_documents, recipe_delta_documents)}
_S = r"list_filter(list_transform(string_split_regex({t}, '[.!?]+\s*|\n'), lambda s: trim(s)), lambda s: s <> '')"
_CLEAN = "'[00:00] ' || array_to_string(list_filter(" + _S.format(t="regexp_replace(text, '[*#%$&|]{{2,}}', '', 'g')").replace("{{", "{").replace("}}", "}") + ", lambda s: len(string_split(s, ' ')) >= 4), '. ')"
_SCORE = """select {when} phase, case when len(w) > 0 and len(s) > 0 then round(least(1.0::double, 200.0::double / len(w)), 6) else 0 end brevity,
  case when len(w) > 0 and len(s) > 0 then round(len(list_filter(s, lambda x: len(string_split(x, ' ')) >= 4 and not regexp_matches(x, '[*#%$&|]{{2,}}'))) / len(s)::double, 6) else 0 end coherence,
  case when len(w) > 0 and len(s) > 0 then round(len(list_distinct(s)) / len(s)::double, 6) else 0 end novelty,
  case when len(w) > 0 and len(s) > 0 then case when regexp_matches(text, '\\[\\d\\d:\\d\\d\\]') then 1.0::double else 0.5::double end else 0 end timing
  from (select text, {words} w, {sentences} s from ({source}) x)"""


def _scored(when: str, source: str) -> str:
    return _SCORE.format(when=f"'{when}'", words=curation.WORDS, sentences=_S.format(t="text"), source=source)


SQL = {
    "recipe_apply_documents": f"select doc_id sample_id, length(text) chars_before, length({_CLEAN}) chars_after from documents",
    "recipe_delta_documents": f"""with m as (select phase, avg(brevity) brevity, avg(coherence) coherence, avg(novelty) novelty, avg(timing) timing from ({_scored("before", "select text from documents")} union all {_scored("after", f"select {_CLEAN} as text from documents")}) t group by phase),
      l as (unpivot m on brevity, coherence, novelty, timing into name dimension value value)
      select dimension, round(max(value) filter (phase = 'before'), 6) before, round(max(value) filter (phase = 'after'), 6) after, round(max(value) filter (phase = 'after') - max(value) filter (phase = 'before'), 6) delta from l group by 1""",
}
