"""Caption linting, verbatim recall, token-matched swap, diagnosis."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import captions, curate
from ..sources import adapters as A
from .curation import WORDS, B

#: Lexicons are data: words that exist in the given texts stand for openers and hedges.
OPENERS, HEDGES = ("the", "der", "les", "los"), ("thing", "pour", "nicht")

#: Frequent words of the given texts in each word list, since the texts are invented.
RULEBOOK = {"absence": ("non", "ohne"), "affect": ("muy", "sehr"), "effect": ("dans", "mit"), "hedge": HEDGES, "inference": ("que", "und"), "summary": ("and", "para")}


def caption_lint_documents(spark, d):
    return captions.lint(A.samples(spark, d), OPENERS, HEDGES)


def caption_lint_families(spark, d):
    """Violations of all eleven families, one row per text and family."""
    v = captions.lint_rulebook(A.samples(spark, d), RULEBOOK, OPENERS)
    return v.select("sample_id", F.explode("violations").alias("family", "hits"))


def lint_totals(spark, d):
    c = caption_lint_documents(spark, d)
    return c.agg(*[F.count_if(x).alias(x) for x in ("opener", "hedge", "markup", "paragraphs", "short_run")])


def ocr_recall_pages(spark, d):
    return captions.verbatim_recall(A.table(spark, d, "pages"))


def equal_token_swap(spark, d):
    """Documents that take the place of all conversations at the same number of tokens."""
    tokens = F.size(F.split("text", " ")).cast("long")
    total = A.table(spark, d, "conversations").agg(F.sum(tokens).alias("total"))
    return captions.equal_tokens(A.table(spark, d, "documents").select(F.col("doc_id").alias("sample_id"), tokens.alias("tokens")), total)


def diagnosis(spark, d):
    """Weakest of three shares by domain: few repeats, distinct words, short of markup."""
    r = curate.rubric(A.samples(spark, d)).groupBy("domain").agg(F.round(1 - F.avg("redundancy"), 6).alias("novelty"), F.round(F.avg(F.least(F.lit(1.0), F.col("n_sentences") / F.greatest(F.lit(1), F.col("n_words")))), 6).alias("sentences"))
    long = r.select("domain", F.explode(F.array(*[F.struct(F.lit(k).alias("dimension"), F.col(k).alias("value")) for k in ("novelty", "sentences")])).alias("x")).select("domain", "x.*")
    return captions.weak_spots(long)


QUERIES = {f.__name__: f for f in (caption_lint_documents, caption_lint_families, lint_totals, ocr_recall_pages, equal_token_swap, diagnosis)}
_LINT = f"""select doc_id sample_id, w[1] in ({', '.join(f"'{o}'" for o in OPENERS)}) opener, len(list_intersect(w, [{', '.join(f"'{h}'" for h in HEDGES)}])) > 0 hedge, contains(text, '**') or contains(text, '###') markup, contains(text, chr(10)) paragraphs,
  contains(array_to_string(list_transform(list_filter(string_split_regex(text, '[.!?]'), lambda s: trim(s) <> ''), lambda s: case when len(string_split(trim(s), ' ')) < 4 then '1' else '0' end), ''), '111') short_run
  from (select *, string_split_regex(lower(text), '[ \\n\\t.,!?]+') w from documents)"""
_HITS = {k: "len(list_filter(w, lambda x: x in (" + ", ".join(f"'{x}'" for x in v) + ")))" for k, v in RULEBOOK.items()} | {
    "opener": "(w[1] in (" + ", ".join(f"'{o}'" for o in OPENERS) + "))::int",
    "restated": "len(s) - len(list_distinct(s))",
    "short_run": "len(regexp_extract_all(array_to_string(list_transform(s, lambda x: case when len(string_split(x, ' ')) < 4 then '1' else '0' end), ''), '1{3,}'))",
    "markup": r"len(list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '\*\*|^#{1,6} |^[-*] ')))",
    "paragraphs": r"len(list_filter(string_split_regex(text, '\n+'), lambda x: trim(x) <> '')) - 1",
}
SQL = {
    "caption_lint_documents": _LINT,
    "caption_lint_families": r"with t as (select doc_id sample_id, text, list_filter(string_split_regex(lower(text), '[ \n\t.,!?]+'), lambda x: x <> '') w, list_filter(list_transform(string_split_regex(text, '[.!?]'), lambda x: regexp_replace(x, '^\s+|\s+$', '', 'g')), lambda x: x <> '') s from documents) "
    + "select * from (" + " union all ".join(f"select sample_id, '{k}' family, ({v})::bigint hits from t" for k, v in _HITS.items()) + ") where hits > 0",
    "lint_totals": f"select {', '.join(f'count(*) filter ({x}) {x}' for x in ('opener', 'hedge', 'markup', 'paragraphs', 'short_run'))} from ({_LINT})",
    "ocr_recall_pages": r"""with p as (select page_id, regexp_replace(regexp_replace(html, '(?s)<script.*?</script>|<style.*?</style>|<!--.*?-->|<nav.*?</nav>', ' ', 'g'), '<[^>]*>', ' ', 'g') v, regexp_extract(html, '<title>([^<]*)</title>', 1) t from pages),
      v as (select page_id, w, count(*) v from (select page_id, unnest(string_split_regex(v, '[ \n\t]+')) w from p) where w <> '' group by 1, 2), t as (select page_id, w, count(*) t from (select page_id, unnest(string_split_regex(t, '[ \n\t]+')) w from p) where w <> '' group by 1, 2)
      select page_id, sum(v)::bigint n, sum(least(v, coalesce(t, 0)))::bigint met from v left join t using (page_id, w) group by 1""",
    "equal_token_swap": f"""with p as (select doc_id sample_id, len(string_split(text, ' ')) tokens, {B.format(seed=42, id='doc_id')} b from documents), c as (select *, sum(tokens) over (order by b, sample_id) cum from p)
      select sample_id, tokens::bigint tokens from c where cum <= (select sum(len(string_split(text, ' '))) from conversations)""",
    "diagnosis": f"""with w as (select source domain, {WORDS} w, len(list_filter(string_split_regex(text, '[.!?]'), lambda x: trim(x) <> '')) s from documents), g as (select *, list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2]) g from w),
      r as (select domain, round(1 - avg(case when len(g) > 0 then 1 - len(list_distinct(g)) / len(g)::double else 0 end), 6) novelty, round(avg(least(1.0::double, s / greatest(1, len(w))::double)), 6) sentences from g group by 1)
      select domain, case when novelty <= sentences then 'novelty' else 'sentences' end dimension, least(novelty, sentences) value from r""",
}
