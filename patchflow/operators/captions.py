"""Caption checks and token-matched swaps of pools."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .curate import bucket


def lint(samples: DataFrame, openers: tuple[str, ...], hedges: tuple[str, ...], short_words: int = 4) -> DataFrame:
    """sample_id and one flag per rule family: opener, hedge, markup, paragraphs, run of short sentences."""
    lower = F.lower("text")
    words = F.split(lower, r"[ \n\t.,!?]+")
    sentences = F.filter(F.split("text", r"[.!?]", -1), lambda s: F.trim(s) != "")
    short = F.array_join(F.transform(sentences, lambda s: F.when(F.size(F.split(F.trim(s), " ")) < short_words, "1").otherwise("0")), "")
    return samples.select(
        "sample_id",
        F.element_at(words, 1).isin(*openers).alias("opener"),
        F.arrays_overlap(words, F.array(*[F.lit(h) for h in hedges])).alias("hedge"),
        (F.contains("text", F.lit("**")) | F.contains("text", F.lit("###"))).alias("markup"),
        F.contains("text", F.lit("\n")).alias("paragraphs"),
        F.contains(short, F.lit("111")).alias("short_run"),
    )


def verbatim_recall(pages: DataFrame) -> DataFrame:
    """(page_id, n, met): tokens visible on a page and those of them, as a multiset, that its title has."""
    hidden = F.regexp_replace("html", r"(?s)<script.*?</script>|<style.*?</style>|<!--.*?-->|<nav.*?</nav>", " ")
    visible = F.regexp_replace(hidden, "<[^>]*>", " ")
    title = F.regexp_extract("html", "<title>([^<]*)</title>", 1)

    def counted(text, name):
        t = pages.select("page_id", F.explode(F.split(text, r"[ \n\t]+")).alias("w")).filter("w <> ''")
        return t.groupBy("page_id", "w").agg(F.count("*").alias(name))

    both = counted(visible, "v").join(counted(title, "t"), ["page_id", "w"], "left")
    return both.groupBy("page_id").agg(F.sum("v").alias("n"), F.sum(F.least("v", F.coalesce("t", F.lit(0)))).cast("long").alias("met"))


def equal_tokens(pool: DataFrame, total: DataFrame) -> DataFrame:
    """Rows of ``pool`` (sample_id, tokens) in hash order while their tokens fit in ``total`` (one row, ``total``).

    Hash order is cut in 256 parts; sums of parts come first, so no window is longer than a part.
    """
    p = pool.withColumn("b", bucket("sample_id")).withColumn("part", F.shiftright("b", 24))
    sums = p.groupBy("part").agg(F.sum("tokens").alias("s"))
    before = sums.withColumn("before", F.sum("s").over(Window.orderBy("part")) - F.col("s")).select("part", "before")  # 256 rows
    own = F.sum("tokens").over(Window.partitionBy("part").orderBy("b", "sample_id"))
    return p.join(F.broadcast(before), "part").withColumn("cum", F.col("before") + own).crossJoin(F.broadcast(total)).filter("cum <= total").select("sample_id", "tokens")


def weak_spots(scores: DataFrame, at: str = "domain") -> DataFrame:
    """The weakest dimension of each group: scores are (group, dimension, value); of equals the first by name."""
    return scores.groupBy(at).agg(F.min_by("dimension", F.struct("value", "dimension")).alias("dimension"), F.min("value").alias("value"))


def lint_rulebook(samples: DataFrame, rulebook: dict[str, tuple[str, ...]], openers: tuple[str, ...] = (), short_words: int = 4) -> DataFrame:
    """(sample_id, violations): map of family to hits, of the families that a text breaks.

    The rulebook names word lists (absence, affect, effect, hedge, inference, summary), single words in lower case.
    Counts are whole: words of each list, sentences said again, runs of three short sentences, lines of
    markup, paragraphs past the first.  A null text breaks nothing; the rulebook is data of a few words a family.
    """
    text = F.coalesce("text", F.lit(""))
    w = F.filter(F.split(F.lower(text), r"[ \n\t.,!?]+"), lambda x: x != "")
    s = F.filter(F.transform(F.split(text, r"[.!?]", -1), lambda x: F.regexp_replace(x, r"^\s+|\s+$", "")), lambda x: x != "")
    lengths = F.array_join(F.transform("_s", lambda x: F.when(F.size(F.split(x, " ")) < short_words, "1").otherwise("0")), "")

    def listed(v):
        return F.size(F.filter("_w", lambda x: x.isin(*v)))

    hits = {k: listed(v) for k, v in rulebook.items() if v}
    hits |= {
        "opener": F.element_at("_w", 1).isin(*openers).cast("int") if openers else F.lit(0),
        "restated": F.size("_s") - F.size(F.array_distinct("_s")),
        "short_run": F.size(F.regexp_extract_all(lengths, F.lit("(1{3,})"), 1)),
        "markup": F.size(F.filter(F.split(text, "\n", -1), lambda x: x.rlike(r"\*\*|^#{1,6} |^[-*] "))),
        "paragraphs": F.size(F.filter(F.split(text, r"\n+", -1), lambda x: F.trim(x) != "")) - 1,
    }
    wide = samples.withColumn("_w", F.when(F.size(w) > 0, w).otherwise(F.array(F.lit("")))).withColumn("_s", s)
    pairs = F.filter(F.array(*[F.struct(F.lit(k).alias("key"), v.cast("long").alias("value")) for k, v in sorted(hits.items())]), lambda p: p["value"] > 0)
    return wide.select("sample_id", F.map_from_entries(pairs).alias("violations"))
