"""Caption-corpus curation: filters with reason codes, exact duplicates, strata, balance, sampling."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Rule thresholds (own choices, parameters of ``reasons``).
MIN_WORDS, MIN_TYPES, MIN_LINES, MAX_PIPES, MAX_SUFFIX = 5, 0.3, 0.7, 5, 0.2


def bucket(*parts, seed: int = 42) -> Column:
    """A 32-bit number from md5: the sampling key, the same on every engine and partitioning."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(seed), *parts)), 1, 8), 16, 10).cast("long")


def words(text: Column) -> Column:
    return F.filter(F.split(F.lower(text), r"[ \n\t]+"), lambda w: w != "")


def reasons(samples: DataFrame, lexicon: tuple[str, ...] = ()) -> DataFrame:
    """sample_id and the codes of the rules that a text breaks, in alphabetical order, comma-joined."""
    w, n = F.col("_w"), F.size("_w")
    lines = F.split("text", "\n", -1)
    rules = {
        "lines": F.size(F.array_distinct(lines)) < MIN_LINES * F.size(lines),
        "pipes": F.size(F.split("text", r"\|", -1)) > MAX_PIPES,
        "short": n < MIN_WORDS,
        "suffix": F.size(F.filter(w, lambda x: x.rlike(r"[%][%][%]$|[#][#][#]$|[*][*][*]$|[$][$][$]$|[&][&][&]$"))) > MAX_SUFFIX * n,
        "types": F.size(F.array_distinct(w)) < MIN_TYPES * n,
        "unsafe": F.arrays_overlap(w, F.array(*[F.lit(x) for x in lexicon]) if lexicon else F.array().cast("array<string>")),
        "void": F.coalesce(F.trim("text") == "", F.lit(True)) | F.contains("text", F.lit("�")),
    }
    codes = F.array_join(F.filter(F.array(*[F.when(F.coalesce(c, F.lit(False)), F.lit(k)) for k, c in rules.items()]), lambda x: x.isNotNull()), ",")
    return samples.withColumn("_w", words(F.col("text"))).withColumn("reasons", codes).drop("_w")


def learn_lexicon(labelled: DataFrame, min_count: int = 5) -> DataFrame:
    """Words of several toxic texts of the learning half and of no clean one."""
    known = labelled.filter(F.col("toxic").isNotNull() & (bucket("sample_id") % 2 == 0))
    tokens = known.select("toxic", F.explode(F.array_distinct(words(F.col("text")))).alias("word"))
    return tokens.groupBy("word").agg(F.sum("toxic").alias("toxic_texts"), F.count("*").alias("texts")).filter((F.col("toxic_texts") == F.col("texts")) & (F.col("texts") >= min_count))


def exact_duplicates(samples: DataFrame) -> DataFrame:
    """One row per text met more than once: the smallest id, which stays, and the number of rows."""
    key = F.sha2(F.col("text"), 256)
    return samples.groupBy(key.alias("text_sha256")).agg(F.min("sample_id").alias("kept"), F.count("*").alias("copies")).filter("copies > 1")


def stratum(seconds: Column) -> Column:
    """Duration classes; the ones the reference leaves open are named gap and over."""
    return F.when(seconds <= 30, "to30").when(seconds <= 60, "to60").when(seconds <= 180, "to180").when(seconds < 600, "gap").when(seconds <= 900, "to900").otherwise("over")


def frame_cap(seconds: Column) -> Column:
    cap = F.when(seconds <= 30, 30).when(seconds <= 60, 60).when(seconds <= 180, 90).otherwise(384)
    return F.least(seconds, cap.cast("long"))


def domain_weights(samples: DataFrame, tau: float = 0.5) -> DataFrame:
    """(domain, n, weight): weight lifts small domains by share**(tau - 1) and keeps the total."""
    per = samples.groupBy("domain").agg(F.count("*").alias("n"))
    total = per.agg(F.sum("n").alias("total"), F.sum(F.pow(F.col("n").cast("double"), tau)).alias("norm"))
    return per.crossJoin(F.broadcast(total)).select("domain", "n", (F.pow(F.col("n").cast("double"), tau - 1) * F.col("total") / F.col("norm")).alias("weight"))


def balanced(samples: DataFrame, tau: float = 0.5) -> DataFrame:
    """(sample_id, domain, copies): whole copies by weight, one more by md5 fraction."""
    w = domain_weights(samples, tau).select("domain", "weight")
    whole = F.floor("weight")
    extra = (bucket("sample_id") / F.lit(float(2**32)) < F.col("weight") - whole).cast("int")
    return samples.join(F.broadcast(w), "domain").select("sample_id", "domain", (whole + extra).cast("long").alias("copies"))  # a row per domain


def stratified(samples: DataFrame, per: int, domains: int, seed: int = 42) -> DataFrame:
    """``per`` rows of each of the first ``domains`` domains by name, by hash order."""
    named = samples.select("domain").distinct().orderBy("domain").limit(domains)
    w = Window.partitionBy("domain").orderBy(bucket("sample_id", seed=seed), "sample_id")
    return samples.join(F.broadcast(named), "domain", "left_semi").withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= per)


def retained(samples: DataFrame, share: float, seed: int = 42) -> DataFrame:
    """A nested subset: a smaller share is always part of a larger one."""
    return samples.filter(bucket("sample_id", seed=seed) < int(share * 2**32))


def rubric(samples: DataFrame) -> DataFrame:
    """Completeness is left to pages; redundancy of 3-grams and coherence of sentences per text."""
    w = words(F.col("text"))
    grams = F.when(F.size("w") >= 3, F.transform(F.sequence(F.lit(1), F.size("w") - 2), lambda i: F.array_join(F.slice("w", i, 3), " "))).otherwise(F.array().cast("array<string>"))
    s = samples.select("sample_id", "domain", "text", w.alias("w")).withColumn("g", grams)
    sentences = F.filter(F.split("text", r"[.!?]", -1), lambda x: F.trim(x) != "")
    redundancy = F.when(F.size("g") > 0, 1 - F.size(F.array_distinct("g")) / F.size("g")).otherwise(0.0)
    return s.select("sample_id", "domain", F.size("w").alias("n_words"), redundancy.alias("redundancy"), F.size(sentences).alias("n_sentences"))
