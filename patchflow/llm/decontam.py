"""Benchmark decontamination: a prefix-filtered set join with positions.

Items are cut into windows of ``size`` consecutive words (a shorter item is one window).  Words of
items are ordered by how often the corpus has them, and each distinct window is found
by its rarest word alone: a text can hold the window only where it holds that word.  The
words of the texts join these prefix words; the place of the word in its window gives
the only place where the window can start, which must lie within the text, and
there all words are compared.

DataFrame functions only.  The prefix words are broadcast in blocks of at most ``block`` windows, so the
size sent is bounded for any benchmark; each block reads the texts once.

Null texts and items without words hold nothing.  Repeated rows get equal results.  A null
item_id is written as an empty string.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Scratch, keyed_rows, no_null_id, read_table

LOWER = ("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
#: What parts words, before A-Z are lower-cased: listed one by one, which Java turns into a bit set.
PARTING = [c for c in range(0x80) if not chr(c).isalnum()]
PARTS = "[" + "".join(f"\\x{c:02X}" for c in PARTING) + "]+"


def words_of(text: Column) -> Column:
    """Words in order; the first and the last entry may be empty and are no words then."""
    return F.split(text, PARTS, -1)


def word_count(text: Column) -> Column:
    words = words_of(text)
    return F.coalesce(F.size(words) - F.element_at(words, 1).eqNullSafe("").cast("int") - (F.element_at(words, -1).eqNullSafe("") & (F.size(words) > 1)).cast("int"), F.lit(0))


def item_windows(items: DataFrame, size: int) -> DataFrame:
    """Distinct windows (win, n, items): lower-cased words, their number, the items with them."""
    words = F.filter(words_of(F.translate(F.col("text").cast("string"), *LOWER)), lambda w: w != "")
    listed = items.select(F.coalesce(F.col("item_id").cast("string"), F.lit("")).alias("item"), words.alias("words")).filter(F.size("words") > 0)
    starts = listed.select("item", "words", F.explode(F.sequence(F.lit(1), F.greatest(F.size("words") - size + 1, F.lit(1)))).alias("s"))
    return starts.select("item", F.slice("words", F.col("s"), F.lit(size)).alias("win")).groupBy("win").agg(F.array_sort(F.collect_set("item")).alias("items")).withColumn("n", F.size("win"))


def _blocks(table: DataFrame, count: int, block: int, key: str) -> list[DataFrame]:
    n = max(1, math.ceil(count / block))
    return [table.filter(F.pmod(F.xxhash64(key), F.lit(n)) == i) for i in range(n)] if n > 1 else [table]


def occurrences(docs: DataFrame, items: DataFrame, size: int, block: int, scratch: Scratch) -> DataFrame:
    """(k1, k2, start, n, items) of each place in a text where a window stands."""
    windows = scratch.save(item_windows(items, size))
    n_windows = windows.count()
    vocabulary = scratch.save(windows.select(F.explode("win").alias("w")).select(F.lower("w").alias("token")).distinct())
    n_tokens = vocabulary.count()
    text = F.col("text").cast("string")
    split = docs.select(no_null_id().alias("k1"), F.xxhash64(F.coalesce(text, F.lit(""))).alias("k2"), words_of(text).alias("words"))
    tokens = split.select(F.explode("words").alias("w")).select(F.lower("w").alias("token"))
    counts = None
    for part in _blocks(vocabulary, n_tokens, block, "token"):
        found = tokens.join(F.broadcast(part), "token").groupBy("token").count()
        counts = found if counts is None else counts.union(found)
    rarity = scratch.save(vocabulary.join(counts, "token", "left").select("token", F.coalesce("count", F.lit(0)).alias("seen")))
    placed = windows.select("win", F.posexplode("win").alias("offset", "w")).select("win", "offset", F.lower("w").alias("token"))
    prefix = placed.join(rarity, "token").filter("seen > 0 or token is null").groupBy("win").agg(F.min(F.struct("seen", "token", "offset")).alias("p"), F.count(F.lit(1)).alias("met"))
    chosen = scratch.save(windows.join(prefix, "win").filter("met = n").select("p.token", "p.offset", "win", F.array_join("win", " ").alias("joined"), "n", "items"))
    out = None
    for part in _blocks(chosen, n_windows, block, "joined"):
        at = split.select("k1", "k2", "words", F.posexplode("words").alias("pos", "w")).withColumn("token", F.lower("w"))
        start = F.col("pos") - F.col("offset")
        candidates = at.join(F.broadcast(part.drop("win")), "token").filter((start >= 0) & (start + F.col("n") <= F.size("words")))
        # as strings: words hold no space, and without lambdas the scan, join and comparison stay one generated loop
        same = F.translate(F.array_join(F.slice("words", start + 1, F.col("n")), " "), *LOWER) == F.col("joined")
        hits = candidates.filter(same).select("k1", "k2", start.alias("start"), "n", "items")
        out = hits if out is None else out.union(hits)
    return out


def decontaminate(docs: DataFrame, items: DataFrame, size: int = 10, block: int = 100_000) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items (sorted ids), contaminated for each row."""
    scratch = Scratch(docs.sparkSession, "decontam")
    hits = occurrences(docs, items, size, block, scratch)
    per_text = hits.groupBy("k1", "k2").agg(F.array_sort(F.collect_set(F.struct("start", "n"))).alias("spans"), F.array_sort(F.array_distinct(F.flatten(F.collect_set("items")))).alias("items"))
    zero = F.struct(F.lit(0).alias("total"), F.lit(0).alias("reach"))

    def add(acc, x):
        end = x["start"] + x["n"]
        new = F.greatest(F.lit(0), end - F.greatest(acc["reach"], x["start"]))
        return F.struct((acc["total"] + new).alias("total"), F.greatest(acc["reach"], end).alias("reach"))

    covered = per_text.select("k1", "k2", "items", F.aggregate("spans", zero, add, lambda acc: acc["total"]).alias("hit"))
    text = F.col("text").cast("string")
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), no_null_id().alias("k1"), F.xxhash64(F.coalesce(text, F.lit(""))).alias("k2"), word_count(text).cast("long").alias("n_words"))
    none = F.array().cast("array<string>")
    return rows.join(covered.hint("merge"), ["k1", "k2"], "left").select(
        "doc_id", "k1", "k2", "n_words", F.coalesce("hit", F.lit(0)).cast("long").alias("n_hit"), F.coalesce(F.size("items"), F.lit(0)).cast("long").alias("n_items"), F.coalesce("items", none).alias("items"), F.col("hit").isNotNull().alias("contaminated")
    )


def drop_contaminated(docs: DataFrame, items: DataFrame, size: int = 10) -> DataFrame:
    """The rows of texts without any window of an item, as they were."""
    bad = decontaminate(docs, items, size).filter("contaminated").select(F.col("k1").alias("_k1"), F.col("k2").alias("_k2")).distinct()
    return keyed_rows(docs).join(bad.hint("shuffle_hash"), ["_k1", "_k2"], "left_anti").select("_row.*")


def op6_decontamination(spark, sf_dir: str) -> DataFrame:
    out = decontaminate(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "benchmark"))
    return out.select("doc_id", "n_words", "n_hit", "n_items", F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), "contaminated")


OP6_SQL = r"""
with d as (
  select doc_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') w from documents
), b as (
  select item_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') w from benchmark
), bw as (
  select distinct item_id, w[s:s + 9] win from (select item_id, w, unnest(range(1, greatest(len(w) - 8, 2))) s from b where len(w) > 0)
), lens as (select distinct len(win) n from bw),
dw as (
  select doc_id, n, s, w[s:s + n - 1] win from (select doc_id, w, n, unnest(range(1, len(w) - n + 2)) s from d, lens where len(w) >= n)
), hit as (
  select doc_id, s, n, item_id from dw join bw using (win)
), cover as (
  select doc_id, count(distinct p) n_hit from (select doc_id, unnest(range(s, s + n)) p from hit) group by 1
), ids as (
  select doc_id, count(*) n_items, string_agg(i, ',' order by i) i from (select distinct doc_id, cast(item_id as varchar) i from hit) group by 1
)
select d.doc_id, coalesce(len(d.w), 0) as n_words, coalesce(n_hit, 0) as n_hit, coalesce(n_items, 0) as n_items, sha256(coalesce(i, '')) as items_sha256, n_hit is not null as contaminated
from d left join cover using (doc_id) left join ids using (doc_id)
"""
