"""Near-duplicate texts: five-word shingles, exact set join and MinHash bands, components.

Texts of equal word sequences form a class, led by its smallest id; only leaders are compared, so
thousands of copies cost one row.  A null text or one without words has no shingle and links to
nothing; one of fewer than five words is one shingle.  Ids are expected to be distinct.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..shared import shared_dir
from .curate import words

SHINGLE, THRESHOLD, HASHES, BANDS = 5, 0.8, 64, 16
#: Members of a bucket on the left side of one task's pairs.
BLOCK = 256


def _set_of(w: Column, n: int) -> Column:
    grams = F.transform(F.sequence(F.lit(1), F.size(w) - (n - 1)), lambda i: F.array_join(F.slice(w, i, n), " "))
    none = F.array().cast("array<string>")
    return F.array_distinct(F.when(F.size(w) >= n, grams).when(F.size(w) > 0, F.array(F.array_join(w, " "))).otherwise(none))


def classes(samples: DataFrame, n: int = SHINGLE) -> DataFrame:
    """(class_key, rep, shingles): one row per word sequence; shingles are 64-bit hashes."""
    w = samples.select("sample_id", F.coalesce(words(F.col("text")), F.array().cast("array<string>")).alias("w"))
    one = w.groupBy(F.sha2(F.array_join("w", " "), 256).alias("class_key")).agg(F.min("sample_id").alias("rep"), F.first("w").alias("w"))
    return one.filter(F.size("w") > 0).select("class_key", "rep", F.transform(_set_of(F.col("w"), n), lambda g: F.xxhash64(g)).alias("shingles"))


def membership(samples: DataFrame) -> DataFrame:
    """(sample_id, rep): texts without words lead themselves."""
    w = samples.select("sample_id", F.coalesce(F.array_join(words(F.col("text")), " "), F.lit("")).alias("t"))
    key = F.when(F.col("t") != "", F.sha2("t", 256))
    keyed = w.select("sample_id", key.alias("class_key"))
    lead = keyed.filter("class_key is not null").groupBy("class_key").agg(F.min("sample_id").alias("rep"))
    return keyed.join(lead.hint("merge"), "class_key", "left").select("sample_id", F.coalesce("rep", "sample_id").alias("rep"))


def meeting(keyed: DataFrame) -> DataFrame:
    """Distinct pairs a < b of (key, rep) rows that share a key.

    A bucket over ``BLOCK`` members is met in salted blocks on one side against all of the other,
    so no task holds a bucket squared and no member is dropped.
    """
    counts = keyed.groupBy("key").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("blocks"), F.count("*").alias("n")).filter("n > 1")
    shared = keyed.join(counts.drop("n").hint("merge"), "key")
    left = shared.select("key", F.col("rep").alias("a"), F.pmod(F.xxhash64("rep"), "blocks").cast("int").alias("salt"))
    right = shared.select("key", F.col("rep").alias("b"), F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("salt"))
    return left.join(right.hint("merge"), ["key", "salt"]).filter("a < b").select("a", "b").distinct()


def verified(pairs: DataFrame, sets: DataFrame, threshold: float) -> DataFrame:
    """(a, b, jaccard) of the pairs at or above the threshold, from whole shingle sets."""
    left = sets.select(F.col("rep").alias("a"), F.col("shingles").alias("sa"))
    right = sets.select(F.col("rep").alias("b"), F.col("shingles").alias("sb"))
    met = pairs.join(left.hint("merge"), "a").join(right.hint("merge"), "b")
    common = F.size(F.array_intersect("sa", "sb"))
    j = common / (F.size("sa") + F.size("sb") - common)
    return met.select("a", "b", j.alias("jaccard")).filter(F.col("jaccard") >= threshold)


def pairs_exact(sets: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """All pairs of leaders by a prefix join: sets at the threshold share one of their rarest shingles."""
    each = sets.select("rep", F.size("shingles").alias("n"), F.explode("shingles").alias("key"))
    rarity = each.groupBy("key").agg(F.count("*").alias("df"))
    ranked = each.join(rarity.hint("merge"), "key").groupBy("rep", "n").agg(F.sort_array(F.collect_list(F.struct("df", "key"))).alias("r"))
    # the epsilon guards the ceiling against the rounding of threshold * n; a longer prefix is safe
    length = F.col("n") - F.ceil(F.lit(threshold) * F.col("n") - 1e-9).cast("int") + 1
    prefix = ranked.select("rep", F.explode(F.slice("r", F.lit(1), length)).alias("x")).select("x.key", "rep")
    return verified(meeting(prefix), sets, threshold)


def signatures(sets: DataFrame, hashes: int = HASHES) -> DataFrame:
    """(rep, m0 ...): least hash of each seeded family; grouped by the class key, so no exchange is added."""
    each = sets.select("class_key", "rep", F.explode("shingles").alias("g"))
    return each.groupBy("class_key", "rep").agg(*[F.min(F.xxhash64(F.lit(i), "g")).alias(f"m{i}") for i in range(hashes)]).drop("class_key")


def pairs_minhash(sets: DataFrame, hashes: int = HASHES, bands: int = BANDS, threshold: float = THRESHOLD) -> DataFrame:
    """Pairs that agree in a band, verified; a pair at 0.8 is missed with probability 2e-4."""
    rows = hashes // bands
    keys = F.array(*[F.xxhash64(F.lit(b), *[f"m{b * rows + r}" for r in range(rows)]) for b in range(bands)])
    return verified(meeting(signatures(sets, hashes).select("rep", F.explode(keys).alias("key"))), sets, threshold)


def cut(df: DataFrame) -> DataFrame:
    """A checkpoint in the shared folder."""
    sc = df.sparkSession.sparkContext
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(shared_dir(df.sparkSession))
    return df.checkpoint()


def components(nodes: DataFrame, pairs: DataFrame) -> DataFrame:
    """(rep, component_id): least label of neighbours, then label of the label, until nothing moves.

    Jumping halves the depth each round, so a chain of n takes about log n rounds; lineage is cut each round.
    """
    both = cut(pairs.select("a", "b").union(pairs.select("b", "a")))
    labels = cut(nodes.select("rep", F.col("rep").alias("l")))
    for _ in range(2 * math.ceil(math.log2(2**40))):
        near = both.join(labels.hint("merge"), both.a == labels.rep).groupBy("b").agg(F.min("l").alias("near"))
        least = labels.join(near.hint("merge"), labels.rep == near.b, "left").select("rep", "l", F.least("l", F.coalesce("near", "l")).alias("m"))
        up = least.select(F.col("rep").alias("m"), F.col("m").alias("top"))
        after = cut(least.join(up.hint("merge"), "m", "left").select("rep", F.least("m", F.coalesce("top", "m")).alias("m"), "l"))
        moved = after.filter("m <> l").limit(1).count()
        labels = after.select("rep", F.col("m").alias("l"))
        if not moved:
            return labels.select("rep", F.col("l").alias("component_id"))
    raise RuntimeError("labels still move")


def near_duplicates(samples: DataFrame, exact: bool = False) -> DataFrame:
    """(sample_id, class_id, links, component_id): links are those of the class leader to other leaders."""
    sets = cut(classes(samples))
    pairs = cut(pairs_exact(sets) if exact else pairs_minhash(sets))
    links = pairs.select(F.explode(F.array("a", "b")).alias("rep")).groupBy("rep").agg(F.count("*").alias("links"))
    found = components(sets, pairs).join(links.hint("merge"), "rep", "left")
    m = membership(samples).join(found.hint("merge"), "rep", "left")
    return m.select("sample_id", F.col("rep").alias("class_id"), F.coalesce("links", F.lit(0)).cast("long").alias("links"), F.coalesce("component_id", "rep").alias("component_id"))
