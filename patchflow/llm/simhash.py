"""SimHash near-duplicate groups.

Fingerprints are made per text in Arrow batches.  Linking works on distinct
fingerprints only, so copies cost one row, and every step keeps members and labels, never pairs:

* the 64 bits are cut in four blocks more than must agree; two fingerprints that differ in at
  most four bits leave enough blocks alike, so each choice of agreeing blocks gives one key: 15
  keys of 21 bits for up to some 30 million fingerprints, 35 of 27 bits and 70 of 32 bits beyond,
  so that the buckets stay small.  The links are the same for each number of blocks;
* a bucket of m <= ``bucket`` fingerprints is compared whole, and only a spanning forest of what is
  linked there leaves it (m - 1 edges at most).  A crowded bucket is dealt into parts of about
  half that size, each treated so; what one family holds mostly becomes one component here;
* what is left to do in a crowded bucket is to link different components.  Where all but
  ``bucket`` of its members are of one component, these few are compared with all;
* in other crowded buckets, fingerprints meet at midpoints: two values are within four bits if,
  and only if, some value is within two bits of both.  Midpoints that one component alone
  reaches go; at the others each component is hooked to the least one it meets, until none meet.

Each step is exact, has no cap, and is linear in the fingerprints.

Components are found by hooking each node to its least neighbour, following the
hooks to their roots, and contracting, over tables in the shared folder.  Null and empty texts have
fingerprint zero; a null id takes part, and is the smallest id of its group only if all ids
there are null.  Repeated rows stay repeated.  Of ties in ``keep_one`` the row with the least text hash stays, of equal
rows one.  Very long texts are read in pieces of 4,096 shingles.  Columns of the input never clash
with ours.  An empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import SENT_KEYS, Scratch, as_bytes, keyed_rows, map_arrow, read_table, sized_join

BITS = 64
#: Lists of at most ``bucket`` fingerprints that may be broadcast.
SENT_LISTS = 1 << 12


def fingerprint(text: bytes, shingle: int, seed: int = 42) -> int:
    """Unsigned fingerprint of one text."""
    import numpy as np
    import xxhash

    words = text.lower().split()  # of bytes: A-Z only, and exactly the six ASCII spaces
    if not words:
        return 0
    hashed = xxhash.xxh64_intdigest
    if len(words) <= shingle:
        return hashed(b" ".join(words), seed)
    joined = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])
    n = len(words) - shingle + 1
    values = np.array([hashed(joined[a:b], seed) for a, b in zip(starts[:n].tolist(), ends[shingle - 1 :].tolist())], np.uint64)
    total = np.zeros(BITS, np.int64)
    for i in range(0, n, 4096):
        bits = np.unpackbits(values[i : i + 4096].astype(">u8").view(np.uint8).reshape(-1, 8), axis=1)
        total += bits.sum(axis=0, dtype=np.int32)
    return int.from_bytes(np.packbits(2 * total > n).tobytes(), "big")


def with_fingerprints(docs: DataFrame, shingle: int = 4) -> DataFrame:
    """Rows (doc_id, k2, fp): k2 is a hash of the text, fp the fingerprint as a signed long."""

    def run(batches: Iterator):
        import numpy as np
        import pyarrow as pa

        for batch in batches:
            values = np.array([fingerprint(t, shingle) for t in as_bytes(batch.column(2))], np.uint64)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(values.view(np.int64))], ["doc_id", "k2", "fp"])

    text = F.col("text").cast("string")
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(F.coalesce(text, F.lit(""))).alias("k2"), text.alias("text"))
    return map_arrow(texts, run, "doc_id long, k2 long, fp long")


def block_keys(fp, blocks: int, agree: int) -> list:
    """One long per choice of ``agree`` blocks: its number and the bits of these blocks (under 48)."""
    edges = [round(i * BITS / blocks) for i in range(blocks + 1)]
    keys = []
    for k, chosen in enumerate(combinations(range(blocks), agree)):
        key = F.lit(0).cast("long")
        for b in chosen:
            width = edges[b + 1] - edges[b]
            key = F.shiftleft(key, width).bitwiseOR(F.shiftrightunsigned(fp, edges[b]).bitwiseAND(F.lit((1 << width) - 1).cast("long")))
        keys.append(key.bitwiseOR(F.lit(k << 48).cast("long")))  # the number above all bits: choices may differ in width
    return keys


def midpoint_masks(bits: int) -> list[int]:
    """All masks of at most ``bits`` set bits, as signed longs."""
    masks = [sum(1 << b for b in c) for k in range(bits + 1) for c in combinations(range(BITS), k)]
    return [m - (1 << BITS) if m >> (BITS - 1) else m for m in masks]


def block_count(fingerprints: int, distance: int = 4, mean: int = 16) -> int:
    """Fewest blocks whose keys put at most ``mean`` of so many uniform fingerprints in a bucket; four of them agree at most."""
    agree = 2
    while agree < 4 and fingerprints >> (BITS * agree // (agree + distance)) >= mean:
        agree += 1
    return distance + agree


def _forest(lists: DataFrame, distance: int) -> DataFrame:
    """Edges (a, b), a > b: a spanning forest of the links within each list ``m`` of fingerprints."""

    def run(batches: Iterator):
        import numpy as np
        import pyarrow as pa

        for batch in batches:
            column = batch.column(0)
            bounds = np.asarray(column.offsets)
            flat = column.values.to_numpy(zero_copy_only=False)
            size = np.diff(bounds)
            made = []
            for n in np.unique(size).tolist():
                starts = bounds[:-1][size == n]
                step = max(1, (1 << 20) // (n * n))
                for i in range(0, len(starts) if n > 1 else 0, step):
                    m = np.sort(flat[starts[i : i + step, None] + np.arange(n)], axis=1)
                    near = np.bitwise_count((m[:, :, None] ^ m[:, None, :]).view(np.uint64)) <= distance  # unsigned: of a signed value it counts the magnitude's bits
                    some = near.sum(axis=(1, 2)) > n
                    m, near = m[some], near[some]
                    label = np.broadcast_to(np.arange(n), m.shape)
                    while len(m):
                        lower = np.where(near, label[:, None, :], n).min(axis=2)
                        if (lower == label).all():
                            break
                        label = lower
                    row, place = np.nonzero(label != np.arange(n))
                    made.append((m[row, place], m[row, label[row, place]]))
            if made:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in zip(*made)], ["a", "b"])

    return map_arrow(lists.select("m"), run, "a long, b long")


def _midpoints(many: DataFrame, bits: int) -> DataFrame:
    """(label, mid) for all values within ``bits`` of the fingerprints of ``many`` (label, fp)."""

    def run(batches: Iterator):
        import numpy as np
        import pyarrow as pa

        masks = np.array(midpoint_masks(bits), np.int64)
        for batch in batches:
            label, fp = (batch.column(k).to_numpy(zero_copy_only=False) for k in (0, 1))
            for i in range(0, len(fp), 64):
                mid = fp[i : i + 64, None] ^ masks
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(label[i : i + 64], len(masks))), pa.array(mid.ravel())], ["label", "mid"])

    return map_arrow(many.select("label", "fp"), run, "label long, mid long")


def _crowded(members: DataFrame, distance: int, bucket: int, scratch: Scratch, sent: int) -> DataFrame:
    """Edges between the labels of ``members`` (key, fp, label), the members of crowded buckets."""
    per = members.groupBy("key", "label").count().groupBy("key").agg(F.max_by("label", F.struct("count", "label")).alias("main"), (F.sum("count") - F.max("count")).alias("others"))
    per = scratch.save(per.filter("others > 0"))
    mixed = scratch.save(sized_join(members, per, ["key"], scratch, sent=sent, rows=per.rows))
    if not mixed.rows:
        return mixed.select(F.col("label").alias("a"), F.col("fp").alias("b"))
    few = mixed.filter((F.col("others") <= bucket) & (F.col("label") != F.col("main")))
    lists = scratch.save(few.groupBy("key").agg(F.collect_list(F.struct("fp", "label")).alias("m")))
    met = sized_join(mixed.filter(F.col("others") <= bucket).select("key", "fp", "label"), lists, ["key"], scratch, sent=min(sent, SENT_LISTS), rows=lists.rows)
    close = F.filter("m", lambda x: (x["label"] != F.col("label")) & (F.bit_count(x["fp"].bitwiseXOR(F.col("fp"))) <= distance))
    edges = met.select("label", F.explode(close).alias("x")).select(F.greatest("label", "x.label").alias("a"), F.least("label", "x.label").alias("b")).distinct()
    out = scratch.save(edges)
    many = scratch.save(mixed.filter(F.col("others") > bucket).select("fp", "label").distinct())
    if not many.rows:
        return out
    reached = _midpoints(many, distance // 2)
    ends = (F.min("label").alias("low"), F.max("label").alias("top"))
    shared = reached.groupBy("mid").agg(*ends).filter("low < top").select("mid")
    reached = scratch.save(reached.join(shared.hint("merge"), "mid", "left_semi").distinct())
    while True:
        low = reached.groupBy("mid").agg(*ends).filter("low < top").select("mid", "low")
        hooks = scratch.save(reached.join(low.hint("merge"), "mid").filter("low < label").groupBy(F.col("label").alias("a")).agg(F.min("low").alias("b")))
        if not hooks.rows:
            return out
        out = scratch.save(out.union(hooks))
        roots = components(hooks.sparkSession, hooks, scratch, sent).select(F.col("node").alias("label"), F.col("label").alias("root"))
        reached = scratch.save(sized_join(reached, roots, ["label"], scratch, "left", sent).select("mid", F.coalesce("root", "label").alias("label")).distinct())


def link_fingerprints(spark, distinct: DataFrame, scratch: Scratch, distance: int = 4, blocks: int | None = None, bucket: int = 64, sent: int = SENT_KEYS) -> DataFrame:
    """Edges (a, b), a > b, whose components are those of all pairs within ``distance`` bits."""
    blocks = blocks or block_count(distinct.count(), distance)
    keys = distinct.select("fp", F.explode(F.array(*block_keys(F.col("fp"), blocks, blocks - distance))).alias("key"))
    hot = scratch.save(keys.groupBy("key").count().filter(F.col("count") > bucket).select("key", F.ceil(2 * F.col("count") / bucket).alias("parts")))
    dealt = scratch.save(sized_join(keys, hot, ["key"], scratch, "left", sent, hot.rows)) if hot.rows else keys
    part = F.pmod(F.xxhash64("fp"), F.coalesce("parts", F.lit(1))) if hot.rows else F.lit(0)
    lists = dealt.groupBy("key", part.alias("part")).agg(F.collect_list("fp").alias("m")).filter(F.size("m") > 1)
    edges = scratch.save(_forest(lists, distance).distinct())
    if not hot.rows:
        return edges
    labels = components(spark, edges, scratch, sent)
    members = dealt.filter("parts is not null").select("key", "fp").join(labels.withColumnRenamed("node", "fp").hint("merge"), "fp", "left")
    members = scratch.save(members.select("key", "fp", F.coalesce("label", "fp").alias("label")))
    return edges.union(_crowded(members, distance, bucket, scratch, sent))


def components(spark, edges: DataFrame, scratch: Scratch, sent: int = SENT_KEYS) -> DataFrame:
    """(node, label) for edges (a, b), a > b: label is the smallest node of the component; the smallest nodes themselves are left out.

    Each round hooks every node to its least neighbour below it, replaces the hooks by their
    roots, and goes on with the edges between different roots.
    """
    rounds = []
    while True:
        up = scratch.save(edges.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("label")))
        n, higher = up.rows, True
        while n and higher:  # two hooks at a time
            hooks = lambda near, far, up=up: up.select(F.col("node").alias(near), F.col("label").alias(far))
            climbed = sized_join(sized_join(up, hooks("label", "far"), ["label"], scratch, "left", sent, n), hooks("far", "top"), ["far"], scratch, "left", sent, n)
            up = scratch.save(climbed.select("node", F.coalesce("top", "far", "label").alias("label"), F.col("top").isNotNull().alias("higher")), higher=F.col("higher"))
            higher = up.found["higher"]
        up = up.select("node", "label")
        if not n:
            break
        rounds.append((up, n))
        here = sized_join(edges, up.select(F.col("node").alias("a"), F.col("label").alias("x")), ["a"], scratch, "left", sent, n).select("x", "b")
        there = sized_join(here, up.select(F.col("node").alias("b"), F.col("label").alias("y")), ["b"], scratch, "left", sent, n).select("x", F.coalesce("y", "b").alias("y"))
        edges = scratch.save(there.filter("x != y").select(F.greatest("x", "y").alias("a"), F.least("x", "y").alias("b")).distinct())
        if not edges.rows:
            break
    if not rounds:
        return spark.createDataFrame([], "node long, label long")
    out, n = rounds.pop()
    while rounds:
        first, more = rounds.pop()
        n += more
        out = scratch.save(sized_join(first, out.select(F.col("node").alias("label"), F.col("label").alias("far")), ["label"], scratch, "left", sent, n - more).select("node", F.coalesce("far", "label").alias("label")).union(out))
    return out


def near_duplicates(docs: DataFrame, shingle: int = 4, distance: int = 4, blocks: int | None = None, bucket: int = 64) -> DataFrame:
    """(doc_id, k2, fp, label, component_id) for every row of ``docs``; label is the least fingerprint of the group."""
    spark = docs.sparkSession
    scratch = Scratch(spark, "simhash")
    made = scratch.save(with_fingerprints(docs, shingle))
    distinct = scratch.save(made.groupBy("fp").agg(F.min("doc_id").alias("least")))
    labels = components(spark, link_fingerprints(spark, distinct.select("fp"), scratch, distance, blocks, bucket), scratch)
    named = scratch.save(sized_join(distinct, labels.withColumnRenamed("node", "fp"), ["fp"], scratch, "left").select("fp", F.coalesce("label", "fp").alias("label"), "least"))
    of_label = scratch.save(named.groupBy("label").agg(F.min("least").alias("component_id")))
    of_fp = scratch.save(sized_join(named, of_label, ["label"], scratch, rows=of_label.rows).select("fp", "label", "component_id"))
    return sized_join(made, of_fp, ["fp"], scratch, rows=of_fp.rows).select("doc_id", "k2", "fp", "label", "component_id")


def keep_one(docs: DataFrame, shingle: int = 4, distance: int = 4) -> DataFrame:
    """One row of each group, as it was: that of the least doc_id (null last), of equals the one with the least text hash."""
    order = F.struct(F.col("doc_id").isNull(), "doc_id", "k2")
    best = near_duplicates(docs, shingle, distance).groupBy("label").agg(F.min(order).alias("b")).select(F.coalesce("b.doc_id", F.lit(-(2**63))).alias("_k1"), F.col("b.k2").alias("_k2"))
    return keyed_rows(docs).join(best.hint("shuffle_hash"), ["_k1", "_k2"], "left_semi").dropDuplicates(["_k1", "_k2"]).select("_row.*")


def op2_simhash_near_dedup(spark, sf_dir: str) -> DataFrame:
    out = near_duplicates(read_table(spark, sf_dir, "documents"))
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
