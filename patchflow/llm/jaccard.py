"""Near-duplicate groups of the pipeline: SimHash candidates, five-word shingles, Jaccard of 0.8 or more, no link lost.

A text is the set of hashes of its five-word runs (words lower-cased, cut at ASCII spaces; fewer
words are one run), and its fingerprint the majority bits of these.  Texts of equal sets are one
node.  Four differing bits see the closest pairs only: at a similarity of 0.8 some ten of 64 bits
differ.  So fingerprints give the first links, and a prefix join those that the bits miss.  With
o = the least overlap of a set of n at the threshold:

* any global order may be used, and two linked sets share m or more of their first n - o + m
  members.  The first n - o + n/10 by hash value are counted, and a node with too few members
  that any other node has too can have no partner: most nodes leave here;
* the rest are first linked along the SimHash blocks of operator 2 and to the leader of each
  MinHash bucket, verified, so that a family of many near copies is mostly one component at linear cost;
* members held by one component only can't link two components.  They come first in the order,
  then those of the fewest components; nodes of different components that share one of their first n - o + 1
  members are compared, if the places of it let them share enough, and the smaller has it among its first n / 9;
* sets of nu and nv members that are linked differ in (nu + nv) / 9 at most.  Each set has ``PARITY`` bits, flipped by its
  members' hashes; bits that differ are never more than members that differ, so pairs with too many aren't made.

Tables of few or short rows are dealt to a few parts before they are written, so that files are begun
by light tasks and not by each task of a join of whole sets.

Every link is verified on whole sets.  Components are those of all pairs at the threshold.  Texts
without words are one node, as copies are.  A null id takes part; null texts are empty.  Of ties the row with the
least text hash stays, of equal rows one.  Other columns are carried as they are, whatever their
names.  Very long texts are sets like others.  An empty table gives an empty one.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import SENT_KEYS, Scratch, as_bytes, keyed_rows, map_arrow, row_groups, sized_join
from .simhash import components, link_fingerprints

SHINGLE = 5
#: Members of several components that may be broadcast (32 bytes each).
SENT_MEMBERS = 1 << 18
#: MinHash buckets of a node, for the links to leaders; they only save work.
BUCKETS = 8
#: Bits of a set that bound how many members of two sets differ.
PARITY = 1024


def shingle_sets(texts: list[bytes], shingle: int = SHINGLE) -> tuple:
    """Sorted distinct shingle hashes of all texts in one array, and the bounds of each text."""
    import numpy as np

    from .textkernel import WORDS_POW, Words, run_hash

    w = Words([t.decode("utf-8", "replace").lower().encode() for t in texts])
    at, h = w.windows(shingle)
    few = np.flatnonzero((w.count > 0) & (w.count < shingle))
    doc = np.concatenate([w.doc[at], few])
    h = np.concatenate([h, run_hash(w.word_sums(), w.first[few], w.first[few] + w.count[few], WORDS_POW)]).view(np.int64)
    order = np.lexsort((h, doc))
    doc, h = doc[order], h[order]
    new = np.ones(len(h), bool)
    new[1:] = (h[1:] != h[:-1]) | (doc[1:] != doc[:-1])
    doc, h = doc[new], h[new]
    return h, np.searchsorted(doc, np.arange(w.n + 1))


def majority_bits(h, bounds):
    """Fingerprint of each set of hashes: a bit is 1 if set in over half of them; 0 for none."""
    import numpy as np

    n = np.diff(bounds)
    some = np.flatnonzero(n)
    out = np.zeros(len(n), np.uint64)
    if len(some):
        bits = np.unpackbits(h.astype(">i8").view(np.uint8).reshape(-1, 8), axis=1)
        total = np.add.reduceat(bits, bounds[:-1][some], axis=0, dtype=np.int32)
        out[some] = np.packbits(2 * total > n[some, None], axis=1).view(">u8").ravel()
    return out.view(np.int64)


def parity_words(h, bounds):
    """PARITY bits of each set as 64-bit words: a bit is 1 if an odd number of members fall on it."""
    import numpy as np

    from .textkernel import mix

    doc = np.repeat(np.arange(len(bounds) - 1), np.diff(bounds))
    place, uses = np.unique(doc * PARITY + (mix(h.view(np.uint64)) & np.uint64(PARITY - 1)).astype(np.int64), return_counts=True)
    place = place[uses % 2 == 1]
    out = np.zeros((len(bounds) - 1) * PARITY // 64, np.uint64)
    np.bitwise_or.at(out, place >> 6, np.uint64(1) << (place & 63).astype(np.uint64))
    return out.view(np.int64)


def with_sets(docs: DataFrame) -> DataFrame:
    """Rows (doc_id, k2, node, n, members, least, fp, parity): ``least`` holds the MinHash values."""

    def run(batches: Iterator):
        import numpy as np
        import pyarrow as pa
        import xxhash

        from .textkernel import mix

        salts = mix(np.arange(1, BUCKETS + 1, dtype=np.uint64))
        for batch in batches:
            for first, texts in row_groups(as_bytes(batch.column(2))):
                h, bounds = shingle_sets(texts)
                n = np.diff(bounds)
                least = np.zeros((len(texts), BUCKETS), np.uint64)
                for k in range(BUCKETS) if len(h) else ():
                    least[n > 0, k] = np.minimum.reduceat(mix(h.view(np.uint64) ^ salts[k]), bounds[:-1][n > 0])
                node = np.array([xxhash.xxh3_64_intdigest(h[a:b].tobytes()) for a, b in zip(bounds[:-1], bounds[1:])], np.uint64)
                yield pa.RecordBatch.from_arrays(
                    [
                        *(batch.column(i).slice(first, len(texts)) for i in range(2)),
                        pa.array(node.view(np.int64)),
                        pa.array(n.astype(np.int64)),
                        pa.ListArray.from_arrays(pa.array(bounds.astype(np.int32)), pa.array(h)),
                        pa.ListArray.from_arrays(pa.array(np.arange(0, least.size + 1, BUCKETS, dtype=np.int32)), pa.array(least.ravel().view(np.int64))),
                        pa.array(majority_bits(h, bounds)),
                        pa.ListArray.from_arrays(pa.array(np.arange(len(texts) + 1, dtype=np.int32) * (PARITY // 64)), pa.array(parity_words(h, bounds))),
                    ],
                    ["doc_id", "k2", "node", "n", "members", "least", "fp", "parity"],
                )

    text = F.col("text").cast("string")
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(F.coalesce(text, F.lit(""))).alias("k2"), text.alias("text"))
    return map_arrow(rows, run, "doc_id long, k2 long, node long, n long, members array<long>, least array<long>, fp long, parity array<long>")


#: n - o + 1 of a set of n, o = ceil(0.8 n), and the lengths that go with it.
PREFIX = "n - (4 * n + 4) div 5 + 1"
COUNTED = f"{PREFIX} + (n + 9) div 10 - 1"
#: Members among the counted that a partner of at least 0.8 n must share.
SHARED = "(2 * n + 24) div 25"


def verified(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """The pairs (a, b, ...) whose sets have a Jaccard similarity of 0.8 or more."""
    left, right = (sets.select(F.col("node").alias(x), F.col("n").alias(f"n{x}"), F.col("members").alias(f"m{x}")) for x in "ab")
    met = pairs.join(left.hint("merge"), "a").join(right.hint("merge"), "b")
    common = F.size(F.array_intersect("ma", "mb"))
    return met.filter(5 * common >= 4 * (F.col("na") + F.col("nb") - common)).select(*pairs.columns)


def partnered(made: DataFrame, scratch: Scratch) -> DataFrame:
    """(node, n, members, least, fp, parity), one row a node, of the nodes that can have a partner; ``made`` is dropped."""
    each = made.select("node", F.explode(F.slice("members", F.lit(1), F.expr(f"cast({COUNTED} as int)"))).alias("x"))
    alone = each.groupBy("x").agg(F.min("node").alias("node"), F.max("node").alias("top")).filter("node = top").groupBy("node").agg(F.count("*").alias("own"))
    nodes = made.filter("n > 0").groupBy("node").agg(F.min("uid").alias("uid"), F.min("n").alias("n")).join(alone.hint("merge"), "node", "left")
    can = scratch.save(nodes.filter(f"{COUNTED} - coalesce(own, 0) >= {SHARED}").select("uid").repartition(scratch.few()))
    few = can.rows <= SENT_KEYS
    out = scratch.save(made.join(F.broadcast(can) if few else can.hint("shuffle_hash"), "uid", "left_semi").select("node", "n", "members", "least", "fp", "parity").coalesce(scratch.few(2)))
    scratch.drop(can, made)
    return out


def block_pairs(sets: DataFrame, scratch: Scratch) -> DataFrame:
    """Candidates (a, b) along operator 2's links of fingerprints; nodes of one fingerprint stand behind the least of them."""
    held = scratch.save(sets.groupBy("fp").agg(F.min("node").alias("b")).repartition(scratch.few()))
    linked = link_fingerprints(sets.sparkSession, held.select("fp"), scratch)
    same = sized_join(sets.select("fp", F.col("node").alias("a")), held, ["fp"], scratch, rows=held.rows).select("a", "b")
    one, two = held.select(F.col("fp").alias("a"), F.col("b").alias("x")), held.select(F.col("fp").alias("b"), F.col("b").alias("y"))
    over = sized_join(sized_join(linked, one, ["a"], scratch, rows=held.rows), two, ["b"], scratch, rows=held.rows)
    return same.union(over.select(F.greatest("x", "y"), F.least("x", "y"))).filter("a > b")


def edges(made: DataFrame, scratch: Scratch) -> DataFrame:
    """Links (a, b) whose components are those of all pairs at the threshold."""
    spark = made.sparkSession
    sets = partnered(made, scratch)
    met = sets.select(F.col("node").alias("a"), F.posexplode("least").alias("k", "v"))
    leaders = met.groupBy("k", "v").agg(F.min("a").alias("b"), F.max("a").alias("top")).filter("b < top").select("k", "v", "b")
    led = met.join(leaders.hint("merge"), ["k", "v"]).filter("a > b").select("a", "b")
    first = scratch.save(verified(led.union(block_pairs(sets, scratch)).distinct(), sets).repartition(scratch.few()))
    named = components(spark, first, scratch)
    part = F.coalesce("label", "node").alias("part")
    sent = first.rows <= SENT_KEYS  # each link names one node at most; else the joined sets are written, as both readers would sort them
    each = sets.join(F.broadcast(named) if sent else named.hint("merge"), "node", "left").select("node", "n", part, "members")
    flat = (each if sent else scratch.save(each)).select("node", "n", "part", F.explode("members").alias("x"))
    # how many components have a member, by partial counts of (member, component)
    mixed = scratch.save(flat.groupBy("x", "part").agg(F.count("*").alias("df")).groupBy("x").agg(F.count("*").alias("parts"), F.sum("df").alias("df")).filter("parts > 1").select("x", F.struct("parts", "df").alias("df")).repartition(scratch.few()))
    ranked = sized_join(flat, mixed, ["x"], scratch, sent=SENT_MEMBERS, rows=mixed.rows).groupBy("node", "n", "part").agg(F.sort_array(F.collect_list(F.struct("df", "x"))).alias("r"))
    # n - size(r) members come before the mixed ones
    need = F.expr(f"cast({PREFIX} - n + size(r) as int)")
    # pos counts the members before one; a pair whose first common member has them at i and j shares n - i and n - j at most
    keys = ranked.withColumn("need", need).filter("need > 0").select("node", "n", "part", (F.col("n") - F.size("r")).alias("before"), F.posexplode(F.slice("r", F.lit(1), F.col("need"))).alias("i", "r"))
    keys = scratch.save(keys.select("node", "n", "part", F.col("r.x").alias("x"), (F.col("before") + F.col("i")).alias("pos")).repartition(scratch.few()))
    links = first
    for r in range(ROUNDS):
        led, keys = led_links(keys, sets, scratch, r)
        links = links.union(led)
    keys = keys.join(sets.select("node", "parity").hint("merge"), "node")
    larger, smaller = keys.alias("u"), keys.filter("9 * pos <= n").alias("v")
    pairs = larger.join(smaller.hint("merge"), F.expr(f"u.x = v.x and v.n <= u.n and v.part != u.part and {FITS} and {CLOSE}"))
    near = pairs.select(F.greatest("u.node", "v.node").alias("a"), F.least("u.node", "v.node").alias("b")).distinct()
    return links.union(scratch.save(verified(scratch.save(near.repartition(scratch.few())), sets).repartition(scratch.few())))


#: Whether nodes u and v, whose first common member has these places, can share enough.
FITS = "4 * u.n <= 5 * v.n - 9 * v.pos and 4 * v.n <= 5 * u.n - 9 * u.pos"
#: Whether the parity bits of u and v leave them few enough differing members.
CLOSE = "9 * (" + " + ".join(f"bit_count(u.parity[{i}] ^ v.parity[{i}])" for i in range(PARITY // 64)) + ") <= u.n + v.n"
#: Rounds of links to the leaders of a member, and leaders a round, before pairs are made; they only save work.
ROUNDS, LEADERS = 3, 12


def led_links(keys: DataFrame, sets: DataFrame, scratch: Scratch, turn: int) -> tuple[DataFrame, DataFrame]:
    """Verified links (a, b) of nodes to a few nodes of each member's that can be the smaller side, others each turn; and the keys under their new parts, without members of one part."""
    row = F.struct("node", "n", "pos", "part")
    leaders = scratch.save(keys.groupBy("x").agg(F.array_distinct(F.array(*[F.min_by(row, F.when(F.expr("9 * pos <= n"), F.xxhash64("node", F.lit(turn * LEADERS + k)))) for k in range(LEADERS)])).alias("v"), F.min("part").alias("low"), F.max("part").alias("top")).filter("low < top").select("x", "v").repartition(scratch.few()))
    open_keys = scratch.save(sized_join(keys, leaders, ["x"], scratch, sent=SENT_MEMBERS // 4, rows=leaders.rows).select("x", row.alias("u"), "v"))
    told = open_keys.select("u", F.explode(F.expr(f"filter(v, v -> u.part != v.part and {FITS})")).alias("v")).select(F.greatest("u.node", "v.node").alias("a"), F.least("u.node", "v.node").alias("b"), F.greatest("u.part", "v.part").alias("pa"), F.least("u.part", "v.part").alias("pb")).distinct()
    new = scratch.save(verified(scratch.save(told.repartition(scratch.few())), sets).repartition(scratch.few()))
    part_edges = new.select(F.col("pa").alias("a"), F.col("pb").alias("b")).distinct()
    merged = components(sets.sparkSession, part_edges, scratch).select(F.col("node").alias("part"), F.col("label").alias("whole"))
    moved = sized_join(open_keys.select("u.*", "x"), merged, ["part"], scratch, "left")
    return new.select("a", "b"), scratch.save(moved.select("node", "n", "pos", F.coalesce("whole", "part").alias("part"), "x"))


def near_duplicates(docs: DataFrame) -> DataFrame:
    """(doc_id, k2, label) for every row of ``docs``."""
    scratch = Scratch(docs.sparkSession, "jaccard")
    made = scratch.save(with_sets(docs).withColumn("uid", F.monotonically_increasing_id()))
    rows = scratch.save(made.select("doc_id", "k2", "node").coalesce(scratch.few()))
    labels = components(docs.sparkSession, edges(made, scratch), scratch)
    return sized_join(rows, labels, ["node"], scratch, "left").select("doc_id", "k2", F.coalesce("label", "node").alias("label"))


def keep_one(docs: DataFrame) -> DataFrame:
    """One row of each group, as it was: that of the least doc_id (null last), of equals the one with the least text hash."""
    order = F.struct(F.col("doc_id").isNull(), "doc_id", "k2")
    best = near_duplicates(docs).groupBy("label").agg(F.min(order).alias("b")).select(F.coalesce("b.doc_id", F.lit(-(2**63))).alias("_k1"), F.col("b.k2").alias("_k2"))
    return keyed_rows(docs).join(best.hint("shuffle_hash"), ["_k1", "_k2"], "left_semi").dropDuplicates(["_k1", "_k2"]).select("_row.*")
