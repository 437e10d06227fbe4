"""Substring dedup by level-wise doubling of repeated word windows.

Goal: all windows of ``length`` words whose words also start elsewhere, in the same text or
another one.

* First level, a quarter of ``length`` (9 of 35): of the short windows inside every full window only the one
  with the least hash is taken (leftmost of equals), its anchor.  Both places of a repeated full
  window choose the same anchor, so nothing is lost, while about 7 % of the places are listed.
  Anchors at one place only can't lie in a repeat; they go.
* Long shot: the span of all full windows that hold the anchor (61 words, cut at the ends of the text).
  Where the whole span stands elsewhere too, all its windows are repeats at once.
* Anchors where it does not, and the others of the same hash, are doubled to the left and to
  the right (18 words); a repeat that holds the anchor has room on one side at least, so
  those with neither doubled window elsewhere go.  Of anchors with one
  and the same repeated span a single one takes part, standing for two.
* Last level: each full window whose anchor survives is counted.

Counting is always within the anchors of one hash, so a 64-bit collision must also happen among
these few.  Texts are read again only for anchors that reach the last level, and sent for the
removal only if they lose words: a bit map of 8 MB tells the scans which (a false
hit sends one text more).

Null texts have no words.  Rows are told apart by id and text: exact repeats of a row are other
places, as they should be.  A null id is an id of its own.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, as_bytes, map_arrow, read_table, row_groups

#: Bits of the map of affected texts.
MAP_BITS = 1 << 26


def anchor_length(length: int) -> int:
    return max(1, (length + 3) // 4)


def _keyed(docs: DataFrame) -> DataFrame:
    """doc_id, text and a key: k1 is the id (for null a hash of the text), k2 a 32-bit hash of the text."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    ident = F.col("doc_id").cast("long")
    return docs.select(ident.alias("doc_id"), F.coalesce(ident, F.xxhash64(text)).alias("k1"), F.hash(text).alias("k2"), text.alias("text"))


def _frame(names: list[str], columns: list):
    import pyarrow as pa

    return pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names)


def _least_windows(words, short: int, inner: int):
    """First words and hashes of all short windows; of each full window its first short window and its anchor, both by number."""
    import numpy as np

    at, h = words.windows(short)
    none = np.zeros(0, np.int64)
    if len(h) < inner:
        return at, h, none, none
    views = np.lib.stride_tricks.sliding_window_view(h, inner)
    base = np.flatnonzero(words.doc[at[: len(views)]] == words.doc[at[inner - 1 :]])
    least = [views[base[i : i + 65536]].argmin(axis=1) for i in range(0, len(base), 65536)]
    return at, h, base, base + np.concatenate([none, *least])


def _anchors(keyed: DataFrame, length: int) -> DataFrame:
    """(k1, k2, pos, h, sides, span) of the anchors.

    h: hash of the anchor; sides: 32 bits each of the doubled windows to the left and right; span: hash
    of all words of full windows with the anchor.
    """
    short = anchor_length(length)
    inner = length - short + 1  # short windows in a full one

    def run(batches: Iterator):
        import numpy as np

        from .textkernel import WORDS_POW, Words, mix, run_hash

        for batch in batches:
            k1, k2 = (batch.column(i).to_numpy(zero_copy_only=False) for i in (0, 1))
            for first, texts in row_groups(as_bytes(batch.column(2))):
                words = Words(texts)
                at, h, _, least = _least_windows(words, short, inner)
                if not len(least):
                    continue
                picked = np.unique(least)
                p = at[picked]
                doc = words.doc[p]
                begin, end = words.first[doc], words.first[doc + 1]
                lo, hi = np.maximum(p - (inner - 1), begin), np.minimum(p + length, end)
                sums = words.word_sums()
                shape = ((p - lo) * 4096 + (hi - p)).astype(np.uint64)
                span = mix(run_hash(sums, lo, hi, WORDS_POW) ^ mix(shape + np.uint64(1)))
                alone = mix(mix(k1[first + doc].view(np.uint64)) ^ p.astype(np.uint64))  # no room: equal to nothing
                left = np.where(p - short >= begin, run_hash(sums, np.maximum(p - short, 0), p + short, WORDS_POW), alone)
                right = np.where(p + 2 * short <= end, run_hash(sums, p, np.minimum(p + 2 * short, len(words.hash)), WORDS_POW), alone)
                sides = left >> np.uint64(32) << np.uint64(32) | right >> np.uint64(32)
                yield _frame(["k1", "k2", "pos", "h", "sides", "span"], [k1[first + doc], k2[first + doc], (p - begin).astype(np.int32), h[picked].view(np.int64), sides.view(np.int64), span.view(np.int64)])

    return map_arrow(keyed.select("k1", "k2", "text"), run, "k1 long, k2 int, pos int, h long, sides long, span long")


def _full_windows(held: DataFrame, length: int) -> DataFrame:
    """(k1, k2, pos, h, w, weight): start and hash of each full window whose anchor is at a place told; held: (k1, k2, text, at), at being (pos, weight)."""
    short = anchor_length(length)
    inner = length - short + 1

    def run(batches: Iterator):
        import numpy as np

        from .textkernel import WORDS_POW, Words, run_hash

        for batch in batches:
            k1, k2 = (batch.column(i).to_numpy(zero_copy_only=False) for i in (0, 1))
            places = batch.column(3)
            for first, texts in row_groups(as_bytes(batch.column(2))):
                words = Words(texts)
                at, h, base, least = _least_windows(words, short, inner)
                weight = np.zeros(len(words.hash), np.int32)  # of the places told
                for d in range(len(texts)):
                    told = places[first + d].values
                    pos, w = (told.field(i).to_numpy(zero_copy_only=False) for i in (0, 1))
                    weight[words.first[d] + pos] = w
                used = np.flatnonzero(weight[at[least]])
                start, anchor = at[base[used]], least[used]
                doc = words.doc[start]
                w = run_hash(words.word_sums(), start, start + length, WORDS_POW)
                yield _frame(["k1", "k2", "pos", "h", "w", "weight"], [k1[first + doc], k2[first + doc], (start - words.first[doc]).astype(np.int32), h[anchor].view(np.int64), w.view(np.int64), weight[at[anchor]]])

    return map_arrow(held.select("k1", "k2", "text", "at"), run, "k1 long, k2 int, pos int, h long, w long, weight int")


def _repeated(rows: DataFrame, *keys: str) -> DataFrame:
    """Keys at more than one place; a row with a weight stands for so many places."""
    times = F.sum("weight") if "weight" in rows.columns else F.count(F.lit(1))
    return rows.groupBy(*keys).agg(times.alias("n")).filter("n > 1").select(*keys)


def _bit():
    return F.pmod(F.xxhash64("k1", "k2"), F.lit(MAP_BITS))


def _bit_map(keys: DataFrame):
    """Bits of the keys: MAP_BITS / 8 bytes at most come to the driver and go to the executors."""
    parts = keys.select((_bit() + 1).alias("b")).groupBy(F.bitmap_bucket_number("b").alias("k")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("b")).alias("bits"))
    return keys.sparkSession.sparkContext.broadcast({k - 1: bytes(bits) for k, bits in parts.collect()})


def _is_set(bits: dict[int, bytes], b: int) -> bool:
    part = bits.get(b >> 15)
    return part is not None and bool(part[(b & 32767) >> 3] >> (b & 7) & 1)


def _among(keyed: DataFrame, keys: DataFrame) -> DataFrame:
    """The rows whose keys may be among ``keys``."""
    shipped = _bit_map(keys)
    rows = keyed.select("k1", "k2", "text", _bit().alias("b"))

    def run(batches: Iterator):
        import pyarrow as pa

        for batch in batches:
            yield batch.filter(pa.array([_is_set(shipped.value, b) for b in batch.column(3).to_pylist()], pa.bool_()))

    return map_arrow(rows, run, rows.schema).drop("b")


def repeated_windows(docs: DataFrame, length: int = 35, scratch: Scratch | None = None) -> DataFrame:
    """(k1, k2, lo, hi): ranges of starts of the windows that occur elsewhere too."""
    scratch = scratch or Scratch(docs.sparkSession, "substring")
    keyed = _keyed(docs)
    reach = length - anchor_length(length)
    every = scratch.save(_anchors(keyed, length))
    common = scratch.save(_repeated(every, "h"))
    anchors = scratch.save(every.join(common.hint("merge"), "h", "left_semi"))
    scratch.drop(every, common)

    spans = scratch.save(_repeated(anchors, "h", "span").withColumn("whole", F.lit(True)))
    told = scratch.save(anchors.join(spans.hint("merge"), ["h", "span"], "left"))
    scratch.drop(anchors, spans)
    ranges = told.filter("whole").select("k1", "k2", F.greatest(F.col("pos") - reach, F.lit(0)).alias("lo"), F.col("pos").alias("hi"))

    place = ["k1", "k2", "pos", "h", "sides"]
    undecided = told.filter("whole is null").select(*place, F.lit(1).alias("weight"))
    open_hashes = scratch.save(undecided.select("h").distinct())
    # anchors with one and the same span have the same windows: one stands for all
    stand_ins = told.filter("whole").groupBy("h", "span").agg(F.min(F.struct("k1", "k2", "pos", "sides")).alias("x")).select("x.k1", "x.k2", "x.pos", "h", "x.sides", F.lit(2).alias("weight"))
    rest = undecided.union(stand_ins.join(open_hashes.hint("merge"), "h", "left_semi").select(*place, "weight"))
    rest = scratch.save(rest.select("k1", "k2", "pos", "h", F.shiftrightunsigned("sides", 32).alias("left"), F.col("sides").bitwiseAND(F.lit(0xFFFFFFFF).cast("long")).alias("right"), "weight"))
    doubled = None
    for side in ("left", "right"):
        again = scratch.save(_repeated(rest, "h", side))
        found = rest.join(again.hint("merge"), ["h", side], "left_semi").select("k1", "k2", "pos", "weight")
        doubled = found if doubled is None else doubled.union(found)
    places = scratch.save(doubled.groupBy("k1", "k2").agg(F.array_sort(F.collect_set(F.struct("pos", "weight"))).alias("at")))
    scratch.drop(rest, open_hashes)

    windows = scratch.save(_full_windows(_among(keyed, places).join(places.hint("shuffle_hash"), ["k1", "k2"]), length))
    again = scratch.save(_repeated(windows, "h", "w"))
    single = scratch.save(windows.join(again.hint("merge"), ["h", "w"], "left_semi").select("k1", "k2", F.col("pos").alias("lo"), F.col("pos").alias("hi")).distinct())
    scratch.drop(windows, again)
    return ranges.union(single)


def remove_repeats(docs: DataFrame, length: int = 35, digest: bool = False) -> DataFrame:
    """doc_id, n_words, n_removed and ``kept`` (the words left, joined by one space), or its digest ``kept_sha256``."""
    scratch = Scratch(docs.sparkSession, "substring")
    places = scratch.save(repeated_windows(docs, length, scratch).groupBy("k1", "k2").agg(F.collect_set(F.struct("lo", "hi")).alias("at")))
    shipped = _bit_map(places)
    name = "kept_sha256" if digest else "kept"

    def told(words: list[bytes]) -> str:
        joined = b" ".join(words)
        return hashlib.sha256(joined).hexdigest() if digest else joined.decode("utf-8", "replace")

    def whole(batches: Iterator):
        """What stays as it is gets its result here; other texts go on."""
        import pyarrow as pa

        for batch in batches:
            sent, total, kept = [], [], []
            for t, b in zip(as_bytes(batch.column(3)), batch.column(4).to_pylist()):
                go = _is_set(shipped.value, b)
                words = None if go else t.split()  # of bytes: the six ASCII spaces
                sent.append(t if go else None)
                total.append(None if go else len(words))
                kept.append(None if go else told(words))
            yield pa.RecordBatch.from_arrays([*batch.columns[:3], pa.array(sent, pa.binary()), pa.array(total, pa.int64()), pa.array(kept, pa.string())], ["doc_id", "k1", "k2", "text", "n_words", name])

    def cut(batches: Iterator):
        import numpy as np
        import pyarrow as pa

        for batch in batches:
            total, removed, kept = (batch.column(i).to_pylist() for i in (2, 2, 3))
            for i, text in enumerate(batch.column(1).to_pylist()):
                removed[i] = 0
                if text is None:
                    continue
                words = text.split()
                total[i] = len(words)
                ranges = batch.column(4)[i]
                if ranges.is_valid:
                    lo, hi = (ranges.values.field(k).to_numpy(zero_copy_only=False) for k in (0, 1))
                    hi = np.minimum(hi, len(words) - length)
                    edge = np.zeros(len(words) + 1, np.int64)
                    np.add.at(edge, lo, 1)
                    np.add.at(edge, hi + length, -1)
                    words = [words[k] for k in np.flatnonzero(np.cumsum(edge[:-1]) == 0).tolist()]
                removed[i] = total[i] - len(words)
                kept[i] = told(words)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(total, pa.int64()), pa.array(removed, pa.int64()), pa.array(kept, pa.string())], ["doc_id", "n_words", "n_removed", name])

    first = map_arrow(_keyed(docs).select("doc_id", "k1", "k2", "text", _bit().alias("b")), whole, f"doc_id long, k1 long, k2 int, text binary, n_words long, {name} string")
    held = first.join(places.hint("shuffle_hash"), ["k1", "k2"], "left")
    return map_arrow(held.select("doc_id", "text", "n_words", name, "at"), cut, f"doc_id long, n_words long, n_removed long, {name} string")


def op3_substring_dedup(spark, sf_dir: str) -> DataFrame:
    return remove_repeats(read_table(spark, sf_dir, "documents"), digest=True)


OP3_SQL = r"""
with d as (
  select row_number() over () id, doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') w from documents
), win as (
  select id, s, md5(array_to_string(w[s:s + 34], ' ')) h from (select id, w, unnest(range(1, len(w) - 33)) s from d where len(w) >= 35)
), again as (
  select id, s from (select id, s, count(*) over (partition by h) n from win) where n > 1
), cover as (
  select distinct id, unnest(range(s, s + 35)) p from again
), words as (
  select id, p, w[p] word from (select id, w, unnest(range(1, len(w) + 1)) p from d)
), kept as (
  select id, string_agg(word, ' ' order by p) t from words anti join cover using (id, p) group by 1
), gone as (
  select id, count(*) n from cover group by 1
)
select doc_id, len(w) as n_words, coalesce(n, 0) as n_removed, sha256(coalesce(t, '')) as kept_sha256 from d left join kept using (id) left join gone using (id)
"""
