"""Quality rules: per-text counts and cross-document line frequency.

One pass measures every text and lists its lines as hashes (words lower-cased in A-Z, joined
by one space).  Lines are counted per host (``source``) over distinct documents; a line in more
than ``SHARE`` of its host's documents, and in more than ``FLOOR`` of them, is removed
(``limit`` sets a number for all hosts instead), and a text that loses more than ``most_removed`` of
its words is rejected.  Copies must not make each other look like boilerplate, so documents of
the same words (lower-cased in A-Z) count as one; texts that differ in a word count each.

Null and empty texts have no words and fail the base rule; very long ones are measured whole.  A
null source is a host of its own.  Repeated rows get equal results; ties can't arise, as all
figures are counts.  Columns of the input never clash with ours.  An empty table gives an empty one.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, as_bytes, keyed_rows, map_arrow, no_null_id, read_table, row_groups, sized_join

SYMBOLS = "#*$%&|<>"
COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
LEAST_WORDS = 50
MOST_REPEATED_PERCENT = 50
#: Share of a host's distinct documents, and least number, above which a line is boilerplate.
SHARE, FLOOR = 0.05, 10


def _measure(texts: list[bytes]) -> tuple:
    """The counts of each text; its lines with words, as (numbers, hashes, words); the hash of all its words."""
    import numpy as np

    from .textkernel import BYTES_POW, WORDS_POW, Words, run_hash, with_doc

    plain, lower = Words(texts), Words(texts, lower=True)
    buffer = plain.buffer
    symbols = np.zeros(256, bool)
    symbols[[ord(c) for c in SYMBOLS]] = True
    chars = plain.per_doc(plain.inside & ((buffer & 0xC0) != 0x80))
    found = plain.per_doc(symbols[buffer])

    at, h = plain.windows(3)
    repeat = np.zeros(plain.n, np.int64)
    if len(at):
        _, back, times = np.unique(with_doc(h, plain.doc[at]), return_inverse=True, return_counts=True)
        covered = np.zeros(len(plain.start), bool)
        for k in range(3):
            covered[at[times[back] > 1] + k] = True
        repeat = np.bincount(plain.doc[covered], minlength=plain.n)

    stop = np.flatnonzero(buffer == 10)
    start = np.concatenate([[0], stop[:-1] + 1]) if len(stop) else stop
    from_word, to_word = np.searchsorted(plain.start, start), np.searchsorted(plain.start, stop)
    full = to_word > from_word
    start, stop, from_word, to_word = start[full], stop[full], from_word[full], to_word[full]
    doc = plain.doc[from_word]
    exact = with_doc(run_hash(plain.sums, start, stop, BYTES_POW), doc)
    first = np.unique(exact, return_index=True)[1]
    dup = np.bincount(doc, minlength=plain.n) - np.bincount(doc[first], minlength=plain.n)

    line = run_hash(lower.word_sums(), from_word, to_word, WORDS_POW).view(np.int64)
    ends = np.searchsorted(doc, np.arange(plain.n), side="right")
    begins = np.concatenate([[0], ends[:-1]])
    line_ends = np.flatnonzero(buffer == 10)
    number = np.searchsorted(line_ends, start) - np.searchsorted(line_ends, plain.doc_start)[doc]
    return [plain.count, chars, found, dup, repeat], [(number[a:b], line[a:b], (to_word - from_word)[a:b]) for a, b in zip(begins, ends)], run_hash(lower.word_sums(), lower.first[:-1], lower.first[1:], WORDS_POW).view(np.int64)


def measured(docs: DataFrame) -> DataFrame:
    """doc_id, k1, k2, host, the counts, the lines: numbers, hashes, words, and the hash of all words."""
    fields = "doc_id long, k1 long, k2 long, host string, " + ", ".join(f"{c} long" for c in COUNTS)
    schema = fields + ", line_no array<int>, line array<long>, line_words array<int>, whole long"

    def run(batches: Iterator):
        import pyarrow as pa

        kinds = [pa.list_(pa.int32()), pa.list_(pa.int64()), pa.list_(pa.int32())]
        names = ["doc_id", "k1", "k2", "host", *COUNTS, "line_no", "line", "line_words", "whole"]
        for batch in batches:
            for first, texts in row_groups(as_bytes(batch.column(4))):
                counts, lines, whole = _measure(texts)
                yield pa.RecordBatch.from_arrays(
                    [
                        *(batch.column(i).slice(first, len(texts)) for i in range(4)),
                        *(pa.array(c, pa.int64()) for c in counts),
                        *(pa.array([x[k] for x in lines], t) for k, t in enumerate(kinds)),
                        pa.array(whole),
                    ],
                    names,
                )

    text = F.col("text").cast("string")
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), no_null_id().alias("k1"), F.xxhash64(F.coalesce(text, F.lit(""))).alias("k2"), F.coalesce(F.col("source").cast("string"), F.lit("")).alias("host"), text.alias("text"))
    return map_arrow(keyed, run, schema)


def judged(docs: DataFrame, limit: int | None = None, most_removed: float = 0.7) -> tuple[DataFrame, DataFrame]:
    """The verdict of each row, and the lines removed as (k1, k2, line_no).

    Verdict rows: doc_id, k1, k2, the counts, base_failed, n_line_words_removed, kept.
    """
    scratch = Scratch(docs.sparkSession, "rules")
    table = scratch.save(measured(docs).withColumn("uid", F.monotonically_increasing_id()))
    lines = table.select("uid", "k1", "k2", "host", "whole", F.explode(F.arrays_zip("line_no", "line", "line_words")).alias("x")).select("uid", "k1", "k2", "host", "whole", "x.*")
    counts = lines.select("host", "line", "whole").distinct().groupBy("host", "line").count().filter(F.col("count") > (FLOOR if limit is None else limit))
    if limit is None:  # hosts too small for the share to pass the floor need no size
        large = scratch.save(table.filter("n_words > 0").select("host", "whole").distinct().groupBy("host").agg((SHARE * F.count("*")).alias("most")).filter(F.col("most") > FLOOR))
        counts = sized_join(counts, large, ["host"], scratch, "left", rows=large.rows).filter(F.col("count") > F.coalesce("most", F.lit(float(FLOOR))))
    often = scratch.save(counts.select("host", "line"))
    gone = scratch.save(sized_join(lines, often, ["host", "line"], scratch, rows=often.rows).select("uid", "k1", "k2", "line_no", "line_words"))
    lost = gone.groupBy("uid").agg(F.sum("line_words").alias("lost"))
    removed = F.coalesce("lost", F.lit(0)).cast("long")
    failed = (F.col("n_words") < LEAST_WORDS) | (100 * F.col("n_repeat_words") > MOST_REPEATED_PERCENT * F.col("n_words"))
    verdict = (
        table.drop("line_no", "line", "line_words", "whole", "host")
        .join(lost.hint("merge"), "uid", "left")
        .withColumn("base_failed", failed)
        .withColumn("n_line_words_removed", removed)
        .withColumn("kept", ~F.col("base_failed") & (F.col("n_line_words_removed") <= most_removed * F.col("n_words")))
        .drop("uid", "lost")
    )
    return verdict, gone.select("k1", "k2", "line_no").distinct()


def filter_quality(docs: DataFrame, limit: int | None = None, most_removed: float = 0.7) -> DataFrame:
    """The rows kept, without their removed lines; other columns as they were, n_chars (where present) anew if the text changed."""
    verdict, gone = judged(docs, limit, most_removed)
    fate = (
        verdict.filter("kept").select(F.col("k1").alias("_k1"), F.col("k2").alias("_k2")).distinct()
        .join(gone.groupBy(F.col("k1").alias("_k1"), F.col("k2").alias("_k2")).agg(F.collect_set("line_no").alias("_gone")).hint("merge"), ["_k1", "_k2"], "left")
    )
    text, whole = F.col("_row.text"), F.col("_gone").isNull()
    left = F.array_join(F.filter(F.split(text, "\n", -1), lambda x, i: ~F.array_contains(F.col("_gone"), i)), "\n")
    row = F.col("_row").withField("text", F.when(whole, text).otherwise(left))
    if "n_chars" in docs.columns:
        row = row.withField("n_chars", F.when(whole, F.col("_row.n_chars")).otherwise(F.length(left).cast(docs.schema["n_chars"].dataType)))
    return keyed_rows(docs).join(fate.hint("shuffle_hash"), ["_k1", "_k2"]).select(row.alias("_row")).select("_row.*")


def op9_quality_rules(spark, sf_dir: str) -> DataFrame:
    verdict, _ = judged(read_table(spark, sf_dir, "documents"))
    return verdict.select("doc_id", *COUNTS, "base_failed", "kept")


OP9_SQL = r"""
with d as (
  select row_number() over () id, doc_id, coalesce(source, '') host, coalesce(text, '') t, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') w from documents
), tri as (
  select id, s, w[s] || ' ' || w[s + 1] || ' ' || w[s + 2] g from (select id, w, unnest(range(1, len(w) - 1)) s from d where len(w) > 2)
), again as (
  select id, count(distinct p) n from (select id, unnest([s, s + 1, s + 2]) p from (select id, s, count(*) over (partition by id, g) n from tri) where n > 1) group by 1
), raw as (
  select id, host, unnest(string_split(t, chr(10))) line from d
), lines as (
  select id, host, line, regexp_extract_all(translate(line, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') w from raw
), said as (
  select id, host, line, array_to_string(w, ' ') norm, len(w) n from lines where len(w) > 0
), dup as (
  select id, count(*) - count(distinct line) n from said group by 1
), whole as (
  select id, host, array_to_string(regexp_extract_all(translate(t, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+'), ' ') all_words from d where len(w) > 0
), hosts as (
  select host, greatest(10, 0.05 * count(distinct all_words)) most from whole group by 1
), often as (
  select s.host, norm from said s join whole using (id) group by 1, 2 having count(distinct all_words) > (select most from hosts h where h.host = s.host)
), lost as (
  select id, sum(n) n from said join often using (host, norm) group by 1
), c as (
  select id, doc_id, len(w) n_words, length(regexp_replace(t, '[\x20\x09-\x0D]+', '', 'g')) word_chars, length(regexp_replace(t, '[^#*$%&|<>]', '', 'g')) n_symbols from d
), j as (
  select doc_id, n_words, word_chars, n_symbols, coalesce(dup.n, 0) n_dup_lines, coalesce(again.n, 0) n_repeat_words, coalesce(lost.n, 0) lost
  from c left join dup using (id) left join again using (id) left join lost using (id)
)
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_words < 50 or 100 * n_repeat_words > 50 * n_words as base_failed,
  not (n_words < 50 or 100 * n_repeat_words > 50 * n_words) and lost <= 0.7 * n_words as kept
from j
"""
