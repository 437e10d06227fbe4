"""URL filter by Bloom filter cascades.

Rules are rows (host, path, verdict) of a table of any size; a rule fits its host and all
subdomains where the url's path starts with the rule's, and the longest decides.  What a rule can
see of a url is a key: a suffix of its host, at a dot, and a start of its path as long as some rule's.
The distinct keys of all urls are the key universe of the corpus.  For each verdict, those of
them that are rules are listed.  A first Bloom filter encodes the listed keys; the next one encodes the
keys not listed that pass it; the next the listed keys that pass this one, and so on, until no key is
wrong.  Over this universe membership is exact: a scan asks the cascades for the keys of each url, longest
first, and the first one listed names the rule.  The rules are joined with distinct keys once, to
build the cascades, and never with urls.  Keys are 128-bit hashes.

The filters together are at most ``most_bytes``; a larger universe is cut into shards by key hash,
each with cascades of its own, asked one after the other.

Null urls and urls without ``://`` have empty host and path, and no rule.  Rules without a host
are left out; a null path is ``/``; of rules with one key, and of rules of one length that fit a url, block goes first.
Very long urls cost one key for each length of a rule's path.  Repeated rows get equal
results, other columns stay (host, path, rule and verdict are replaced), and empty tables of
urls or rules are fine.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Scratch, fresh, map_arrow, read_table, sized_join

LOWER = ("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


# fixed values: the rules of the contract
RULES = (("net", "/", "block"), ("example.net", "/en/", "allow"), ("example.com", "/de/", "block"), ("org", "/fr/", "allow"))
VERDICTS = ("block", "allow")


def url_parts(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path."""
    mark = F.instr(url, "://")
    rest = F.when(mark > 0, F.substr(url, mark + 3)).otherwise(F.lit(""))
    rest = F.coalesce(rest, F.lit(""))
    return F.translate(F.regexp_extract(rest, r"^[^/?#]*", 0), *LOWER), F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)


def keys_of(host: str, path: str, lengths: list[int]) -> list[bytes]:
    """What rules can see of a url, longest first."""
    if not host:
        return []
    cuts = [0, *(i + 1 for i, c in enumerate(host) if c == "." and i + 1 < len(host))]
    seen = [n for n in lengths if n <= len(path)]
    ranked = sorted(((len(host) - c + n, n, c) for c in cuts for n in seen), reverse=True)
    return [(host[c:] + path[:n]).encode() for _, n, c in ranked]


def hashes_of(keys: list[bytes]):
    """128 bits of each key, as two arrays of longs."""
    import numpy as np
    import xxhash

    both = np.frombuffer(b"".join(xxhash.xxh3_128_digest(k) for k in keys), ">i8").reshape(-1, 2).astype(np.int64)
    return np.ascontiguousarray(both[:, 0]), np.ascontiguousarray(both[:, 1])


def rule_keys(rules: DataFrame) -> DataFrame:
    """(h1, h2, verdict), one row a key."""

    def run(batches: Iterator):
        import pyarrow as pa

        for batch in batches:
            h1, h2 = hashes_of([(h + p).encode() for h, p in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist())])
            yield pa.RecordBatch.from_arrays([pa.array(h1), pa.array(h2), batch.column(2)], ["h1", "h2", "verdict"])

    return map_arrow(rules, run, "h1 long, h2 long, verdict string").groupBy("h1", "h2").agg(F.max("verdict").alias("verdict"))  # block > allow


class Filter:
    """Bits of one level."""

    def __init__(self, level: int, n: int, rate: float):
        self.level = level
        self.bits = max(64, math.ceil(-n * math.log(rate) / math.log(2) ** 2))
        self.hashes = max(1, round(self.bits / max(n, 1) * math.log(2)))
        self.data = None

    def positions(self, h1, h2):
        import numpy as np

        from .textkernel import mix

        salt = np.uint64(0x9E3779B97F4A7C15 * (self.level + 1) % 2**64)
        a, b = mix(h1.view(np.uint64) ^ salt), mix(h2.view(np.uint64) + salt) | np.uint64(1)
        return [((a + np.uint64(i) * b) % np.uint64(self.bits)).astype(np.int64) for i in range(self.hashes)]

    def has(self, h1, h2):
        import numpy as np

        out = np.ones(len(h1), bool)
        for p in self.positions(h1, h2):
            out &= (self.data[p >> 3] >> (p & 7).astype(np.uint8)) & 1 == 1
        return out


def fill(keys: DataFrame, f: Filter) -> Filter:
    """Sets the bits of all keys; executors build 4 KB parts, so the driver gets no key."""
    import numpy as np

    def run(batches: Iterator):
        import pyarrow as pa

        for batch in batches:
            h1, h2 = (batch.column(i).to_numpy(zero_copy_only=False) for i in (0, 1))
            if len(h1):
                yield pa.RecordBatch.from_arrays([pa.array(np.unique(np.concatenate(f.positions(h1, h2))) + 1)], ["p"])

    parts = map_arrow(keys.select("h1", "h2"), run, "p long").groupBy(F.bitmap_bucket_number("p").alias("k")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("p")).alias("b"))
    f.data = np.zeros(-(-f.bits // 32768) * 4096, np.uint8)
    for k, b in parts.collect():  # bits/8 bytes in all
        f.data[(k - 1) * 4096 : k * 4096] = np.frombuffer(b, np.uint8)
    return f


def passing(keys: DataFrame, f: Filter) -> DataFrame:
    def run(batches: Iterator):
        import pyarrow as pa

        for batch in batches:
            h1, h2 = (batch.column(i).to_numpy(zero_copy_only=False) for i in (0, 1))
            yield batch.filter(pa.array(f.has(h1, h2)))

    return map_arrow(keys, run, keys.schema)


def build_cascade(universe: DataFrame, scratch: Scratch) -> list[Filter]:
    """Filters for a table (h1, h2, listed) of distinct keys."""
    n_in, n_out = universe.agg(F.count_if("listed"), F.count_if(~F.col("listed"))).first()
    held, other, filters = universe.filter("listed"), universe.filter(~F.col("listed")), []
    n = n_in
    while n:
        rate = 0.5 if filters else min(0.5, n_in / max(n_out, 1) * math.sqrt(0.5))
        filters.append(fill(held, Filter(len(filters), n, rate)))
        wrong = scratch.save(passing(other, filters[-1]))
        held, other, n = wrong, held, wrong.count()
    return filters


def member(filters: list[Filter], h1, h2):
    """Exact membership for keys of the universe: which level first says no decides."""
    import numpy as np

    out = np.full(len(h1), len(filters) % 2 == 1)
    for i in reversed(range(len(filters))):
        out = np.where(filters[i].has(h1, h2), out, i % 2 == 1)
    return out


def judge_urls(pages: DataFrame, url: str = "url", rules: DataFrame | None = None, most_bytes: int = 64 << 20) -> DataFrame:
    """The rows with host, path, rule and verdict (replaced where present); ``rules`` are rows (host, path, verdict), by default RULES."""
    import pyarrow as pa

    spark = pages.sparkSession
    scratch = Scratch(spark, "urls")
    if rules is None:
        rules = spark.createDataFrame(RULES, "host string, path string, verdict string")
    clean = rules.select(F.translate("host", *LOWER).alias("host"), F.coalesce("path", F.lit("/")).alias("path"), "verdict").filter((F.col("host") != "") & F.col("verdict").isin(*VERDICTS))
    listed = scratch.save(rule_keys(clean))
    lengths = sorted(r[0] for r in clean.select(F.length("path")).distinct().collect())  # lengths of paths, not paths
    host, path = url_parts(F.col(url).cast("string"))
    parted = pages.withColumns({"host": host, "path": path}).drop("rule", "verdict")

    def seen(batches: Iterator):
        for batch in batches:
            urls = set(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()))
            h1, h2 = hashes_of(sorted({k for h, p in urls for k in keys_of(h, p, lengths)}))
            yield pa.RecordBatch.from_arrays([pa.array(h1), pa.array(h2)], ["h1", "h2"])

    every = map_arrow(parted.select("host", "path"), seen, "h1 long, h2 long").distinct()
    universe = scratch.save(sized_join(every, listed, ["h1", "h2"], scratch, "left", rows=listed.rows), listed=F.col("verdict").isNotNull())
    n_in = universe.found["listed"]
    bytes_needed = 0.25 * n_in * (8 + max(0.0, math.log2(max(universe.rows - n_in, 1) / max(n_in, 1))))
    shards = max(1, math.ceil(bytes_needed / most_bytes))
    best, how = fresh("_rule", parted.columns), fresh("_verdict", parted.columns)
    rows = parted.withColumns({best: F.lit(None).cast("string"), how: F.lit(None).cast("string")})
    names = rows.columns
    at = [names.index(c) for c in ("host", "path", best, how)]
    for s in range(shards):
        part = universe.filter(F.pmod("h1", F.lit(shards)) == s)
        cascades = {v: build_cascade(part.select("h1", "h2", F.coalesce(F.col("verdict") == v, F.lit(False)).alias("listed")), scratch) for v in VERDICTS}
        shipped = spark.sparkContext.broadcast(cascades)

        def run(batches: Iterator, shipped=shipped, s=s):
            import numpy as np

            for batch in batches:
                hosts, paths, found, verdicts = (batch.column(k).to_pylist() for k in at)
                keys = [keys_of(h, p, lengths) for h, p in zip(hosts, paths)]
                flat = [k for ks in keys for k in ks]
                row = np.repeat(np.arange(len(keys)), [len(ks) for ks in keys])
                h1, h2 = hashes_of(flat)
                mine = h1 % shards == s
                for v in VERDICTS:
                    hit = np.flatnonzero(mine)[member(shipped.value[v], h1[mine], h2[mine])]
                    first = np.unique(row[hit], return_index=True)[1]  # keys stand longest first
                    for k in hit[first].tolist():
                        r, name = row[k], flat[k].decode()
                        if found[r] is None or len(name) > len(found[r]):
                            found[r], verdicts[r] = name, v
                yield pa.RecordBatch.from_arrays([*batch.columns[: at[2]], pa.array(found, pa.string()), pa.array(verdicts, pa.string())], names)

        rows = map_arrow(rows, run, rows.schema)
    kept = [F.col(f"`{c}`") for c in parted.columns]
    return rows.select(*kept, F.col(best).alias("rule"), F.coalesce(how, F.lit("allow")).alias("verdict"))


def op4_url_filter(spark, sf_dir: str) -> DataFrame:
    return judge_urls(read_table(spark, sf_dir, "pages").select("page_id", "url")).select("page_id", "host", "path", "rule", "verdict")


OP4_SQL = """
with p as (
  select page_id, coalesce(case when instr(url, '://') > 0 then substr(url, instr(url, '://') + 3) else '' end, '') rest from pages
), q as (
  select page_id, translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') host,
    regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) path from p
), r as (
  select *, case
    when ('.' || host) like '%.example.net' and starts_with(path, '/en/') then 'example.net/en/'
    when ('.' || host) like '%.example.com' and starts_with(path, '/de/') then 'example.com/de/'
    when ('.' || host) like '%.org' and starts_with(path, '/fr/') then 'org/fr/'
    when ('.' || host) like '%.net' and starts_with(path, '/') then 'net/' end as rule from q
)
select page_id, host, path, rule, case when rule in ('net/', 'example.com/de/') then 'block' else 'allow' end as verdict from r
"""
