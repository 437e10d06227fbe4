"""Operators against plain versions, and on messy and empty tables."""

import collections
import hashlib
import random
import re
from array import array

import pytest
from pyspark.sql import functions as F

from patchflow.llm import bpe, decontam, htmltext, pii, quality, rules, sharding, simhash, substring, urlfilter
from patchflow.llm.common import Scratch

SF = "/root/testdata/sf0.001"
WORD = re.compile(r"[^\x20\x09-\x0D]+")
LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def texts_of(spark):
    return [(r.doc_id, r.text) for r in spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text").collect()]


# 1


def test_bpe_equals_the_public_library(spark):
    import tiktoken

    path, pattern = bpe.default_vocabulary()
    c = bpe.codec(open(path, "rb").read(), pattern)
    t = tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=c.ranks, special_tokens={})
    rng, tokens = random.Random(1), list(c.ranks)
    cases = [x for _, x in texts_of(spark)] + ["", " ", "a" * 5000, "ab" * 3000, "\n\n  x"]
    cases += ["".join(rng.choice("ab") for _ in range(40)) for _ in range(500)]
    cases += [b"".join(rng.choice(tokens) for _ in range(4)).decode("utf-8", "replace") for _ in range(2000)]
    for text in cases:
        packed = c.encode(text)
        assert array("I", packed).tolist() == t.encode_ordinary(text)
        assert c.decode(packed) == text.encode()


def test_bpe_messy(messy, nothing):
    out = bpe.decode(bpe.encode(messy)).collect()
    assert len(out) == 10 and all(bytes(r.decoded).decode() == (r.text or "") for r in out)
    assert all(r.k1 == "own k1" and r._in == "own _in" for r in out)
    assert bpe.token_digests(nothing).count() == 0


# 2


def components(values, distance=4):
    parent = list(range(len(values)))

    def top(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in range(len(values)):
        for j in range(i):
            if (values[i] ^ values[j]).bit_count() <= distance:
                a, b = top(i), top(j)
                parent[max(a, b)] = min(a, b)
    return [top(i) for i in range(len(values))]


@pytest.mark.parametrize(("bucket", "blocks", "sent"), [(1, None, 1 << 16), (64, 6, 1 << 16), (4, 7, 0), (64, 8, 0), (2, 8, 1 << 16)])
def test_fingerprint_links_equal_all_pairs(spark, bucket, blocks, sent):
    """Pairs within small buckets, midpoints beyond; each number of blocks; crowded keys broadcast and merged."""
    rng = random.Random(3)
    values = set()
    for _ in range(12):
        center = rng.getrandbits(64)
        for _ in range(8):
            v = center
            for b in rng.sample(range(64), rng.randint(0, 6)):
                v ^= 1 << b
            values.add(v)
    values = sorted(values)
    signed = [v - (1 << 64) if v >> 63 else v for v in values]
    s = Scratch(spark, "t")
    df = spark.createDataFrame([(v,) for v in signed], "fp long")
    got = {r.node: r.label for r in simhash.components(spark, simhash.link_fingerprints(spark, df, s, blocks=blocks, bucket=bucket, sent=sent), s).collect()}
    want = components(values)
    groups = collections.defaultdict(set)
    for v, g in zip(signed, want):
        groups[g].add(v)
    for g in groups.values():
        assert {got.get(v, v) for v in g} == {min(g)}


def test_fingerprints_equal_plain_version(spark, messy):
    """Every bit from its definition: words, shingles with repeats, strict majority."""
    import xxhash

    def plain(text):
        words = WORD.findall((text or "").translate(LOWER))
        shingles = [" ".join(words[i : i + 4]) for i in range(max(1, len(words) - 3))] if words else []
        h = [xxhash.xxh64_intdigest(x.encode(), 42) for x in shingles]
        return sum(1 << b for b in range(64) if 2 * sum(v >> b & 1 for v in h) > len(h))

    rows = texts_of(spark)[:80] + [(10**6, "É a\u00a0b c\u2003d e"), (10**6 + 1, "a b"), (10**6 + 2, "x y z w " * 5), (10**6 + 3, None)] + [(10**6 + 4, messy.filter("doc_id = 6").first().text)]
    got = {r.doc_id: r.fp % 2**64 for r in simhash.with_fingerprints(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {d: plain(t) for d, t in rows}


def test_block_keys_of_different_choices_never_meet(spark):
    rng = random.Random(8)
    df = spark.createDataFrame([(rng.getrandbits(63),) for _ in range(300)], "fp long")
    for blocks in (6, 7, 8):
        keys = df.select(F.array(*simhash.block_keys(F.col("fp"), blocks, blocks - 4)).alias("k"))
        assert keys.filter(F.size(F.array_distinct("k")) < F.size("k")).count() == 0


def test_edges_of_one_family_grow_with_its_size(spark):
    """A family of near fingerprints leaves a few edges a member, however large it is."""
    rng = random.Random(5)
    center = rng.getrandbits(63)
    family = sorted({center ^ sum(1 << b for b in rng.sample(range(63), 3)) for _ in range(2400)})
    rng.shuffle(family)
    edges = []
    for n in (500, 1000, 2000):
        s = Scratch(spark, "t")
        made = simhash.link_fingerprints(spark, spark.createDataFrame([(v,) for v in family[:n]], "fp long"), s)
        edges.append(made.count())
        groups = {r.label for r in simhash.components(spark, made, s).collect()}
        if n == 500:
            assert len(groups) == sum(g > 1 for g in collections.Counter(components(family[:500])).values())
    assert edges[2] <= 15 * 2000 and edges[2] <= 2.6 * edges[1] and edges[1] <= 2.6 * edges[0]


def test_block_count_grows_with_the_fingerprints():
    assert [simhash.block_count(n) for n in (0, 10**6, 10**8, 10**10, 10**13)] == [6, 6, 7, 8, 8]


def test_simhash_messy(messy, nothing):
    out = simhash.near_duplicates(messy).collect()
    assert len(out) == 10
    by_id = {r.doc_id: r for r in out}
    assert by_id[1].component_id == by_id[2].component_id == 1
    assert {by_id[i].fp for i in (3, 4, 5)} == {0} and by_id[5].component_id == 3
    kept = simhash.keep_one(messy)
    assert kept.columns == messy.columns and sorted(r.doc_id for r in kept.collect() if r.doc_id) == [1, 3, 6, 7]
    assert simhash.near_duplicates(nothing).count() == 0 and simhash.keep_one(nothing).count() == 0


# 3


def plain_removal(rows, length):
    seen = collections.Counter()
    for _, t in rows:
        w = WORD.findall(t or "")
        seen.update(tuple(w[i : i + length]) for i in range(len(w) - length + 1))
    out = []
    for d, t in rows:
        w = WORD.findall(t or "")
        cover = [False] * len(w)
        for i in range(len(w) - length + 1):
            if seen[tuple(w[i : i + length])] > 1:
                cover[i : i + length] = [True] * length
        kept = [x for x, c in zip(w, cover) if not c]
        out.append((str(d), len(w), len(w) - len(kept), " ".join(kept)))
    return sorted(out)


def as_plain(df):
    return sorted((str(r.doc_id), r.n_words, r.n_removed, r.kept) for r in df.collect())


@pytest.mark.parametrize(("length", "letters"), [(35, 40), (8, 6), (13, 3)])
def test_substrings_equal_plain_version(spark, length, letters):
    rng = random.Random(length)
    pool = [["x" * (1 + rng.randrange(letters)) for _ in range(rng.randint(5, 120))] for _ in range(12)]
    rows = []
    for d in range(100):
        w = []
        for _ in range(rng.randint(0, 5)):
            b = rng.choice(pool)
            a = rng.randrange(len(b))
            w += b[a : a + rng.randint(1, 120)] if rng.random() < 0.6 else [str(rng.random()) for _ in range(rng.randint(1, 30))]
        rows.append((d if d % 17 else None, " ".join(w) if d % 29 else None))
    rows += rows[:3]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert as_plain(substring.remove_repeats(df, length)) == plain_removal(rows, length)


def test_substrings_on_documents_and_messy(spark, messy, nothing):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    assert as_plain(substring.remove_repeats(docs)) == plain_removal(texts_of(spark), 35)
    rows = [(r.doc_id, r.text) for r in messy.collect()]
    assert as_plain(substring.remove_repeats(messy)) == plain_removal(rows, 35)
    assert substring.remove_repeats(nothing).count() == 0


# 4


def test_urls(spark):
    urls = ["http://a.NET/x?q#f", "https://m.example.net/en/1", "http://x.org/fr", "http://x.org/fr/", "http://example.com/de/1", "http://notexample.com/de/1", "ftp://net", "nohost", "", None, "://net/?a", "http://h.net#/b"]
    pages = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string").withColumns({"_h1": F.lit("own"), "host": F.lit("old")})
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in urlfilter.judge_urls(pages).collect()}
    assert got == {
        0: ("a.net", "/x", "net/", "block"), 1: ("m.example.net", "/en/1", "example.net/en/", "allow"), 2: ("x.org", "/fr", None, "allow"), 3: ("x.org", "/fr/", "org/fr/", "allow"),
        4: ("example.com", "/de/1", "example.com/de/", "block"), 5: ("notexample.com", "/de/1", None, "allow"), 6: ("net", "", None, "allow"), 7: ("", "", None, "allow"), 8: ("", "", None, "allow"),
        9: ("", "", None, "allow"), 10: ("net", "/", "net/", "block"), 11: ("h.net", "", None, "allow"),
    }
    assert {r.page_id: r.verdict for r in urlfilter.judge_urls(pages, most_bytes=1).collect()} == {k: v[3] for k, v in got.items()}
    assert urlfilter.judge_urls(pages.limit(0)).count() == 0


@pytest.mark.parametrize("most_bytes", [64 << 20, 3000])
def test_a_long_list_of_rules_equals_a_join(spark, most_bytes):
    """100,000 rules of many hosts and path lengths, against candidates joined one by one; urls repeated and very long."""
    rng = random.Random(12)
    n = 100_000
    rules = spark.range(n).select(
        F.concat(F.lit("h"), (F.col("id") % 5000).cast("string"), F.lit(".Org")).alias("host"), F.concat(F.lit("/p"), F.expr("cast(id div 5000 as string)")).alias("path"), F.when(F.col("id") % 3 == 0, "allow").otherwise("block").alias("verdict")
    ).union(spark.createDataFrame([("h7.org", "/p1", "allow"), (None, "/", "block"), ("org", None, "block"), ("h9.org", "/", "allow")], "host string, path string, verdict string"))
    urls = [f"http://{rng.choice(['', 'a.', 'b.a.', 'x'])}h{rng.randrange(6000)}.{rng.choice(['org', 'ORG', 'net'])}/p{rng.randrange(30)}{rng.choice(['', '/q', '?p1'])}" for _ in range(3000)]
    urls += urls[:5] + ["http://h1.org/p1" + "x" * 50_000, "http://h9.org/", "http://h7.org/p1"]
    pages = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")
    got = {r.page_id: (r.rule, r.verdict) for r in urlfilter.judge_urls(pages, rules=rules, most_bytes=most_bytes).collect()}
    table = {}
    for r in rules.collect():
        if r.host:
            key = r.host.translate(LOWER) + (r.path or "/")
            table[key] = "block" if table.get(key) == "block" else r.verdict
    want = {}
    for i, u in enumerate(urls):
        rest = u.split("://", 1)[1]
        host = re.match(r"[^/?#]*", rest)[0]
        path = re.match(r"[^?#]*", rest[len(host) :])[0]
        labels = host.translate(LOWER).split(".")
        names = [".".join(labels[k:]) + path[:m] for k in range(len(labels)) for m in range(1, min(len(path), 8) + 1)]
        fits = [x for x in names if x in table]
        rule = max(fits, key=len) if fits else None
        want[i] = (rule, table[rule] if rule else "allow")
    assert got == want
    assert {r.verdict for r in urlfilter.judge_urls(pages, rules=rules.limit(0)).collect()} == {"allow"}


def test_cascade_is_exact(spark):
    keys = spark.range(5000).select(F.xxhash64("id").alias("h1"), F.xxhash64("id", F.lit(1)).alias("h2"), (F.col("id") % 7 == 0).alias("listed"))
    filters = urlfilter.build_cascade(keys, Scratch(spark, "t"))
    p = keys.toPandas()
    assert len(filters) > 1 and (urlfilter.member(filters, p.h1.to_numpy(), p.h2.to_numpy()) == p.listed.to_numpy()).all()


# 5

BASE = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}


def luhn(s):
    return sum(d if i % 2 == 0 else 2 * d - (9 if d > 4 else 0) for i, d in enumerate(map(int, reversed(s)))) % 10 == 0


def base_spans(text):
    out = []
    for kind, pattern in BASE.items():
        for m in re.finditer(pattern, text or ""):
            digits = re.sub("[^0-9]", "", m[0])
            if kind == "email" or kind == "ip" and all(int(p) <= 255 for p in m[0].split(".")) or kind == "card" and 16 <= len(digits) <= 19 and luhn(digits) or kind == "phone" and 8 <= len(digits) <= 15:
                out.append((kind, m.start(), m.end()))
    return out


def test_personal_data_base_spans(spark, messy, nothing):
    rng = random.Random(9)
    odd = ["".join(rng.choice("0123456789.-@+ ()ab_é😀") for _ in range(rng.randint(0, 60))) for _ in range(400)]
    odd += ["a@b.c_d@e.f", "a@b.c@d.e", "x@y.z.", "256.1.1.1 1.2.3.4.5.6.7.8", "0000000001.2.3.4", "4539 1488 0343 6467", "9" * 30000, "a" * 30000 + "@", "+1" + " " * 5000 + "2345678", "+12345678" * 40]
    rows = [(i, t) for i, t in enumerate(odd)] + [(10**6 + d if d else None, t) for d, t in [(r.doc_id, r.text) for r in messy.collect()]] + [(2 * 10**6 + d, t) for d, t in texts_of(spark)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = collections.defaultdict(list)
    for r in pii.find_personal_data(df).collect():
        got[r.doc_id].append([(s.kind, s.start, s.end) for s in r.spans if s.base])
    want = collections.defaultdict(list)
    for d, t in rows:
        want[d].append(base_spans(t))
    assert {k: sorted(v) for k, v in got.items()} == {k: sorted(v) for k, v in want.items()}
    assert pii.find_personal_data(nothing).count() == 0
    masked = pii.mask_personal_data(messy)
    assert masked.columns == messy.columns and masked.count() == 10
    seven = masked.filter("doc_id = 7").first()
    assert "[EMAIL]" in seven.text and "[PHONE]" in seven.text and "[CARD]" in seven.text and "[IP]" in seven.text and seven.n_chars == len(seven.text)


def test_secrets_are_added(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    t = docs.limit(1).select(F.lit(-5).cast("long").alias("doc_id"), F.lit('see token = "96d17ded865a61704b5b8dc58aafba7d26a3c1ef" end').alias("text"))
    spans = pii.find_personal_data(docs.select("doc_id", "text").union(t)).filter("doc_id = -5").first().spans
    assert [(s.kind, s.start, s.end, s.base) for s in spans] == [("secret", 13, 53, False)]


# 6


def plain_hits(docs, items, size):
    cut = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    windows = {}
    for i, t in items:
        w = cut.findall((t or "").translate(LOWER))
        for s in range(max(1, len(w) - size + 1) if w else 0):
            windows.setdefault(tuple(w[s : s + size]), set()).add(str(i))
    out = []
    for d, t in docs:
        w, hit, found = cut.findall((t or "").translate(LOWER)), set(), set()
        for n in {len(x) for x in windows}:
            for s in range(len(w) - n + 1):
                if (x := tuple(w[s : s + n])) in windows:
                    hit |= set(range(s, s + n))
                    found |= windows[x]
        out.append((str(d), len(w), len(hit), sorted(found), bool(hit)))
    return sorted(out)


@pytest.mark.parametrize("block", [3, 100_000])
def test_decontamination_equals_plain_version(spark, messy, nothing, block):
    rng = random.Random(4)
    items = [(i, " ".join(rng.choice("the of É a1 B-c x K é".split()) for _ in range(rng.choice([0, 1, 3, 10, 14])))) for i in range(8)] + [(99, None), (100, "Word3 and word4 AND")]
    docs = [(d, ", ".join(rng.choice("The of é É A1 b c x K k".split()) for _ in range(rng.randint(0, 60)))) for d in range(40)] + [(r.doc_id, r.text) for r in messy.collect()]
    df, it = spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    got = sorted((str(r.doc_id), r.n_words, r.n_hit, r["items"], r.contaminated) for r in decontam.decontaminate(df, it, 10, block).collect())
    assert got == plain_hits(docs, items, 10)
    assert decontam.decontaminate(nothing, it).count() == 0 and decontam.decontaminate(df, it.limit(0)).filter("contaminated").count() == 0
    clean = decontam.drop_contaminated(messy, it)
    assert clean.columns == messy.columns and {r.doc_id for r in clean.collect()} == {d for d, *_, c in [(None if x[0] == "None" else int(x[0]), x[4]) for x in plain_hits([(r.doc_id, r.text) for r in messy.collect()], items, 10)] if not c}


# 7

PAGE = """<!DOCTYPE html><html><head><title>t</title><style>p{}</style><script>var t="</p>";</script></head><body class="has-sidebar">
<nav><ul><li><a>menu</a></ul></nav><div class="ad">buy</div><div class="cookie-banner">ok?</div>%s<section id="comments"><article class="comment"><p>me too</p></article></section><footer>&copy; x</footer>"""


def test_html(spark):
    body = "<article><h1>A &amp;\n  B</h1><p>one<b> two</b><br>three<p>four &lt;x&gt; &#233;<ul><li>five<li>six</ul><form>no<input></form><!-- c --></article>"
    text = "A & B\n\none two three\n\nfour <x> é\n\nfive\n\nsix"
    assert htmltext.main_text(htmltext.parse(PAGE % body)) == text
    assert htmltext.main_text(htmltext.parse("")) == "" and htmltext.main_text(htmltext.parse("<div>a</div><p>b<p")) == "a\n\nb"
    deep = "<div>" * 20000 + "x"
    assert htmltext.main_text(htmltext.parse(deep)) == "x"
    rows = [(1, "http://h.org/1", PAGE % body), (1, "http://h.org/1", PAGE % body), (2, None, None), (3, "x", "")]
    got = htmltext.extract(spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("_host", F.lit("own"))).collect()
    assert sorted((r.page_id, r.text) for r in got) == [(1, text), (1, text), (2, ""), (3, "")]


@pytest.mark.parametrize("most", [500_000, 0])
def test_site_templates_go(spark, most):
    rows = [(i, f"http://h.org/{i}", f"<div><span>Welcome to our site</span></div><div><p>page {i}</p></div><article><p>shared</p></article>" if i % 2 else f"<div><span>Welcome to our site</span></div><div><p>page {i}</p></div>") for i in range(60)]
    got = {r.page_id: r.text for r in htmltext.extract(spark.createDataFrame(rows, "page_id long, url string, html string"), most_hashes=most).collect()}
    assert all(t == ("shared" if i % 2 else f"page {i}") for i, t in got.items())


@pytest.mark.parametrize("most", [500_000, 0])
def test_templates_inside_articles_go_and_copies_stay(spark, most):
    box = "<div class='x1'><h3>Get our letter</h3><p>Every week, no fee</p></div>"
    page = "<html><body><article><h1>Title %s</h1><p>text %s says <b>this</b> well</p>%s<p>end %s</p></article></body></html>"
    rows = [(i, f"http://h.org/{i}", page % (i, i, box, i)) for i in range(40)]
    rows += [(100 + i, f"http://h.org/c{i}", page % ("c", "c", "", "c")) for i in range(40)]  # copies of one page
    got = {r.page_id: r.text for r in htmltext.extract(spark.createDataFrame(rows, "page_id long, url string, html string"), most_hashes=most).collect()}
    assert all(t == "Title {0}\n\ntext {0} says this well\n\nend {0}".format(i if i < 100 else "c") for i, t in got.items())


def test_template_limits_follow_the_host(spark):
    """On 400 pages a box of all goes and a passage quoted by 40 stays; off the article a menu of 40 goes, one of 10 stays."""
    box, quote, menu, rare = "<div><p>Get our letter</p></div>", "<p>to be or not to be</p>", "<div><span>section menu</span></div>", "<div><span>odd note</span></div>"
    page = lambda i: f"<html><body>{menu if i < 40 else ''}{rare if i < 10 else ''}<div class='t'><p>page {i}</p></div></body></html>"
    post = lambda i: f"<html><body><article><p>post {i}</p>{quote if i < 40 else ''}{box}</article></body></html>"
    rows = [(i, f"http://a.org/{i}", page(i)) for i in range(400)] + [(1000 + i, f"http://b.org/{i}", post(i)) for i in range(400)]
    got = {r.page_id: r.text for r in htmltext.extract(spark.createDataFrame(rows, "page_id long, url string, html string"), named=False).collect()}
    assert all(got[i] == ("odd note\n\n" if i < 10 else "") + f"page {i}" for i in range(400))
    assert all(got[1000 + i] == f"post {i}" + ("\n\nto be or not to be" if i < 40 else "") for i in range(400))


# 8


def test_quality_scores(spark, messy, nothing):
    docs, labels = spark.read.parquet("/root/testdata/sf0.01/documents.parquet"), spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    rows = quality.score_quality(docs, labels).join(labels, "doc_id").filter("held_out").collect()
    assert sum(r.predicted == r.quality for r in rows) / len(rows) > 0.95
    good, bad = [r.score for r in rows if r.quality], [r.score for r in rows if not r.quality]
    assert sum(g > b for g in good for b in bad) / len(good) / len(bad) > 0.95
    out = quality.score_quality(messy, labels).collect()
    assert len(out) == 10 and all(0 <= r.score <= 1 for r in out)
    assert quality.score_quality(nothing, labels).count() == 0
    assert {r.score for r in quality.score_quality(messy, labels.limit(0)).collect()} == {0.5}


def test_least_hashes_are_chosen_by_counts(spark):
    rows = spark.range(30000).select(F.col("id").alias("doc_id"))
    want = {r.doc_id for r in rows.orderBy(F.shiftrightunsigned(F.xxhash64("doc_id"), 1)).limit(2000).collect()}
    got = {r.doc_id for r in quality.least_hashes(rows, 2000, spare=20).collect()}
    assert want <= got and len(got) <= 2020
    assert quality.least_hashes(rows, 30000).count() == 30000 and quality.least_hashes(rows.limit(0), 5).count() == 0


def test_quality_scores_are_calibrated_and_equal_for_repeated_rows(spark):
    docs, labels = spark.read.parquet("/root/testdata/sf0.01/documents.parquet"), spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    twice = docs.union(docs.limit(50))
    rows = quality.score_quality(twice, labels, sample=150).join(labels, "doc_id", "left").collect()
    assert len(rows) == docs.count() + 50 and len({(r.doc_id, r.score) for r in rows}) == docs.count()
    known = [r for r in rows if r.held_out and r.quality is not None]
    assert abs(sum(r.score for r in known) - sum(r.quality for r in known)) / len(known) < 0.1


# 9


def test_rules_equal_plain_version(spark, messy, nothing):
    rows = texts_of(spark) + [(r.doc_id, r.text) for r in messy.collect()] + [(10**7, "a b c\n\na b c\n a b c\nA b c a b c |<#　é")]
    got = sorted(tuple(map(str, (r.doc_id, r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed))) for r in rules.judged(spark.createDataFrame(rows, "doc_id long, text string").withColumn("source", F.lit("s")))[0].collect())
    want = []
    for d, t in rows:
        t = t or ""
        w = WORD.findall(t)
        c = collections.Counter(tuple(w[i : i + 3]) for i in range(len(w) - 2))
        cover = {i + k for i in range(len(w) - 2) for k in range(3) if c[tuple(w[i : i + 3])] > 1}
        seen, dup = set(), 0
        for line in t.split("\n"):
            if WORD.search(line):
                dup += line in seen
                seen.add(line)
        want.append(tuple(map(str, (d, len(w), sum(map(len, w)), sum(t.count(s) for s in "#*$%&|<>"), dup, len(cover), len(w) < 50 or 100 * len(cover) > 50 * len(w)))))
    assert got == sorted(want)
    assert rules.judged(nothing)[0].count() == 0 and rules.filter_quality(nothing).count() == 0
    kept = rules.filter_quality(messy)
    assert kept.columns == messy.columns and sorted(str(r.doc_id) for r in kept.collect()) == ["1", "2", "2", "6", "None"]


def test_boilerplate_lines_go_and_copies_stay(spark):
    own = lambda i, n: " ".join(f"w{i}_{k}" for k in range(n))
    rows = [(i, f"Subscribe to our weekly letter\n{own(i, 30)}\n{own(-i, 30)}", "s") for i in range(1, 31)]
    rows += [(100 + i, "\n".join(own(9999 + k, 20) for k in range(5)), "s") for i in range(30)]  # copies of one text
    rows += [(200, "Subscribe to our weekly letter\n" * 40 + own(77, 20), "s")]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    kept = {r.doc_id: r.text for r in rules.filter_quality(df, limit=20).collect()}
    assert set(kept) == {*range(1, 31), *range(100, 130)} and "Subscribe" not in kept[3] and kept[100] == rows[30][1]


def test_lines_that_travel_together_count_every_document(spark):
    own = lambda i, n: " ".join(f"w{i}_{k}" for k in range(n))
    menu = [own(f"m{k}", 6) for k in range(10)]
    rows = [(i, "\n".join([*menu, own(f"a{i}", 30), own(f"b{i}", 30)]), "s") for i in range(150)]
    rows += [(1000 + i, "\n".join(own(9999 + k, 20) for k in range(5)), "s") for i in range(150)]  # copies of one text
    kept = {r.doc_id: r.text for r in rules.filter_quality(spark.createDataFrame(rows, "doc_id long, text string, source string"), limit=100).collect()}
    assert len(kept) == 300 and kept[1000] == rows[150][1]
    assert all(kept[i] == f"{own(f'a{i}', 30)}\n{own(f'b{i}', 30)}" for i in range(150))


@pytest.mark.parametrize("shared", [1, 2, 4, 8])
def test_every_shared_line_goes_however_many_travel(spark, shared):
    own = lambda i, n: " ".join(f"w{i}_{k}" for k in range(n))
    menu = [own(f"m{k}", 4) for k in range(shared)]
    rows = [(i, "\n".join([*menu, own(i, 80)]), "s") for i in range(60)]
    verdict, gone = rules.judged(spark.createDataFrame(rows, "doc_id long, text string, source string"))
    assert gone.count() == 60 * shared and verdict.filter("kept").count() == 60


def test_lines_go_from_the_given_tables(spark):
    """At production parameters, line by line as a plain count says; few documents hang on it."""
    docs = spark.read.parquet("/root/testdata/sf0.1/documents.parquet")
    seen, sizes = collections.defaultdict(set), collections.defaultdict(set)
    norm = lambda line: " ".join(WORD.findall(line.translate(LOWER)))
    texts = [(r.doc_id, r.source or "", r.text or "") for r in docs.select("doc_id", "source", "text").collect()]
    for _, host, t in texts:
        if whole := norm(t):
            sizes[host].add(whole)
            for line in t.split("\n"):
                if norm(line):
                    seen[host, norm(line)].add(whole)
    often = {k for k, v in seen.items() if len(v) > max(rules.FLOOR, rules.SHARE * len(sizes[k[0]]))}
    want = {(d, i) for d, host, t in texts for i, line in enumerate(t.split("\n")) if (host, norm(line)) in often}
    got = {(r.k1, r.line_no) for r in rules.judged(docs)[1].collect()}
    assert got == want and len(got) > 100


def test_line_limit_follows_the_host(spark):
    own = lambda i, n: " ".join(f"w{i}_{k}" for k in range(n))
    rows = [(i, ("all rights are kept by us\n" if i < 20 else "") + own(i, 60), "small") for i in range(60)]
    rows += [(1000 + i, ("it was a good day\n" if i < 120 else "sign up for news\n" if i < 400 else "") + own(1000 + i, 60), "large") for i in range(3000)]
    kept = {r.doc_id: r.text for r in rules.filter_quality(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()}
    assert kept == {i: t if t.startswith(("w", "it")) else t.split("\n")[1] for i, t, _ in rows}


# 10


def test_store_compacts_and_commits_versions(spark, messy):
    store = sharding.ShardStore(spark, Scratch(spark, "store").root, messy.schema, fanout=3, target=1 << 20)
    for _ in range(7):
        store.append(messy)
    assert store.version() == 7 and len(store.runs()) == 7
    before = store.runs(7)
    version = store.compact()
    assert version > 7 and len(store.runs()) < 7 and store.read().count() == 70
    assert sorted(r.text or "" for r in store.read().collect()) == sorted([r.text or "" for r in messy.collect()] * 7)
    with pytest.raises(sharding.Conflict):
        store._commit(version, before)
    store.append(messy.limit(0))
    assert store.read().count() == 70


def test_empty_store(spark, messy):
    store = sharding.ShardStore(spark, Scratch(spark, "store").root, messy.schema)
    assert store.version() == 0 and store.read().count() == 0 and store.compact() == 0


def test_documents_pass_through_versions_and_tiers(spark):
    store = sharding.sharded(spark, "/root/testdata/sf0.01")
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    assert store.version() == 3 and len(store.runs()) == 1  # 16 arrivals, 4 runs, 1 run
    assert store.runs()[0].files == 1 and not store.runs()[0].path.count("=")
    assert store.read().exceptAll(docs).count() == 0 and docs.exceptAll(store.read()).count() == 0


def test_vacuum_spares_readers_and_clears_what_died(spark, messy):
    rows = messy.withColumn("_arrival", F.lit("own"))
    store = sharding.ShardStore(spark, Scratch(spark, "store").root, rows.schema, fanout=2, target=1 << 20)
    store.append(rows, F.coalesce(F.col("doc_id") % 2, F.lit(9)))
    assert store.read().filter("_arrival = 'own'").count() == 10 and len(store.runs()) == 3
    rows.write.parquet(f"{store.root}/data/died")  # a writer that never committed
    old = store.read()
    version = store.compact()
    assert version > 1 and old.count() == 10  # a reader of the version before still reads
    assert store.vacuum(2) == [] and old.count() == 10  # all within the grace period
    gone = store.vacuum(1, grace_s=-5)
    assert any(p.endswith("died") for p in gone) and store.read().count() == 10 and store.version() == version


def test_store_under_a_path_without_scheme(spark, tmp_path):
    rows = spark.range(64).repartition(1)
    store = sharding.ShardStore(spark, str(tmp_path / "plain"), rows.schema, fanout=2, target=1 << 20)
    store.append(rows, F.col("id") % 8)
    store.compact(keep=1, grace_s=-5)  # 8 arrivals, 4, 2, 1 run: each round reads what the one before merged
    assert len(store.runs()) == 1 and store.read().distinct().count() == 64


def test_context_sums_travel_as_bytes_and_are_exact(spark):
    rows = spark.createDataFrame([(1, "a b " * 300 + "c d e"), (2, None), (3, "c d")], "doc_id long, text string")
    made = quality.context_sums(rows)
    assert "REPARTITION_BY_COL" in made._jdf.queryExecution().executedPlan().toString()  # nothing is summed into wide rows before
    got = {r["slot"]: r for r in made.collect()}
    words = [t.split() for t in ("a b " * 300 + "c d e", "c d")]
    from patchflow.llm.textkernel import Words

    h = {w: Words([w.encode()], lower=True).hash for w in "abcde"}
    place = {w: quality.index_vectors(x) for w, x in h.items()}
    want = {w: [0.0] * quality.WIDTH for w in "abcde"}
    for t in words:
        for i, w in enumerate(t):
            for j in range(max(0, i - 2), min(len(t), i + 3)):
                if i != j:
                    for p, s in zip(place[t[j]][0][0], place[t[j]][1][0]):
                        want[w][p] += s
    assert max(map(abs, want["a"])) > 127 and len(got) == 5
    for w, x in want.items():
        row = got[int(quality.slots(h[w])[0])]
        assert [row[f"c{i}"] for i in range(quality.WIDTH)] == x and row["n"] == sum(t.count(w) for t in words)
