"""Near duplicates against plain versions on planted texts."""

import random

from patchflow.operators import neardup
from patchflow.workloads import neardups


def plain(rows, n=5, threshold=0.8):
    def grams(text):
        w = (text or "").lower().split()
        return {" ".join(w[i : i + n]) for i in range(len(w) - n + 1)} if len(w) >= n else {" ".join(w)} - {""}

    sets = {i: grams(t) for i, t in rows}
    lead = {}
    for i, t in sorted(rows):
        lead.setdefault(" ".join((t or "").lower().split()) or i, i)
    of = {i: lead[" ".join((t or "").lower().split()) or i] for i, t in rows}
    reps = sorted({r for r in of.values() if sets[r]})
    pairs = {(a, b) for a in reps for b in reps if a < b and len(sets[a] & sets[b]) >= threshold * len(sets[a] | sets[b])}
    comp = {r: r for r in of.values()}
    moved = True
    while moved:
        moved = False
        for a, b in pairs:
            low = min(comp[a], comp[b])
            moved |= comp[a] != low or comp[b] != low
            comp[a] = comp[b] = low
    return pairs, {i: (of[i], sum(of[i] in p for p in pairs), comp[of[i]]) for i, _ in rows}


def planted():
    r = random.Random(5)
    word = [f"w{i}" for i in range(400)]
    base = [r.choice(word) for _ in range(120)]
    rows = [(1, None), (2, ""), (3, "one two"), (4, "One  two"), (5, " ".join(base)), (6, " ".join(base))]
    for i in range(7, 40):  # a chain: each changes one word of the text before
        base = list(base)
        base[r.randrange(120)] = r.choice(word)
        rows.append((i, " ".join(base)))
    return rows + [(i, " ".join(r.choice(word) for _ in range(r.randrange(1, 80)))) for i in range(40, 90)]


def test_planted_near_dups(spark):
    rows = planted()
    pairs, want = plain(rows)
    df = spark.createDataFrame(rows, "sample_id long, text string")
    assert {(x.a, x.b) for x in neardup.pairs_exact(neardup.classes(df)).collect()} == pairs
    for exact in (True, False):
        got = {x.sample_id: (x.class_id, x.links, x.component_id) for x in neardup.near_duplicates(df, exact).collect()}
        assert got == want


def test_hot_bucket_meets_in_blocks(spark):
    n = neardup.BLOCK + 40
    keyed = spark.range(n).selectExpr("7L as key", "id as rep").union(spark.range(5).selectExpr("id + 100 as key", "id as rep"))
    assert neardup.meeting(keyed).count() == n * (n - 1) // 2


def test_long_chain_and_empty(spark):
    nodes = spark.range(300).withColumnRenamed("id", "rep")
    pairs = spark.range(299).selectExpr("id as a", "id + 1 as b")
    assert neardup.components(nodes, pairs).filter("component_id <> 0").count() == 0
    none = spark.createDataFrame([], "sample_id long, text string")
    assert neardup.near_duplicates(none).count() == 0


def test_queries_lose_no_link_that_bands_miss(spark, monkeypatch, tmp_path):
    rows = planted()
    spark.createDataFrame([(i, t, "en") for i, t in rows], "doc_id long, text string, lang string").write.parquet(f"{tmp_path}/documents.parquet")
    monkeypatch.setattr(neardup, "pairs_minhash", lambda sets: neardup.pairs_exact(sets).limit(0))  # bands that miss all
    monkeypatch.setattr(neardups.A, "samples", lambda s, d: s.read.parquet(f"{d}/documents.parquet").withColumnRenamed("doc_id", "sample_id"))
    _, want = plain(rows)
    got = {x.sample_id: (x.class_id, x.links, x.component_id) for x in neardups.near_dup_components_documents(spark, str(tmp_path)).collect()}
    assert got == want
    assert [x.kept for x in neardups.near_dup_kept(spark, str(tmp_path)).collect()] == [sum(i == c for i, (_, _, c) in want.items())]
