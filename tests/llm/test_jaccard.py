"""The pipeline's near-duplicate stage against a plain version."""

import random
import sys

import corpus_pipeline
from patchflow.llm import jaccard


def grams(text):
    w = (text or "").lower().split()
    return {" ".join(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else {" ".join(w)} - {""}


def plain(rows):
    sets = [grams(t) for _, t in rows]
    comp = list(range(len(rows)))

    def top(i):
        while comp[i] != i:
            i = comp[i]
        return i

    for i, a in enumerate(sets):
        for j, b in enumerate(sets[:i]):
            if 5 * len(a & b) >= 4 * len(a | b):
                low, high = sorted((top(i), top(j)))
                comp[high] = low
    return [rows[i][0] for i in range(len(rows)) if top(i) == i]


def planted():
    r = random.Random(7)
    word = [f"w{i}" for i in range(600)]
    some = lambda n: [r.choice(word) for _ in range(n)]
    shared, rows = some(60), []
    for _ in range(12):  # families, some of them chains, with changes around the threshold
        base = some(r.randrange(60, 240))
        for _ in range(8):
            t = list(base)
            for _ in range(r.randrange(1, 7)):
                t[r.randrange(len(t))] = r.choice(word)
            rows.append(t)
            base = t if r.random() < 0.3 else base
    rows += [shared + some(r.randrange(5, 40)) for _ in range(60)]  # texts that are mostly one passage
    rows += [some(r.randrange(1, 80)) for _ in range(60)] + [["One", "two"], ["one", "TWO"], ["É", "x"], ["é", "x"]]
    r.shuffle(rows)
    return [(i, " ".join(t)) for i, t in enumerate(rows)] + [(1000, ""), (1001, None)]


def test_near_dedup_loses_no_link(spark, messy, nothing, monkeypatch):
    rows = planted()
    df = spark.createDataFrame(rows, "doc_id long, text string")
    want = [i for i in plain(rows) if i != 1001]  # texts without words are copies of each other
    assert sorted(r.doc_id for r in corpus_pipeline.near_dedup(spark, df, "").collect()) == want
    monkeypatch.setattr(jaccard, "SENT_KEYS", 0)
    assert sorted(r.doc_id for r in jaccard.keep_one(df).collect()) == want
    kept = jaccard.keep_one(messy)
    assert kept.columns == messy.columns and sorted(r.doc_id for r in kept.collect() if r.doc_id) == [1, 3, 6, 7]
    assert jaccard.keep_one(nothing).count() == 0


def test_parity_bits_never_differ_more_than_the_sets(spark):
    import numpy as np

    r = random.Random(5)
    sets = [{r.getrandbits(62) for _ in range(n)} for n in (0, 1, 40, 76, 5000)]
    core = sorted(sets[3])
    sets += [{*core[:i], *core[i + 10 :], *(r.getrandbits(62) for _ in range(10))} for i in range(0, 60, 3)]
    bounds = np.cumsum([0, *map(len, sets)])
    bits = jaccard.parity_words(np.array([x for s in sets for x in sorted(s)], np.int64), bounds).reshape(len(sets), -1)
    told = lambda i, j: sum(int(x).bit_count() for x in (bits[i] ^ bits[j]).view(np.uint64))
    assert all(told(i, j) <= len(sets[i] ^ sets[j]) for i in range(len(sets)) for j in range(i))
    assert 9 * told(5, 24) > len(sets[5]) + len(sets[24])  # two copies with other members in other places are told apart


def test_small_tables_are_written_by_few_tasks(spark, monkeypatch):
    """Each file starts processes that stand in an executor's whole memory, so only tables of whole sets are written by all tasks."""
    files = {}

    class Counted(jaccard.Scratch):
        def save(self, df, **counted):
            out = super().save(df, **counted)
            if sys._getframe(1).f_code.co_filename == jaccard.__file__ and "members" not in df.columns:
                files[f"{self.saved} {df.columns}"] = sum(f.rsplit("/", 1)[-1].startswith("part-") for f in out.inputFiles())
            return out

    held = {k: spark.conf.get(k) for k in ("spark.sql.shuffle.partitions", "spark.sql.adaptive.coalescePartitions.enabled")}
    monkeypatch.setattr(jaccard, "Scratch", Counted)
    rows = planted()
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(48)
    try:
        spark.conf.set("spark.sql.shuffle.partitions", "48")
        spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
        kept = sorted(r.doc_id for r in jaccard.keep_one(df).collect())
    finally:
        for k, v in held.items():
            spark.conf.set(k, v)
    assert kept == [i for i in plain(rows) if i != 1001]
    assert len(files) > 9 and max(files.values()) <= max(spark.sparkContext.defaultParallelism, 6), files
