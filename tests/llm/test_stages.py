"""The pipeline's stages as stages: messy and empty tables, columns kept, decisions by hand."""

import corpus_pipeline
import pytest
from patchflow.llm import pii

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("number", range(5))
def test_stage_on_messy_and_empty_tables(spark, messy, nothing, number):
    name, stage = corpus_pipeline.STAGES[number]
    out = stage(spark, messy, SF)
    ids = sorted((r.doc_id for r in out.collect()), key=str)
    want = {
        "quality_rules": [1, 2, 2, 6, None],  # empty and short texts fail the base rule
        "simhash_near_dedup": [1, 3, 6, 7, None],  # 2 copies 1; texts without words are one group; the null id's text is a near copy or stays
        "benchmark_decontamination": [1, 2, 2, 3, 4, 5, 6, 7, None, None],
        "personal_data": [1, 2, 2, 3, 4, 5, 6, 7, None, None],
        "byte_bpe": [1, 2, 2, 3, 4, 5, 6, 7, None, None],
    }[name]
    if name == "simhash_near_dedup":
        assert set(ids) - {None} == set(want) - {None}
    else:
        assert ids == sorted(want, key=str)
    if number < 4:
        assert out.columns == messy.columns and all(r["_row"] == "own _row" and r["host"] == "own host" for r in out.collect())
    assert stage(spark, nothing, SF).count() == 0


def test_added_spans_have_precision_and_recall(spark):
    """Keys after a key word are found; digests, numbers and words without one are left, among the given texts."""
    key = lambda i: f"{i * 2654435761 % 2**32:08x}{i * 40503 + 977:08x}{i * 69069 % 2**32:08x}{i * 31337 + 5:08x}"
    right = [f'the service reads api_key = "{key(i)}" at start' for i in range(40)]
    wrong = [f"the build of {key(i)} passed again" for i in range(20)] + [f"a winding road to Llanfairpwllgwyngyll{'x' * i}gogerych was closed" for i in range(20)]
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    planted = spark.createDataFrame([(-1 - i, t) for i, t in enumerate(right + wrong)], "doc_id long, text string")
    got = {r.doc_id: [s for s in r.spans if not s.base] for r in pii.find_personal_data(docs.union(planted)).filter("doc_id < 0").collect()}
    hits = sum(any(s.kind == "secret" and right[i][s.start : s.end] == key(i) for s in got[-1 - i]) for i in range(40))
    false = sum(bool(got[-41 - i]) for i in range(40))
    assert hits >= 36 and hits / max(1, hits + false) >= 0.9
