"""Short events, attention pooling, supplementation and Python functions by hand, and on empty input."""

import math

import pandas as pd
from pyspark.sql import functions as F

from patchflow.functions import measures, pyfuncs
from patchflow.operators import balance, cluster, select


def test_short_events_stand_alone(spark):
    facts = spark.createDataFrame([(1, 3, 0, 0), (1, 3, 0, 0), (1, 5, 0, 0), (1, 6, 0, 0), (1, 3, 0, 1), (2, 4, 0, 0)], "clip_id long, frame_idx int, row int, col int")
    short = measures.short_events(facts)
    assert {tuple(r) for r in short.collect()} == {(1, 3, 0, 0), (1, 3, 0, 1), (2, 4, 0, 0)}
    hits = {"third": F.col("frame_idx") == 3, "none": F.lit(None).cast("boolean")}
    assert tuple(measures.event_recall(short, hits).first()) == (3, round(2 / 3, 6), 0.0)
    assert tuple(measures.event_recall(short.limit(0), hits).first()) == (0, None, None)


def test_uniform_indices_equal_the_table(spark):
    clips = spark.createDataFrame([(1,)], "clip_id long")
    for n, frames in ((1, 1), (4, 64), (5, 7), (9, 3)):
        got = [r.frame_idx for r in select.uniform_frames(clips, n, frames).orderBy("i").collect()]
        assert got == select.uniform_indices(n, frames)


def test_attentive_pool_weighs_by_softmax(spark):
    tokens = spark.createDataFrame([(1, [1.0, 0.0]), (1, [0.0, 1.0]), (2, [0.6, 0.8])], "clip_id long, x array<double>")
    query = spark.createDataFrame([([1.0, 0.0],)], "query array<double>")
    got = {(r.clip_id, r.dim): r.v for r in cluster.attentive_pool(tokens, query, 0.5).collect()}
    first = math.exp(2) / (math.exp(2) + 1)
    assert all(math.isclose(got[k], v) for k, v in {(1, 0): first, (1, 1): 1 - first, (2, 0): 0.6, (2, 1): 0.8}.items())
    assert cluster.attentive_pool(tokens.limit(0), query).count() == 0


def test_supplement_draws_unused_rows_of_weak_domains(spark):
    pool = spark.createDataFrame([(i, "ab"[i % 2]) for i in range(20)] + [(99, None)], "sample_id long, domain string")
    scores = spark.createDataFrame([("a", 0.2), ("b", 0.9), (None, 0.1)], "domain string, score double")
    used = F.col("sample_id") < 10
    got = {tuple(r) for r in balance.supplement(pool, scores, 0.5, 3, used).collect()}
    assert len(got) == 3 and all(i >= 10 and dom == "a" for i, dom in got)
    assert balance.supplement(pool, scores, 0.5, 100, used).count() == 5
    assert balance.supplement(pool.limit(0), scores, 0.5, 3, used).count() == 0


def test_python_functions():
    assert list(pyfuncs.Shingles().eval("a b\nc", 2)) == [(0, "a b"), (1, "b c")]
    assert list(pyfuncs.Shingles().eval(None, 2)) == list(pyfuncs.Shingles().eval("a", 2)) == []
    level, p, n = (pd.Series(x) for x in ([1, 9], [1, 1], [3, 1]))
    assert math.isclose(pyfuncs.ap_of_levels(level, p, n), 0.5 + 0.5 * 2 / 4)
    assert pyfuncs.ap_of_levels(level, p * 0, n) is None
    a = pd.DataFrame({"frame_idx": [0, 1], "row": [0, 0], "col": [0, 0]})
    assert pyfuncs.agreement((7,), a, a.iloc[:1]).iloc[0].tolist() == [7, 2, 1, 1, 0.5]
    assert pyfuncs.agreement((7,), a.iloc[:0], a).iloc[0].tolist() == [7, 0, 2, 0, 0.0]


def test_pareto_of_all_sizes(spark):
    from patchflow.workloads import surface

    d = "/root/testdata/sf0.01"
    rows = [(r.p_partkey, r.p_size, r.p_retailprice) for r in spark.read.parquet(f"{d}/part.parquet").collect()]
    want = {k for k, size, price in rows if not any(z <= size and p > price for _, z, p in rows)}
    got = [r.p_partkey for r in surface.QUERIES["join_theta_pareto_all_sizes"](spark, d).collect()]
    assert set(got) == want and len(got) == len(want) > 3
