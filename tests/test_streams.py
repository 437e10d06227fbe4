"""Streams: restart, timers of silent sequences, late rows, the rulebook's families."""

import datetime as dt

from pyspark.sql import functions as F

from patchflow.operators import captions
from patchflow.streaming import flows

DAY = dt.datetime(2024, 1, 1)


def _write(spark, path, rows):
    spark.createDataFrame([(v, DAY + dt.timedelta(hours=h)) for v, h in rows], "video_id long, ts timestamp").coalesce(1).write.mode("append").parquet(path)


def _stream(spark, path, delay="1 hour"):
    return spark.readStream.schema("video_id long, ts timestamp").parquet(path).withWatermark("ts", delay)


def test_restart_goes_on_where_it_stopped(spark, tmp_path):
    src, out, state = (f"file://{tmp_path}/{n}" for n in ("in", "out", "state"))
    _write(spark, src, [(1, 0), (2, 1)])
    flows.to_files(_stream(spark, src), out, state)
    _write(spark, src, [(3, 2)])
    flows.to_files(_stream(spark, src), out, state)  # same checkpoint: only the new file is read
    flows.to_files(_stream(spark, src), out, state)
    assert sorted(r.video_id for r in spark.read.parquet(out).collect()) == [1, 2, 3]


def test_silent_sequence_is_told_once(spark, tmp_path):
    src, out, state = (f"file://{tmp_path}/{n}" for n in ("in", "out", "state"))
    for rows in ([(1, 0), (2, 0), (1, 1)], [(2, 9)], [(2, 12)], [(2, 14)]):
        _write(spark, src, rows)
        flows.to_files(flows.silent_sequences(_stream(spark, src), 4 * 3600), out, state)
    got = [(r.video_id, r.n) for r in spark.read.parquet(out).collect()]
    assert got.count((1, 2)) == 1 and (2, 1) in got and len(got) == 2


def test_late_rows_are_counted(spark):
    b = spark.createDataFrame([(0, 10), (1, 2), (1, 9), (1, 20), (2, 11)], "batch_no int, h int").select("batch_no", F.expr("timestamp'2024-01-01' + make_dt_interval(0, h)").alias("ts"))
    assert {(r.batch_no, r.late, r.n) for r in flows.late_rows(b, 2 * 3600).collect()} == {(0, 0, 1), (1, 1, 3), (2, 1, 1)}


def test_rate_source_shape(spark):
    r = flows.rate_tiles(spark, 10)
    assert r.isStreaming and r.columns == ["clip_id", "timestamp", "row", "col", "residual"]


def test_each_family_fires_alone(spark):
    book = {"absence": ("without",), "affect": ("lovely",), "effect": ("making",), "hedge": ("maybe",), "inference": ("suggests",), "summary": ("overall",)}
    long = "the boat lies at the old pier"
    cases = {k: f"{long} {v[0]} rope" for k, v in book.items()}
    cases |= {"opener": "this boat lies at the old pier", "restated": f"{long}. {long}.", "short_run": f"{long}. a b. c d. e f.", "markup": f"**{long}**", "paragraphs": f"{long}\n\n{long} again"}
    rows = [(i, t) for i, t in enumerate(cases.values())] + [(98, long), (99, None)]
    got = {r.sample_id: set(r.violations) for r in captions.lint_rulebook(spark.createDataFrame(rows, "sample_id long, text string"), book, ("this",)).collect()}
    assert got == {**{i: {k} for i, k in enumerate(cases)}, 98: set(), 99: set()}
