"""Positions, batches, budgets, windows, gates and measures by hand."""

import pytest
from pyspark.sql import functions as F

from patchflow.operators import gating, sequence

TOKEN = "clip_id long, frame_idx int, row int, col int, importance long, is_anchor boolean, rank_in_clip int"


def tokens(spark):
    rows = [(0, 0, 0, 0, 5, True, 1), (0, 0, 0, 1, 0, True, 2), (0, 3, 1, 0, 9, False, 3), (1, 0, 0, 0, 1, True, 1), (4, 2, 1, 1, 7, False, 1)]
    return spark.createDataFrame(rows, TOKEN)


def test_padding_follows_the_batch_and_the_mask_its_sequence(spark):
    got = {r.clip_id: (r.batch_idx, r.valid_len, r.pad_len, r["mask"]) for r in sequence.pack_sequences(tokens(spark), 4).collect()}
    assert got == {0: (0, 3, 3, [1, 1, 1]), 1: (0, 1, 3, [1, 0, 0]), 4: (1, 1, 1, [1])}
    cut = {r.clip_id: (r.valid_len, len(r.tokens), sum(r["mask"]), len(r["mask"])) for r in sequence.pack_sequences(tokens(spark), 4, 2).collect()}
    assert cut == {0: (2, 2, 2, 2), 1: (1, 1, 1, 2), 4: (1, 1, 1, 2)}


def test_zeros_fill_what_is_missing(spark):
    got = sequence.zero_filled(tokens(spark), 3)
    assert {r.clip_id: (r.n, r.pads, r.last) for r in got.groupBy("clip_id").agg(F.count("*").alias("n"), F.count_if("is_pad").alias("pads"), F.max("rank_in_clip").alias("last")).collect()} == {0: (3, 0, 3), 1: (3, 2, 3), 4: (3, 2, 3)}


def test_angles_turn_with_frame_row_and_column(spark):
    r = sequence.rotary(tokens(spark), (4, 2, 2), 100.0).filter("clip_id = 0 and frame_idx = 3").first()
    assert r.angles == pytest.approx([3.0, 0.3, 1.0, 0.0])


def test_windows_put_anchors_first(spark):
    r = sequence.codec_windows(tokens(spark), 16).filter("clip_id = 0").first()
    assert [tuple(x) for x in r.anchors] == [(0, 0, 0), (0, 0, 1)] and [tuple(x) for x in r.updates] == [(3, 1, 0)]


def test_bits_stop_at_the_budget(spark):
    bits = spark.createDataFrame([(0, f, 0, 0, b) for f, b in enumerate([3.0, 2.5, 2.0, 1.0])], "clip_id long, frame_idx int, row int, col int, importance double")
    assert sorted(r.frame_idx for r in sequence.bits_budget(bits, 5.5).collect()) == [0, 1]
    assert sorted(r.frame_idx for r in sequence.bits_budget(bits, 5.6).collect()) == [0, 1, 2]


def test_a_burst_is_a_cut(spark):
    imp = spark.createDataFrame([(0, f, 0, 0, 100 if f == 5 else 1) for f in range(8)], "clip_id long, frame_idx int, row int, col int, importance long")
    got = sequence.scene_cuts(imp, imp.select("clip_id").distinct(), 8, 4)
    assert sorted((r.frame_idx, r.why) for r in got.collect()) == [(0, "gop"), (4, "gop"), (5, "cut")]


def test_frames_by_rate_or_cap(spark):
    clips = spark.createDataFrame([(0,)], "clip_id long")
    assert [r.frame_idx for r in sequence.by_fps(clips, 10, 4, 1, 8).collect()] == [0, 4, 8]
    assert [r.frame_idx for r in sequence.by_fps(clips, 10, 4, 4, 5).collect()] == [1, 3, 5, 7, 9]


def test_unknown_selectors_are_refused(spark):
    with pytest.raises(KeyError):
        sequence.importance_by("none", None)
    assert {"motion", "residual", "motion_residual"} <= set(sequence.SELECTORS)


def test_area_between_curves(spark):
    curve = spark.createDataFrame([(4, 0.5, 0.25), (8, 0.75, 0.25), (16, 1.0, 1.0)], "n int, a double, b double")
    assert sequence.gain_area(curve).first().area == pytest.approx((0.375 + 0.25) / 2)


def test_mixture_error_counts_both_sides(spark):
    counts, targets = spark.createDataFrame([("a", 3), ("b", 1)], "component string, n long"), spark.createDataFrame([("a", 0.5), ("c", 0.5)], "component string, target double")
    got = {r.component: (r.n, r.error, r.worst) for r in sequence.mixture_error(counts, targets).collect()}
    assert got == {"a": (3, 0.25, 0.5), "b": (1, 0.25, 0.5), "c": (0, 0.5, 0.5)}


def gate_rows(spark):
    return spark.createDataFrame([(0, p, 10 * p, s, m) for p, (s, m) in enumerate([(0, 1), (1, 5), (0, 3), (1, 9)])], "video_id long, pos int, t_s long, speak int, memory long")


def test_a_planted_leak_is_found(spark):
    g = gate_rows(spark)
    gating.assert_causal(g, F.lag("t_s").over(gating.in_order()))
    with pytest.raises(ValueError, match="3 decisions"):
        gating.assert_causal(g, F.lead("t_s").over(gating.in_order()))


def test_history_lowers_the_chance_after_a_speak(spark):
    got = [r.p_speak for r in gating.with_history(gate_rows(spark), 2, 1.0, F.lit(0.0)).orderBy("pos").collect()]
    assert got[0] == got[1] == 0.5 and got[2] == got[3] == pytest.approx(0.268941, abs=1e-5)


def test_memory_holds_all_that_came_before(spark):
    got = [(r.held, r.most, r.since) for r in gating.accumulated(gate_rows(spark), "memory").orderBy("pos").collect()]
    assert got == [(0, 0, 1), (1, 1, 2), (6, 5, 1), (9, 5, 2)]


def test_curve_at_each_threshold(spark):
    got = {r.tau: (r.tp, r.fp, r.fn) for r in gating.threshold_curve(gate_rows(spark), "memory", [0, 4, 100]).collect()}
    assert got == {0: (2, 2, 0), 4: (2, 0, 0), 100: (0, 0, 2)}
    assert gating.argmax(F.lit(1.0), F.lit(1.0)) is not None
