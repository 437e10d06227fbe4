"""Hand-made cases for the methods."""

from pyspark.sql import functions as F

from patchflow.functions import measures
from patchflow.operators import curate, motion, select, timeline
from patchflow.sources import adapters as A
from patchflow.workloads import gates

SF = "/root/testdata/sf0.001"
TILE = "clip_id long, frame_idx int, row int, col int, importance long"


def test_vanishing_tile_leaves_a_change(spark):
    facts = spark.createDataFrame([(0, 3, 0, 0, 1, 500)], "clip_id long, frame_idx int, row int, col int, n long, c long")
    got = {(r.frame_idx, r.dn, r.dv) for r in A.tile_changes(facts, 64).collect()}
    assert got == {(3, 1, 500), (4, -1, -500)}


def test_tiny_budget_cuts_anchors_in_frame_order(spark):
    imp = spark.createDataFrame([(0, 1, 0, 0, 9)], TILE)
    got = select.topk_budget(imp, 5, gop=2, frames=4, grid=(2, 2)).collect()
    assert [(r.frame_idx, r.row, r.col) for r in sorted(got, key=lambda r: r.rank_in_clip)] == [(0, 0, 0), (0, 0, 1), (0, 1, 0), (0, 1, 1), (2, 0, 0)]


def test_sparse_clip_is_not_filled(spark):
    imp = spark.createDataFrame([(0, 1, 0, 0, 9), (0, 1, 0, 1, 0)], TILE)
    got = select.topk_budget(imp, 320, gop=2, frames=4, grid=(2, 2)).collect()
    assert len(got) == 9 and sum(not r.is_anchor for r in got) == 1


def test_ties_go_by_place(spark):
    imp = spark.createDataFrame([(0, f, r, c, 7) for f in (1, 3) for r in (1, 0) for c in (1, 0)], TILE)
    got = select.topk_budget(imp, 10, gop=2, frames=4, grid=(2, 2)).filter("not is_anchor").orderBy("rank_in_clip").collect()
    assert [(r.frame_idx, r.row, r.col) for r in got] == [(1, 0, 0), (1, 0, 1)]


def test_shift_is_found(spark):
    before = [10 * (i // 4) + i % 4 * 3 for i in range(16)]
    after = [before[4 * (i // 4) + max(i % 4 - 1, 0)] for i in range(16)]
    frames = spark.createDataFrame([(0, 0, 4, 4, before), (0, 1, 4, 4, after)], "clip_id long, frame_idx int, height int, width int, pixels array<int>")
    got = {(r.row, r.col): (r.mv_r, r.mv_c, r.residual) for r in motion.block_match(frames, 2).collect()}
    assert got[0, 1] == (0, -1, 0) and got[1, 1] == (0, -1, 0)


def test_published_fixture_counts(spark):
    from patchflow.workloads import tokens

    r = tokens.tokens_events(spark, "/root/testdata/sf0.01").filter("not is_anchor").agg(F.count("*"), F.sum("importance"), F.sum("frame_idx"), F.sum(F.col("row") * 10 + F.col("col"))).first()
    assert tuple(r) == (3840, 56025364, 123557, 65667)


def test_captions_that_start_together_make_one_target(spark):
    t = spark.createDataFrame([(1, 0, 0, 3, "a"), (1, 1, 5, 9, "b"), (1, 2, 5, 10, "c")], "video_id long, seg_idx int, start_s long, end_s long, caption string")
    got = timeline.to_gate(t).filter("target = 'speak'").orderBy("pos").collect()
    assert [(r.pos, r.response) for r in got] == [(0, "a"), (5, "b\nc")]
    assert timeline.to_gate(t).filter("prefix_end_s > t_s").count() == 0


def test_bad_times(spark):
    t = spark.createDataFrame([(1, 0, 5, 3), (1, 1, -1, 2), (1, 2, 1, 99), (1, 3, 0, 4)], "video_id long, seg_idx int, start_s long, end_s long")
    d = spark.createDataFrame([(1, 10)], "video_id long, duration_s long")
    assert [r.seg_idx for r in timeline.bad_times(t, d).orderBy("seg_idx").collect()] == [0, 1, 2]


def test_ranking_with_ties_by_hand(spark):
    rows = [(1, 1, 5), (1, 0, 5), (1, 1, 3), (1, 0, 2), (1, 0, 1), (1, 0, 1)]
    r = measures.ranking(spark.createDataFrame(rows, "video_id long, speak int, score long")).first()
    assert r.roc_auc == round((3.5 + 3) / 8, 6) and r.pr_auc == round(0.5 * 0.5 + 0.5 * 2 / 3, 6)


def test_all_silent_has_high_accuracy_and_no_balance(spark):
    rows = [(1, int(i < 2), 0) for i in range(100)]
    r = measures.timing(spark.createDataFrame(rows, "video_id long, speak int, fired int")).first()
    assert (r.trigger_acc, r.timing_balance, r.f1) == (0.98, 0.0, 0.0)


def test_tolerance_counts_the_near_one_only(spark):
    truth, fired = spark.createDataFrame([(1, 10), (1, 20)], "video_id long, t_s long"), spark.createDataFrame([(1, 11), (1, 22)], "video_id long, t_s long")
    assert tuple(measures.relaxed_hits(truth, fired, 1).first()) == (1, 2, 1)


def test_span_overlap(spark):
    assert abs(spark.range(1).select(measures.span_overlap(F.lit(0), F.lit(10), F.lit(5), F.lit(15))).first()[0] - 1 / 3) < 1e-9


def test_shifted_masks(spark):
    a = [(0, 0, r, c) for r in range(3) for c in range(3)]
    schema = "clip_id long, frame_idx int, row int, col int"
    got = measures.region_and_border(spark.createDataFrame(a, schema), spark.createDataFrame([(x, f, r, c + 1) for x, f, r, c in a], schema)).first()
    assert got.j == 0.5


def test_strata_edges(spark):
    s = spark.createDataFrame([(float(x),) for x in (30, 30.5, 60, 180, 181, 599, 600, 900, 901)], "d double")
    assert [r[0] for r in s.select(curate.stratum(F.col("d"))).collect()] == ["to30", "to60", "to60", "to180", "gap", "gap", "to900", "to900", "over"]


def test_live_gate_equals_batch(spark):
    live = {tuple(r) for r in gates.stream_gate_events(spark, SF).collect()}
    batch = {(r.video_id, r.pos, r.t_s, r.memory) for r in gates._fired(spark, SF).filter("fired = 1").collect()}
    assert live == batch and live


def test_uniform_recall_is_below_budgeted_importance(spark):
    from patchflow.workloads import tokens

    rows = tokens.budget_curve_events(spark, SF).orderBy("n").collect()
    assert all(a.codec <= b.codec for a, b in zip(rows, rows[1:])) and rows[2].codec > rows[2].uniform
