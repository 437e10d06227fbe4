"""The closed loop: edits one at a time, veto, rejected edits stay out, empty texts."""

from patchflow.operators import loop

TEXTS = [(None,), ("",), ("A cat sits on a mat. A cat sits on a mat. Go.",), ("The dog  ran very far $$$ today. Ha. Oh.",), ("It it rains over the hills. It snows a lot there.",)] * 4


def test_accepted_edits_raise_the_score(spark):
    b = spark.createDataFrame(TEXTS, "text string")
    recipe, log = loop.optimize(b, b)
    assert recipe.clock and log[0][1] == "timing"
    for _, _, before, after, low, high, verdict in log:
        assert (high > low) == (verdict == "accepted")
        assert len(set(after.split("+")) ^ set(before.split("+")) - {"none"}) == 1
    assert len({(x[2], x[3]) for x in log}) == len(log)


def test_veto_keeps_the_recipe(spark):
    b = spark.createDataFrame(TEXTS, "text string")
    recipe, log = loop.optimize(b, b, rounds=3, reviewer=lambda old, new: False)
    assert recipe == loop.Recipe() and {x[-1] for x in log} <= {"vetoed", "rejected"}


def test_apply_and_null(spark):
    b = spark.createDataFrame(TEXTS[:3], "text string")
    got = [r.text for r in loop.apply(b, loop.Recipe(("no_restated",), True)).collect()]
    assert got == [None, "[00:00] ", "[00:00] A cat sits on a mat. Go"]
    assert [r.novelty for r in loop.score(b).collect()][:2] == [0.0, 0.0]
