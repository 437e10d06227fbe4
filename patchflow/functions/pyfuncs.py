"""Python functions that Spark calls by group or row, for users who plug their own in; all take bounded groups."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import functions as F


def ap_of_levels(level: pd.Series, positives: pd.Series, rows: pd.Series) -> float:
    """Average precision of one sequence from its counts by score level; none without positives."""
    t = pd.DataFrame({"s": level, "p": positives, "n": rows}).sort_values("s", ascending=False)
    total = t["p"].sum()
    return float((t["p"] / total * t["p"].cumsum() / t["n"].cumsum()).sum()) if total else None


def ap_udaf():
    return F.pandas_udf(ap_of_levels, "double")


class Shingles:
    """Table function: (pos, shingle) of every run of ``n`` words; nothing for null or shorter texts."""

    def eval(self, text: str, n: int):
        import re

        words = re.findall(r"[^ \n\t]+", text or "")
        for i in range(len(words) - n + 1):
            yield i, " ".join(words[i : i + n])


def shingles_udtf():
    return F.udtf(Shingles, returnType="pos int, shingle string")


def agreement(key, a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
    """Tiles used by two selectors on one clip; a clip's tiles are bounded by its budget."""
    left, right = (set(x[["frame_idx", "row", "col"]].itertuples(index=False, name=None)) for x in (a, b))
    shared = len(left & right)
    return pd.DataFrame({"clip_id": [key[0]], "used_a": [len(left)], "used_b": [len(right)], "shared": [shared], "jaccard": [round(shared / len(left | right), 6)]})
