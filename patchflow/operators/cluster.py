"""Clusters over feature vectors and probes of frozen features.

Vectors are scaled to integers, so that distances and ties are the same on every engine.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def scaled(df: DataFrame, column: str = "embedding", dims: int | None = None):
    v = F.col(column) if dims is None else F.slice(column, 1, dims)
    return F.transform(v, lambda x: F.round(x.cast("double") * 1000000).cast("long"))


def squared_distance(a, b):
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0).cast("long"), lambda s, x: s + x)


def assign(features: DataFrame, centers: DataFrame, m: int = 1, keep: tuple[str, ...] = ()) -> DataFrame:
    """(sample_id, *keep, center_id, d2, rank): the m nearest centers; centers are broadcast as one row (K is a model's size), no shuffle of features.

    features: (sample_id, q); centers: (center_id, p).
    """
    gathered = centers.agg(F.array_sort(F.collect_list(F.struct("center_id", "p"))).alias("cs"))
    every = F.transform("cs", lambda c: F.struct(squared_distance(F.col("q"), c["p"]).alias("d2"), c["center_id"].alias("center_id")))
    near = F.array(F.array_min(every)) if m == 1 else F.slice(F.array_sort(every), 1, m)
    out = features.crossJoin(F.broadcast(gathered)).select("sample_id", *keep, F.posexplode(near).alias("i", "n"))
    return out.select("sample_id", *keep, "n.center_id", "n.d2", (F.col("i") + 1).alias("rank"))


def lloyd_step(features: DataFrame, centers: DataFrame) -> DataFrame:
    """(center_id, dim, total, n): integer sums of the samples of each center; one aggregate."""
    own = assign(features, centers, keep=("q",))
    return own.select("center_id", F.posexplode("q").alias("dim", "v")).groupBy("center_id", "dim").agg(F.sum("v").alias("total"), F.count("*").alias("n"))


def discrimination_loss(features: DataFrame, assigned: DataFrame, centers: DataFrame, share: float = 0.1, temperature: float = 0.1, seed: int = 42) -> DataFrame:
    """Mean loss of positives against a hashed share of the other centers (vectors of unit length).

    Centers come as one broadcast row and positives as an array of the sample, so each sample is one row throughout.
    """
    bound = int(share * 2**32)
    gathered = centers.agg(F.collect_list(F.struct("center_id", "c")).alias("cs"))
    mine = assigned.groupBy("sample_id").agg(F.collect_set("center_id").alias("own"))
    rows = features.join(mine, "sample_id").crossJoin(F.broadcast(gathered))

    def picked(c):
        hashed = F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(seed), F.col("sample_id"), c["center_id"])), 1, 8), 16, 10).cast("long")
        return F.array_contains("own", c["center_id"]) | (hashed < bound)

    def mass(c):
        dot = F.aggregate(F.zip_with("x", c["c"], lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)
        return F.struct(F.exp(dot / temperature).alias("e"), F.array_contains("own", c["center_id"]).alias("own"))

    total = lambda a: F.aggregate(a, F.lit(0.0), lambda s, m: s + m["e"])
    made = rows.select(F.transform(F.filter("cs", picked), mass).alias("m"))
    per = made.select((F.log(total(F.col("m"))) - F.log(total(F.filter("m", lambda m: m["own"])))).alias("loss"))
    return per.agg(F.count("*").alias("n"), F.round(F.avg("loss"), 6).alias("loss"))


def train_row(id_column: str, seed: int = 42):
    """md5 split: four fifths train."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(seed), id_column)), 1, 8), 16, 10).cast("long") % 100 < 80


def centroid_probe(features: DataFrame) -> DataFrame:
    """Held-out accuracy of the nearest class mean; features: (sample_id, q, label, train)."""
    means = features.filter("train").select("label", F.posexplode("q").alias("dim", "v")).groupBy("label", "dim").agg(F.round(F.avg("v")).cast("long").alias("v")).groupBy("label").agg(F.transform(F.array_sort(F.collect_list(F.struct("dim", "v"))), lambda x: x["v"]).alias("p"))
    test = features.filter("not train")
    guess = assign(test.select("sample_id", "q"), means.select(F.col("label").alias("center_id"), "p"))
    return test.join(guess, "sample_id").agg(F.count("*").alias("n"), F.count_if(F.col("label") == F.col("center_id")).alias("hits"))


def attentive_pool(tokens: DataFrame, query: DataFrame, temperature: float = 0.1) -> DataFrame:
    """(clip_id, dim, v): mean of a clip's vectors, weighted by the softmax of their product with a query.

    tokens: (clip_id, x) of unit length, so that the exponent stays in range; query: one row (query).
    """
    dot = F.aggregate(F.zip_with("x", "query", lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)
    weighed = tokens.crossJoin(F.broadcast(query)).select("clip_id", F.exp(dot / temperature).alias("w"), F.posexplode("x").alias("dim", "v"))
    return weighed.groupBy("clip_id", "dim").agg((F.sum(F.col("w") * F.col("v")) / F.sum("w")).alias("v"))
