"""Quality classifier: random-indexing word vectors and a two-layer network.

Every word (A-Z lower-cased) has a sparse random index vector, made from its hash.  Over all texts, the
context vector of a word gathers the index vectors of its neighbours up to two words away; tasks
add up their own texts and Spark sums the parts.  Context vectors stand in ``WORDS`` hash slots, so that the
table sent to the executors is 34 MB whatever the corpus; words that meet in a slot share a
vector, and the more frequent one makes most of it.  A text is pooled three ways: mean and spread of
its words' vectors, and the mean product of the vectors of neighbours, which tells prose from lists and
repetition.  Nothing else goes in.  A network of one hidden layer in numpy is fitted to a bounded sample
of labelled rows and its scores are calibrated by a temperature on rows set aside.

Labels are read only for the fit, and never for rows with crc32(doc_id) mod 3 = 1.  ``sample`` bounds
the rows of the fit: the least by hash of doc_id, found by counting hashes, so that only these come to the
driver.  Null and empty texts have zero vectors and get a score like others; very long texts are one row
of the same size.  Repeated rows get equal scores; there are no ties to break but equal hashes of ids, which
are equal ids.  Null ids are never held out and have no label.  Other columns are not read.  Without labels of both
classes the score is the share of class 1, or 0.5.  An empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, as_bytes, map_arrow, read_table, row_groups

WORDS, WIDTH, NONZERO, REACH = 1 << 18, 32, 4, 2


def index_vectors(hashes):
    """Places and signs of the nonzero entries of the words with these hashes."""
    import numpy as np

    from .textkernel import mix

    h = mix(hashes ^ np.uint64(0x2545F4914F6CDD1D))[:, None] >> (np.arange(NONZERO, dtype=np.uint64) * np.uint64(6))
    return (h & np.uint64(WIDTH - 1)).astype(np.int64), np.where(h >> np.uint64(5) & np.uint64(1), 1.0, -1.0)


def slots(hashes):
    import numpy as np

    return (hashes % np.uint64(WORDS)).astype(np.int64)


def context_sums(docs: DataFrame) -> DataFrame:
    """(slot, n, c): uses of each slot and the sum of its neighbours' index vectors."""

    def run(batches: Iterator):
        import numpy as np
        import pyarrow as pa

        from .textkernel import Words

        total, uses = np.zeros((WORDS, WIDTH), np.float32), np.zeros(WORDS, np.int64)
        for batch in batches:
            for _, texts in row_groups(as_bytes(batch.column(0))):
                words = Words(texts, lower=True)
                if not len(words.hash):
                    continue
                place, sign = index_vectors(words.hash)
                mine, local = np.unique(slots(words.hash), return_inverse=True)
                uses[mine] += np.bincount(local)
                one, two = [], []
                for d in range(1, REACH + 1):
                    same = np.flatnonzero(words.doc[d:] == words.doc[:-d])
                    one += [local[same], local[same + d]]
                    two += [same + d, same]
                one, two = np.concatenate(one), np.concatenate(two)
                found = np.zeros(len(mine) * WIDTH)
                for k in range(NONZERO):
                    found += np.bincount(one * WIDTH + place[two, k], weights=sign[two, k], minlength=len(found))
                total[mine] += found.reshape(-1, WIDTH)
        held = np.flatnonzero(uses)
        for i in range(0, len(held), 8192):
            part = held[i : i + 8192]
            c = total[part].astype(np.int64)  # the sums are whole numbers, mostly of one byte
            small = np.abs(c).max(1) < 128

            def lists(rows, kind):
                ends = np.concatenate([[0], np.cumsum(rows)]).astype(np.int32) * WIDTH
                return pa.ListArray.from_arrays(pa.array(ends), pa.array(c[rows].ravel().astype(kind)))

            yield pa.RecordBatch.from_arrays([pa.array(part), pa.array(uses[part]), lists(small, np.int8), lists(~small, np.int64)], ["slot", "n", "c", "wide"])

    parts = map_arrow(docs.select(F.col("text").cast("string").alias("text")), run, "slot long, n long, c array<byte>, wide array<long>")
    sums = [F.sum(F.coalesce(F.get("c", F.lit(i)).cast("long"), F.get("wide", F.lit(i)))).cast("float").alias(f"c{i}") for i in range(WIDTH)]
    # dealt by slot as they are: sums made before the shuffle would be 32 wide numbers a row, and a task has each slot once
    return parts.repartition("slot").groupBy("slot").agg(F.sum("n").alias("n"), *sums)


def word_vectors(docs: DataFrame):
    """WORDS x WIDTH matrix of unit context vectors, rarer slots weighing more; fixed size whatever the corpus."""
    import numpy as np

    vectors, uses = np.zeros((WORDS, WIDTH), np.float32), np.zeros(WORDS)
    made = context_sums(docs).toArrow()  # WORDS rows at most
    slot = made.column(0).to_numpy()
    uses[slot] = made.column(1).to_numpy()
    for i in range(WIDTH):
        vectors[slot, i] = made.column(2 + i).to_numpy()
    vectors /= np.maximum(uses, 1)[:, None].astype(np.float32)
    vectors -= ((vectors * uses[:, None]).sum(0) / max(uses.sum(), 1)).astype(np.float32)
    vectors /= np.maximum(np.linalg.norm(vectors, axis=1, keepdims=True), 1e-9)
    rare = 1e-3 / (1e-3 + uses / max(uses.sum(), 1))
    return (vectors * rare[:, None]).astype(np.float32)


FEATURES = 3 * WIDTH


def _features(texts: list[bytes], vectors):
    """One row per text: mean and spread of its words' vectors, and the mean product of neighbours'."""
    import numpy as np

    from .textkernel import Words

    words = Words(texts, lower=True)
    out = np.zeros((words.n, FEATURES), np.float32)
    some = np.flatnonzero(words.count)
    if len(some):
        n = words.count[some, None].astype(np.float64)
        v = vectors[slots(words.hash)]
        mean = np.add.reduceat(v, words.first[some], axis=0, dtype=np.float64) / n
        square = np.add.reduceat(v * v, words.first[some], axis=0, dtype=np.float64) / n
        beside = np.zeros_like(v)
        same = np.flatnonzero(words.doc[1:] == words.doc[:-1])
        beside[same] = v[same] * v[same + 1]
        out[some, :WIDTH] = mean
        out[some, WIDTH : 2 * WIDTH] = np.sqrt(np.maximum(square - mean * mean, 0))
        out[some, 2 * WIDTH :] = np.add.reduceat(beside, words.first[some], axis=0, dtype=np.float64) / np.maximum(n - 1, 1)
    return out


def with_features(docs: DataFrame, vectors) -> DataFrame:
    """(doc_id, x)."""
    shipped = docs.sparkSession.sparkContext.broadcast(vectors)

    def run(batches: Iterator):
        import numpy as np
        import pyarrow as pa

        for batch in batches:
            ids = batch.column(0)
            for first, texts in row_groups(as_bytes(batch.column(1))):
                x = _features(texts, shipped.value)
                flat = pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * x.shape[1]), pa.array(x.ravel()))
                yield pa.RecordBatch.from_arrays([ids.slice(first, len(texts)), flat], ["doc_id", "x"])

    return map_arrow(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), run, "doc_id long, x array<float>")


class Network:
    """Standardised inputs, one hidden layer of tanh units, a logistic output with a temperature."""

    def __init__(self, hidden: int = 24, seed: int = 7):
        self.hidden, self.seed, self.temperature = hidden, seed, 1.0

    def fit(self, x, y, epochs: int = 60, rate: float = 0.01, decay: float = 1e-4):
        import numpy as np

        rng = np.random.default_rng(self.seed)
        x, y = np.asarray(x, np.float64), np.asarray(y, np.float64)
        self.mean, self.scale = (x.mean(0), np.maximum(x.std(0), 1e-6)) if len(x) else (np.zeros(x.shape[1:] or 1), np.ones(x.shape[1:] or 1))
        self.layers = None
        share = float(y.mean()) if len(y) else 0.5
        self.constant = share
        if len(y) < 10 or share in (0.0, 1.0):
            return self
        z = self._scaled(x)
        aside = rng.random(len(y)) < 0.15
        a, b = z[~aside], y[~aside]
        d = z.shape[1]
        params = [rng.normal(0, d**-0.5, (d, self.hidden)), np.zeros(self.hidden), rng.normal(0, self.hidden**-0.5, self.hidden), np.array(np.log(share / (1 - share)))]
        first, second, t = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params], 0
        for _ in range(epochs):
            order = rng.permutation(len(b))
            for k in range(0, len(b), 128):
                i = order[k : k + 128]
                h = np.tanh(a[i] @ params[0] + params[1])
                e = (1 / (1 + np.exp(-(h @ params[2] + params[3]))) - b[i]) / len(i)
                back = np.outer(e, params[2]) * (1 - h * h)
                slopes = [a[i].T @ back + decay * params[0], back.sum(0), h.T @ e + decay * params[2], e.sum()]
                t += 1
                for j, g in enumerate(slopes):
                    first[j] = 0.9 * first[j] + 0.1 * g
                    second[j] = 0.999 * second[j] + 0.001 * g * g
                    params[j] = params[j] - rate * (first[j] / (1 - 0.9**t)) / (np.sqrt(second[j] / (1 - 0.999**t)) + 1e-8)
        self.layers = params
        if aside.sum() >= 5:
            logits, truth = self._logits(z[aside]), y[aside]
            grid = np.exp(np.linspace(-1.5, 2.5, 81))
            losses = [np.mean(np.logaddexp(0, logits / c) - truth * logits / c) for c in grid]
            self.temperature = float(grid[int(np.argmin(losses))])
        return self

    def _scaled(self, x):
        import numpy as np

        return np.clip((np.asarray(x, np.float64) - self.mean) / self.scale, -8, 8)

    def _logits(self, z):
        import numpy as np

        w, b, v, c = self.layers
        return np.tanh(z @ w + b) @ v + c

    def score(self, x):
        import numpy as np

        if self.layers is None:
            return np.full(len(x), self.constant)
        return 1 / (1 + np.exp(-np.clip(self._logits(self._scaled(x)) / self.temperature, -40, 40)))


def held_out():
    """Whether the labels of a row must not be learned from."""
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 == 1, F.lit(False))


def least_hashes(rows: DataFrame, sample: int, spare: int = 1000) -> DataFrame:
    """The rows whose hash of doc_id is among the ``sample`` least, and up to ``spare`` more, by counts of hash prefixes."""
    place = F.shiftrightunsigned(F.xxhash64("doc_id"), 1)
    low, bits, need = 0, 63, sample
    while bits:
        step = min(12, bits)
        inside = rows.select(place.alias("p")).filter((F.col("p") >= low) & (F.col("p") - low < 2**bits)) if bits < 63 else rows.select(place.alias("p"))
        counts = sorted(inside.groupBy(F.shiftright(F.col("p") - low, bits - step).alias("k")).count().collect())  # 4,096 rows at most
        if low == 0 and sum(n for _, n in counts) <= need:
            return rows
        bits -= step
        for k, n in counts:
            if n >= need:
                break
            need -= n
        low += k << bits
        if n - need <= spare:
            break
    return rows.filter(place - low < 2**bits)


def score_quality(docs: DataFrame, labels: DataFrame, label: str = "quality", sample: int = 20_000) -> DataFrame:
    """doc_id, held_out, score, predicted for each row."""
    import numpy as np

    scratch = Scratch(docs.sparkSession, "quality")
    table = scratch.save(with_features(docs, word_vectors(docs)))
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("int").alias("y")).filter(F.col("y").isin(0, 1) & F.col("doc_id").isNotNull() & ~held_out())
    chosen = table.join(least_hashes(known, sample).hint("merge"), "doc_id")
    rows = sorted(chosen.select(F.xxhash64("doc_id").alias("h"), "doc_id", "y", "x").collect())[: sample]  # about ``sample`` rows of 96 floats
    x = np.array([r["x"] for r in rows], np.float32).reshape(len(rows), FEATURES)
    shipped = docs.sparkSession.sparkContext.broadcast(Network().fit(x, [r["y"] for r in rows]))

    def run(batches: Iterator):
        import pyarrow as pa

        for batch in batches:
            if batch.num_rows:
                x = batch.column(2).flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1)
                s = shipped.value.score(x)
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(s), pa.array((s >= 0.5).astype("int32"))], ["doc_id", "held_out", "score", "predicted"])

    return map_arrow(table.select("doc_id", held_out().alias("held_out"), "x"), run, "doc_id long, held_out boolean, score double, predicted int")


def op8_quality_classifier(spark, sf_dir: str) -> DataFrame:
    return score_quality(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels"))
