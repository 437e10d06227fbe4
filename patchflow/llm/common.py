"""Shared plumbing: table access, scratch tables in the shared folder, row groups."""

from __future__ import annotations

import atexit
import contextlib
import tempfile
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from ..shipping import ship_package

#: Rows of a join's one-row-a-key side that may be broadcast, after a count.
SENT_KEYS = 1 << 16
#: Keys that may be answered apart in a merge because they hold many rows: those of at least this share of all.
HOT_SHARE, HOT_ROWS = 1024, 10_000
#: Bytes of an Arrow batch sent to a Python worker, so that long texts don't add up to more than a worker holds.
BATCH_BYTES = 4 << 20
#: Bytes of text that the numpy kernels take at a time (a longer text is taken alone).
GROUP_BYTES = 1 << 19


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share.

    ``spark.checkpoint.dir`` names it on a cluster.  Only where that setting is
    absent (a single-machine test) a temporary folder of this machine is used.
    """
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    own = spark.sparkContext.getCheckpointDir()
    if own:
        return own.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
    folder = "file://" + tempfile.mkdtemp(prefix="patchflow-")
    spark.sparkContext.setCheckpointDir(folder)
    return spark.sparkContext.getCheckpointDir().rstrip("/")


def map_arrow(df: DataFrame, run, schema) -> DataFrame:
    """mapInArrow with this package at hand on the executors, in batches of BATCH_BYTES (a longer row comes alone)."""
    spark, limit = df.sparkSession, "spark.sql.execution.arrow.maxBytesPerBatch"
    ship_package(spark)
    if int(spark.conf.get(limit).rstrip("b")) > BATCH_BYTES:
        spark.conf.set(limit, str(BATCH_BYTES))
    return df.mapInArrow(run, schema)


def filesystem(spark: SparkSession, path: str):
    jvm = spark._jvm
    at = jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark._jsc.hadoopConfiguration()), at


def delete_path(spark: SparkSession, path: str) -> None:
    fs, at = filesystem(spark, path)
    fs.delete(at, True)


class Scratch:
    """Tables written to the shared folder: they cut lineage and survive lost executors.

    A result that is read lazily needs its tables until the session ends, so what
    is not dropped earlier goes when the interpreter exits.
    """

    def __init__(self, spark: SparkSession, what: str):
        self.spark = spark
        self.root = f"{shared_dir(spark)}/{what}-{uuid.uuid4().hex}"
        self.saved = 0
        atexit.register(self.close)

    def save(self, df: DataFrame, **counted) -> DataFrame:
        """The table as read back, with ``rows``; ``counted`` names conditions whose rows are counted as it is written, in ``found``."""
        self.saved += 1
        path = f"{self.root}/t{self.saved}"
        seen = Observation()
        watched = df.observe(seen, F.count(F.lit(1)).alias("rows"), *[F.count_if(c).alias(n) for n, c in counted.items()])
        watched.write.option("compression", "zstd").parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        out._scratch_path, out.found = path, seen.get
        out.rows = out.found["rows"]
        return out

    def few(self, share: int = 8) -> int:
        """Parts of a table that is much smaller than what it is made from: a fraction of the shuffle partitions, one a core at least.

        Each part is a file, and for each file and its folder Hadoop's local file system starts a process (chmod, three times), which
        stands in the executor's whole memory until it has begun.
        """
        return max(self.spark.sparkContext.defaultParallelism, int(self.spark.conf.get("spark.sql.shuffle.partitions")) // share)

    def drop(self, *tables: DataFrame) -> None:
        for t in tables:
            delete_path(self.spark, t._scratch_path)

    def close(self) -> None:
        with contextlib.suppress(Exception):  # the JVM may have gone before
            delete_path(self.spark, self.root)


def sized_join(left: DataFrame, right: DataFrame, on: list[str], scratch: Scratch, how: str = "inner", sent: int = SENT_KEYS, rows: int | None = None) -> DataFrame:
    """``left`` joined (inner or left) with a table of one row a key; ``rows`` is its size where known.

    Up to ``sent`` rows are broadcast, after a count.  Beyond that the tables are merged by key, but for keys
    that hold 1 / HOT_SHARE of the rows of ``left`` or more: these, HOT_SHARE at most, are answered by a broadcast.
    """
    if (right.count() if rows is None else rows) <= sent:
        return left.join(F.broadcast(right), on, how)
    sizes = left.groupBy(*on).count()
    most = max(HOT_ROWS, left.count() // HOT_SHARE)
    hot = scratch.save(sizes.filter(F.col("count") >= most).select(*on))
    if not hot.rows:
        return left.join(right.hint("merge"), on, how)
    first = left.join(F.broadcast(hot), on, "left_semi").join(F.broadcast(right.join(F.broadcast(hot), on, "left_semi")), on, how)
    return left.join(F.broadcast(hot), on, "left_anti").join(right.hint("merge"), on, how).unionByName(first)


def no_null_id(column: str = "doc_id"):
    """A join key that stands in for a null id."""
    return F.coalesce(F.col(column).cast("long"), F.lit(-(2**63)))


def keyed_rows(docs: DataFrame) -> DataFrame:
    """``_row``, the whole row as a struct, so that no column of it clashes, and the key ``_k1``, ``_k2`` of id and text."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    return docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_row"), no_null_id().alias("_k1"), F.xxhash64(text).alias("_k2"))


def fresh(name: str, taken: list[str]) -> str:
    """``name``, longer where ``taken`` has it already."""
    while name.lower() in (t.lower() for t in taken):
        name += "_"
    return name


def row_groups(texts: list[bytes], most: int = GROUP_BYTES) -> Iterator[tuple[int, list[bytes]]]:
    """Consecutive texts of about ``most`` bytes together, with the index of the first."""
    first, held, size = 0, [], 0
    for i, t in enumerate(texts):
        if held and size + len(t) > most:
            yield first, held
            first, held, size = i, [], 0
        held.append(t)
        size += len(t) + 1
    if held:
        yield first, held


def as_bytes(column) -> list[bytes]:
    """UTF-8 bytes of an Arrow string column; null becomes empty."""
    import pyarrow as pa

    return [x if x is not None else b"" for x in column.cast(pa.binary()).to_pylist()]
