"""Sharding by size-tiered compaction.

A store is a folder of immutable Parquet runs and a row of manifests, one for each version.
Arrivals are appended as small runs.  Runs of like size form a tier; when a tier holds
``fanout`` runs they are merged into files of about ``target`` bytes, and the next version of the
manifest names the new run in place of the old ones.  A version is committed by renaming a
finished file to a name that must not exist yet, so of two writers one fails and a reader
sees either the old or the new state.

``vacuum`` keeps the last versions and what they name.  All other runs go, also those of
writers that died or lost a race, once they are older than a grace period: until then they
may be the work of a writer that has not committed, or be read under an older version.
Compaction by itself deletes nothing.

Rows are copied as they are: nulls, ties, repeated rows, very long texts and columns of any
name stay.  An empty arrival adds no run, and an empty store reads as an empty table.

DataFrame functions only; the driver handles names and sizes of runs.
"""

from __future__ import annotations

import json
import math
import time
import uuid
from concurrent.futures import ThreadPoolExecutor
from dataclasses import asdict, dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Scratch, filesystem, fresh, read_table


@dataclass(frozen=True)
class Run:
    path: str
    bytes: int
    files: int


class Conflict(RuntimeError):
    """Another writer has committed this version."""


class ShardStore:
    def __init__(self, spark: SparkSession, root: str, schema, fanout: int = 4, target: int = 128 << 20):
        self.spark, self.schema, self.fanout, self.target = spark, schema, fanout, target
        self.root = self._plain(root)

    # manifests

    def _manifest(self, version: int) -> str:
        return f"{self.root}/manifest/{version:09d}.json"

    def version(self) -> int:
        fs, at = filesystem(self.spark, f"{self.root}/manifest")
        names = [s.getPath().getName() for s in fs.listStatus(at)] if fs.exists(at) else []
        return max([int(n[:9]) for n in names if len(n) == 14 and n.endswith(".json") and n[:9].isdigit()], default=0)

    def runs(self, version: int | None = None) -> list[Run]:
        version = self.version() if version is None else version
        if not version:
            return []
        fs, at = filesystem(self.spark, self._manifest(version))
        stream = fs.open(at)
        try:
            return [Run(**r) for r in json.loads(bytes(stream.readAllBytes()).decode())["runs"]]
        finally:
            stream.close()

    def _commit(self, version: int, runs: list[Run]) -> None:
        fs, draft = filesystem(self.spark, f"{self.root}/manifest/draft-{uuid.uuid4().hex}")
        out = fs.create(draft, False)
        out.write(bytearray(json.dumps({"version": version, "runs": [asdict(r) for r in runs]}).encode()))
        out.close()
        jvm = self.spark._jvm
        context = jvm.org.apache.hadoop.fs.FileContext.getFileContext(draft.toUri(), self.spark._jsc.hadoopConfiguration())
        none = self.spark.sparkContext._gateway.new_array(jvm.org.apache.hadoop.fs.Options.Rename, 0)
        try:
            context.rename(draft, jvm.org.apache.hadoop.fs.Path(self._manifest(version)), none)  # fails if the name is taken
        except Exception as e:
            fs.delete(draft, False)
            raise Conflict(f"version {version} exists") from e

    # runs

    def _described(self, path: str) -> Run | None:
        fs, at = filesystem(self.spark, path)
        sizes = [s.getLen() for s in fs.listStatus(at) if s.getPath().getName().endswith(".parquet")]
        return Run(path, sum(sizes), len(sizes)) if sizes else None

    def append(self, df: DataFrame, arrival: Column | None = None) -> int:
        """Adds the rows as a run, or as one run for each value of ``arrival``; returns the version."""
        home = f"{self.root}/data/{uuid.uuid4().hex}"
        if arrival is None:
            df.write.parquet(home)
            paths = [home]
        else:
            name = fresh("_arrival", df.columns)
            df.withColumn(name, arrival).write.partitionBy(name).parquet(home)
            fs, at = filesystem(self.spark, home)
            paths = sorted(s.getPath().toString() for s in fs.listStatus(at) if s.isDirectory())
        arrived = [r for r in map(self._described, paths) if r]
        version = self.version()
        self._commit(version + 1, self.runs(version) + arrived)
        return version + 1

    def tier(self, run: Run) -> int:
        """Runs whose sizes are within a factor of ``fanout`` share a tier; all below target / fanout**2 are in the first."""
        least = self.target / self.fanout**2
        return 0 if run.bytes < least else 1 + int(math.log(run.bytes / least, self.fanout))

    def _merge(self, runs: list[Run]) -> Run:
        home = f"{self.root}/data/{uuid.uuid4().hex}"
        files = max(1, math.ceil(sum(r.bytes for r in runs) / self.target))
        self.spark.read.schema(self.schema).parquet(*[r.path for r in runs]).coalesce(files).write.parquet(home)
        return self._described(home)

    def compact(self, keep: int | None = None, grace_s: float = 86400) -> int:
        """Merges full tiers until none is full; the groups of a round are merged side by side and committed together.

        With ``keep``, older versions and their runs are vacuumed after each commit.
        """
        while True:
            version = self.version()
            runs = self.runs(version)
            tiers: dict[int, list[Run]] = {}
            for r in runs:
                tiers.setdefault(self.tier(r), []).append(r)
            groups = [held[i : i + self.fanout] for held in tiers.values() for i in range(0, len(held) - self.fanout + 1, self.fanout)]
            if not groups:
                return version
            with ThreadPoolExecutor(8) as pool:
                merged = list(pool.map(self._merge, groups))
            gone = {r.path for g in groups for r in g}
            self._commit(version + 1, [r for r in runs if r.path not in gone] + merged)
            if keep is not None:
                self.vacuum(keep, grace_s)

    def vacuum(self, keep: int = 2, grace_s: float = 86400) -> list[str]:
        """Deletes all but the last ``keep`` manifests, and every run older than ``grace_s`` seconds that these don't name; returns the runs deleted."""
        last = self.version()
        oldest = max(1, last - keep + 1)
        alive = {self._plain(r.path) for v in range(oldest, last + 1) for r in self.runs(v)}
        fs, at = filesystem(self.spark, f"{self.root}/manifest")
        for s in fs.listStatus(at) if fs.exists(at) else []:
            name = s.getPath().getName()
            stale = s.getModificationTime() < 1000 * (time.time() - grace_s)
            if name.endswith(".json") and name[:9].isdigit() and int(name[:9]) < oldest or name.startswith("draft-") and stale:
                fs.delete(s.getPath(), False)
        _, data = filesystem(self.spark, f"{self.root}/data")
        gone = []
        for home in fs.listStatus(data) if fs.exists(data) else []:
            inside = [s for s in fs.listStatus(home.getPath()) if s.isDirectory() and "=" in s.getPath().getName()]
            for run in inside or [home]:
                if self._plain(run.getPath().toString()) not in alive and run.getModificationTime() < 1000 * (time.time() - grace_s):
                    fs.delete(run.getPath(), True)
                    gone.append(run.getPath().toString())
            if inside and not any("=" in s.getPath().getName() for s in fs.listStatus(home.getPath())):
                fs.delete(home.getPath(), True)
        return gone

    def _plain(self, path: str) -> str:
        """A path as listings write it: with its scheme, also where that is only the default one."""
        fs, at = filesystem(self.spark, path.rstrip("/"))
        return fs.makeQualified(at).toString()

    def read(self, version: int | None = None) -> DataFrame:
        runs = self.runs(version)
        if not runs:
            return self.spark.createDataFrame([], self.schema)
        return self.spark.read.schema(self.schema).parquet(*[r.path for r in runs])


def sharded(spark, sf_dir: str, arrivals: int = 16) -> ShardStore:
    """A store of all documents, dealt into arrivals by a hash of the id, appended in one go and compacted."""
    docs = read_table(spark, sf_dir, "documents")
    store = ShardStore(spark, Scratch(spark, "shards").root, docs.schema)
    store.append(docs, F.pmod(F.xxhash64("doc_id"), F.lit(arrivals)))
    store.compact(keep=1, grace_s=0)  # nobody else reads or writes this store
    return store


def op10_sharding(spark, sf_dir: str) -> DataFrame:
    """All documents as the last manifest names them: 16 arrivals, merged tier by tier."""
    return sharded(spark, sf_dir).read().select("doc_id", "lang", "source", "n_chars", F.sha2(F.col("text").cast("binary"), 256).alias("text_sha256"))


OP10_SQL = "select doc_id, lang, source, n_chars, sha256(text) as text_sha256 from documents"
