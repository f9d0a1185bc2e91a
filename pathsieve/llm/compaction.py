"""Sharding by size-tiered compaction with versioned manifests, in DataFrame operations only."""

from __future__ import annotations

import math
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

TARGET_BYTES, FANOUT, LEAST_RUN, ARRIVALS, ATTEMPTS = 128 << 20, 4, 2, 4, 20
_MANIFEST = "path string, bytes bigint, tier int, since bigint"


class CommitConflict(RuntimeError):
    """Another writer committed the version first."""


class ShardStore:
    """Immutable Parquet shards under ``root`` and a manifest for each version.

    ``data/<batch>/`` holds shard files, which are never changed; ``manifest/v<20 digits>`` lists a version's live
    shards. A version comes into being by renaming a finished manifest folder to a name that must not
    exist yet, so readers see all of a commit or nothing, and of two writers one fails and can try again. A writer leaves
    ``open/<batch>`` from before its first file until after its commit, so that no vacuum takes files that are about to be listed.
    """

    def __init__(self, spark: SparkSession, root: str, target_bytes: int = TARGET_BYTES, fanout: int = FANOUT, least_run: int = LEAST_RUN) -> None:
        if target_bytes < 1 or fanout < 2 or least_run < 2:
            raise ValueError("target_bytes must be positive, fanout and least_run at least 2")
        self.spark, self.root, self.target, self.fanout, self.least = spark, root.rstrip("/"), target_bytes, fanout, least_run

    def _fs(self, path: str):
        hadoop = self.spark._jvm.org.apache.hadoop.fs
        target = hadoop.Path(path)
        return target, target.getFileSystem(self.spark._jsc.hadoopConfiguration())

    def version(self) -> int:
        """The latest committed version; 0 for none."""
        path, fs = self._fs(f"{self.root}/manifest")
        if not fs.exists(path):
            return 0
        return max((int(s.getPath().getName()[1:]) for s in fs.listStatus(path) if s.getPath().getName()[:1] == "v"), default=0)

    def manifest(self, version: int | None = None) -> DataFrame:
        """Live shards of a version: path, bytes, tier, since."""
        version = self.version() if version is None else version
        if version == 0:
            return self.spark.createDataFrame([], _MANIFEST)
        return self.spark.read.schema(_MANIFEST).parquet(f"{self.root}/manifest/v{version:020d}")

    def _commit(self, shards: DataFrame, base: int) -> int:
        """Make ``shards`` the version after ``base``."""
        made = f"{self.root}/manifest/.new-{uuid.uuid4().hex}"
        shards.coalesce(1 + base // 1_000_000).write.parquet(made)
        fs = self.spark._jvm.org.apache.hadoop.fs
        source, store = self._fs(made)
        target = fs.Path(f"{self.root}/manifest/v{base + 1:020d}")
        none = self.spark._jvm.java.lang.reflect.Array.newInstance(fs.Options.Rename.NONE.getClass(), 1)
        none[0] = fs.Options.Rename.NONE
        try:
            if store.exists(target):
                raise CommitConflict(f"version {base + 1} exists")
            fs.FileContext.getFileContext(source.toUri(), self.spark._jsc.hadoopConfiguration()).rename(source, target, none)
        except Exception as e:
            store.delete(source, True)
            if isinstance(e, CommitConflict) or "FileAlreadyExists" in str(e):
                raise CommitConflict(f"version {base + 1} exists") from e
            raise
        return base + 1

    def tier(self, size: Column) -> Column:
        """0 for shards up to target/fanout**8 and one more for each factor of fanout; full ones get no higher."""
        ratio = F.greatest(size.cast("double"), F.lit(1.0)) * self.fanout**8 / self.target
        return F.least(F.greatest(F.ceil(F.log(ratio) / math.log(self.fanout)), F.lit(0)), F.lit(8)).cast("int")

    def _files(self, folders: list[str], version: int) -> DataFrame:
        """Manifest rows of the files in new folders, from the file system's listing."""
        rows = []
        for folder in folders:
            path, fs = self._fs(folder)
            files = fs.listStatus(path) if fs.exists(path) else []
            rows += [(s.getPath().toString(), int(s.getLen())) for s in files if s.getPath().getName().endswith(".parquet")]
        listed = self.spark.createDataFrame(rows, "path string, bytes bigint")
        return listed.select("path", "bytes", self.tier(F.col("bytes")).alias("tier"), F.lit(version).cast("long").alias("since"))

    def _opened(self) -> str:
        """A new batch, marked as being written."""
        batch = uuid.uuid4().hex
        path, fs = self._fs(f"{self.root}/open/{batch}")
        fs.create(path).close()
        return batch

    def _closed(self, batch: str, keep: bool) -> None:
        """Take the mark off; without ``keep``, the batch's files go first."""
        if not keep:
            path, fs = self._fs(f"{self.root}/data/{batch}")
            fs.delete(path, True)
        path, fs = self._fs(f"{self.root}/open/{batch}")
        fs.delete(path, False)

    def append(self, rows: DataFrame) -> int:
        """Add an arrival as new immutable shards, one file for each of its partitions that has rows; returns the version.

        Another writer's commit in between is built upon, as arrivals don't depend on each other.
        """
        batch = self._opened()
        done = False
        try:
            rows.write.parquet(f"{self.root}/data/{batch}")
            for attempt in range(ATTEMPTS):
                base = self.version()
                try:
                    made = self._commit(self.manifest(base).unionByName(self._files([f"{self.root}/data/{batch}"], base + 1)), base)
                    done = True
                    return made
                except CommitConflict:
                    if attempt == ATTEMPTS - 1:
                        raise
            raise AssertionError
        finally:
            self._closed(batch, done)

    def compact(self) -> int:
        """Merge runs of similarly sized shards, tier by tier; returns the version (the same if nothing was merged).

        A tier with ``least_run`` shards or more below half the target size is read and written as files of about target size, without
        a shuffle: neighbouring partitions are only joined. Shards that are full stay as they are. Each merge leaves fewer shards.
        If another writer committed meanwhile, the merge stands as long as all shards that it replaces are still listed.
        """
        base = self.version()
        live = self.manifest(base)
        small = live.where(F.col("bytes") < self.target / 2)
        runs = small.groupBy("tier").agg(F.count("*").alias("n"), F.sum("bytes").alias("bytes")).where(F.col("n") >= self.least).orderBy("tier").collect()
        if not runs:
            return base
        merged = live.where(F.col("tier").isin([r["tier"] for r in runs]) & (F.col("bytes") < self.target / 2)).select("path")
        batches, done = [], False
        try:
            for run in runs:
                paths = [r[0] for r in small.where(F.col("tier") == run["tier"]).orderBy("path").select("path").collect()]
                batches.append(self._opened())
                self.spark.read.parquet(*paths).coalesce(max(1, round(run["bytes"] / self.target))).write.parquet(f"{self.root}/data/{batches[-1]}")
            for attempt in range(ATTEMPTS):
                try:
                    made = self._commit(live.join(merged, "path", "left_anti").unionByName(self._files([f"{self.root}/data/{b}" for b in batches], base + 1)), base)
                    done = True
                    return made
                except CommitConflict:
                    base = self.version()
                    live = self.manifest(base)
                    if attempt == ATTEMPTS - 1 or not merged.join(live, "path", "left_anti").isEmpty():
                        raise
            raise AssertionError
        finally:
            for batch in batches:
                self._closed(batch, done)

    def read(self, version: int | None = None) -> DataFrame | None:
        """All rows of a version, as of its manifest; None if it has no shard. The driver holds one path for each live shard."""
        paths = [r[0] for r in self.manifest(version).orderBy("path").select("path").collect()]
        return self.spark.read.parquet(*paths) if paths else None

    def vacuum(self) -> int:
        """Delete shards that the latest version doesn't list; returns how many. Older versions can't be read then.

        The data folders are listed first, then the open marks, then the manifest: a batch that is no longer open by the second step
        is in the manifest of the third if it was committed at all. A mark left by a dead writer keeps its files until it is removed.
        """
        folders = self._names("data")
        writing = set(self._names("open"))
        listed = [(name,) for folder in folders if folder not in writing for name in self._paths(folder)]
        if not listed:
            return 0
        dead = self.spark.createDataFrame(listed, "path string").join(self.manifest(), "path", "left_anti").collect()
        for row in dead:
            path, fs = self._fs(row["path"])
            fs.delete(path, False)
        return len(dead)

    def _names(self, folder: str) -> list[str]:
        path, fs = self._fs(f"{self.root}/{folder}")
        return [s.getPath().getName() for s in fs.listStatus(path)] if fs.exists(path) else []

    def _paths(self, batch: str) -> list[str]:
        path, fs = self._fs(f"{self.root}/data/{batch}")
        return [s.getPath().toString() for s in fs.listStatus(path) if s.getPath().getName().endswith(".parquet")]


def sharded(docs: DataFrame, root: str, target_bytes: int = TARGET_BYTES, arrivals: int = ARRIVALS) -> DataFrame:
    """Store ``docs`` as ``arrivals`` one after the other, compact after every second, and read the rows of the last version.

    Rows are dealt to arrivals by a hash of doc_id. All columns and rows stay, nulls and repeats too; a table without rows gives one
    without. A ``shard`` column names the file.
    """
    store = ShardStore(docs.sparkSession, root, target_bytes)
    for k in range(arrivals):
        store.append(docs.where(F.pmod(F.xxhash64("doc_id"), F.lit(arrivals)) == k))
        if k % 2 or k == arrivals - 1:
            while store.version() != store.compact():
                store.vacuum()
    found = store.read()
    name = "shard" if "shard" not in docs.columns else "shard_file"
    if found is None:
        return docs.limit(0).withColumn(name, F.lit(None).cast("string"))
    return found.withColumn(name, F.element_at(F.split(F.col("_metadata.file_path"), "/"), -1))
