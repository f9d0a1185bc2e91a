"""Helpers of iterative jobs: cutting lineage on shared storage."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from contextvars import ContextVar

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

_UNSET_DIR = "/tmp/checkpoints"


def scratch_dir(spark: SparkSession) -> str:
    """Folder that driver and executors share.

    ``spark.checkpoint.dir`` of the session names it. Only where that is unset, as in local
    tests, a folder of our own is used.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    return f"{(base or _UNSET_DIR).rstrip('/')}/pathsieve"


def new_path(spark: SparkSession, name: str = "cut") -> str:
    """A fresh path under :func:`scratch_dir`."""
    return f"{scratch_dir(spark)}/{name}-{uuid.uuid4().hex}"


def remove(spark: SparkSession, path: str) -> None:
    """Delete a path in whatever file system it lies."""
    hadoop = spark._jvm.org.apache.hadoop.fs
    target = hadoop.Path(path)
    target.getFileSystem(spark._jsc.hadoopConfiguration()).delete(target, True)


class Scratch:
    """Tables written within one job; those not kept are removed at its end."""

    def __init__(self) -> None:
        self.made: list[tuple[DataFrame | None, str]] = []
        self.kept: set[str] = set()

    def keep(self, *tables: DataFrame) -> DataFrame:
        """Name tables made by :func:`cut` that the job's result reads; returns the first."""
        self.kept |= {path for table, path in self.made for t in tables if t is table}
        return tables[0]


_scratch: ContextVar[Scratch | None] = ContextVar("scratch", default=None)


@contextmanager
def scratch(spark: SparkSession) -> Iterator[Scratch]:
    """Remove the tables that the block wrote with :func:`cut`, but for those it keeps.

    Scopes nest: what an inner one keeps belongs to the outer one, which removes it in turn unless its own
    result was written anew. Without any scope, tables stay until the scratch folder is cleared.
    """
    outer, here = _scratch.get(), Scratch()
    token = _scratch.set(here)
    try:
        yield here
    finally:
        _scratch.reset(token)
        for table, path in here.made:
            if path not in here.kept:
                remove(spark, path)
            elif outer is not None:
                outer.made.append((table, path))


def cut(df: DataFrame, name: str = "cut") -> DataFrame:
    """Write ``df`` as Parquet on shared storage and return the table that was written.

    Later plans start from files that survive the loss of any executor, so no lineage is
    recomputed, and the optimizer sees true sizes.
    """
    return cut_with_path(df, name)[0]


def cut_with_path(df: DataFrame, name: str = "cut") -> tuple[DataFrame, str]:
    """As :func:`cut`, and the path, for tables that a loop removes once they are replaced."""
    spark = df.sparkSession
    path = new_path(spark, name)
    df.write.parquet(path)
    made = spark.read.schema(df.schema).parquet(path)
    if (open_scope := _scratch.get()) is not None:
        open_scope.made.append((made, path))
    return made, path


def cut_counted(df: DataFrame, name: str = "cut", condition: Column | None = None) -> tuple[DataFrame, str, int]:
    """As :func:`cut_with_path`, and the rows (that meet ``condition``) counted while they are written.

    Tasks that ran again may be counted twice, so the number serves to tell whether there are any.
    """
    counted = Observation()
    rows = F.count("*") if condition is None else F.count_if(condition)
    made, path = cut_with_path(df.observe(counted, rows.alias("n")), name)
    return made, path, counted.get.get("n") or 0


class Layers:
    """Rows of a loop, one layer a round, each written once; all layers together are read as one scan."""

    def __init__(self, first: DataFrame, name: str = "layer") -> None:
        self.spark, self.schema, self.name = first.sparkSession, first.schema, name
        self.paths: list[str] = []
        self.last, path = cut_with_path(first, name)
        self.paths.append(path)
        self.each = [self.last]

    def add(self, df: DataFrame) -> bool:
        """Write a round's rows as the last layer; false, and the layer is left out, where there are none."""
        made, path, n = cut_counted(df, self.name)
        if n == 0:
            remove(self.spark, path)
            return False
        self.last = made
        self.paths.append(path)
        self.each.append(made)
        return True

    @property
    def all(self) -> DataFrame:
        return self.spark.read.schema(self.schema).parquet(*self.paths)
