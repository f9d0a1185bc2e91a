"""Edges from event streams."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout


def read_edges(spark: SparkSession, path: str, schema: str, files_per_batch: int = 1) -> DataFrame:
    """A stream of Parquet files that arrive in a folder."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def _next_edges(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    rows = pd.concat(list(frames)).sort_values(["ts", "seq"], kind="stable")
    last_ts, last_seq, last = state.get if state.exists else (None, None, None)
    src, dst, late = [], [], 0
    for ts, seq, vertex in zip(rows["ts"], rows["seq"], rows["vertex"], strict=True):
        at = (ts.value, int(seq))
        if last_ts is not None and at <= (last_ts, last_seq):
            late += 1
            continue
        if last is not None:
            src.append(last)
            dst.append(int(vertex))
        last_ts, last_seq, last = at[0], at[1], int(vertex)
    state.update((last_ts, last_seq, last))
    n = len(src)
    yield pd.DataFrame({"src": src + [None] * (late > 0), "dst": dst + [None] * (late > 0), "label": [key[0]] * (n + (late > 0)), "late": [0] * n + [late] * (late > 0)}).astype({"src": "Int64", "dst": "Int64", "late": "int64"})


def chained_edges(events: DataFrame, key: str, vertex: str, ts: str, seq: str) -> DataFrame:
    """(src, dst, label, late) from a stream: each event's vertex to that of the next event with the same key, by (ts, seq).

    Works on batches in any split. The last vertex of a key is its state. An event at or before the state's place comes too late:
    it makes no edge, and a row with null ends counts it. One key's events of a batch meet in one task.
    """
    rows = events.select(F.col(key).cast("string").alias("key"), F.col(vertex).cast("long").alias("vertex"), F.col(ts).alias("ts"), F.col(seq).cast("long").alias("seq"))
    return rows.groupBy("key").applyInPandasWithState(_next_edges, "src long, dst long, label string, late long", "ts long, seq long, vertex long", "append", GroupStateTimeout.NoTimeout)


def distinct_edges(edges: DataFrame, ts: str, delay: str = "1 hour") -> DataFrame:
    """The stream's edges without repeats within the watermark."""
    return edges.withWatermark(ts, delay).dropDuplicatesWithinWatermark(["src", "dst", "label"])


def windowed_counts(events: DataFrame, ts: str, label: str, width: str = "1 day", slide: str | None = None, delay: str = "1 hour") -> DataFrame:
    """(start, label, n) per tumbling or sliding window; rows later than the watermark are dropped by the engine."""
    w = F.window(ts, width, slide) if slide else F.window(ts, width)
    return events.withWatermark(ts, delay).groupBy(w.alias("w"), F.col(label).alias("label")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "label", "n")


def session_counts(events: DataFrame, ts: str, key: str, gap: str = "30 minutes", delay: str = "1 hour") -> DataFrame:
    """(key, start, end, n) per session of a key."""
    return events.withWatermark(ts, delay).groupBy(F.session_window(ts, gap).alias("w"), F.col(key).alias("key")).agg(F.count("*").alias("n")).select("key", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def late_edges(events: DataFrame, ts: str, seq: str, delay: str = "1 hour") -> DataFrame:
    """(n_events, n_late) of a table read in order of ``seq``: events older than the newest before them by more than ``delay``.

    The running maximum is per range of ``seq`` and then across ranges, one row a range.
    """
    from pyspark.sql import Window

    from pathsieve.loop import cut

    ranged = cut(events.select(ts, seq).repartitionByRange(seq).withColumn("part", F.spark_partition_id()), "ordered")
    tops = ranged.groupBy("part").agg(F.max(ts).alias("top")).withColumn("before", F.max("top").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)))
    inside = F.max(ts).over(Window.partitionBy("part").orderBy(seq).rowsBetween(Window.unboundedPreceding, -1))
    seen = ranged.withColumn("own", inside).join(F.broadcast(tops.select("part", "before")), "part").withColumn("top", F.greatest("own", "before"))
    return seen.agg(F.count("*").alias("n_events"), F.count_if(F.col(ts) < F.col("top") - F.expr(f"INTERVAL {delay}")).alias("n_late"))


def joined_within(left: DataFrame, right: DataFrame, key: str, left_ts: str, right_ts: str, within: str, delay: str = "1 hour") -> DataFrame:
    """Rows of two streams with an equal key and times at most ``within`` apart; state is bounded by the watermarks."""
    a, b = left.withWatermark(left_ts, delay).alias("a"), right.withWatermark(right_ts, delay).alias("b")
    near = F.expr(f"a.{key} = b.{key} AND b.{right_ts} BETWEEN a.{left_ts} AND a.{left_ts} + INTERVAL {within}")
    return a.join(b, near)


def with_attributes(edges: DataFrame, vertices: DataFrame, key: str = "vid") -> DataFrame:
    """A stream of edges with a static table's columns of the source vertex."""
    return edges.join(vertices.withColumnRenamed(key, "src"), "src", "left")
