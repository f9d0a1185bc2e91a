"""Cost and accuracy measures; each gives rows (graph, method, config, metric, value)."""

from __future__ import annotations

import threading
import time
import uuid
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathsieve.functions import masks as M
from pathsieve.loop import cut
from pathsieve.operators.graph import Graph, closure_components, closure_vertices
from pathsieve.plans.index import TwoAxisIndex
from pathsieve.plans.point import PointGraph

_KIND = "graph string, method string, config string, metric string, value double"


def rows(spark: SparkSession, graph: str, method: str, config: str, **values: float) -> DataFrame:
    return spark.createDataFrame([(graph, method, config, k, float(v)) for k, v in values.items()], _KIND)


def index_time(spark: SparkSession, graph: str, method: str, config: str, build: Callable[[], object]) -> tuple[object, DataFrame]:
    """Runs a build, which must write its tables, and clocks it."""
    t = time.time()
    made = build()
    return made, rows(spark, graph, method, config, build_s=time.time() - t)


def index_space(index: TwoAxisIndex | PointGraph) -> float:
    """Logical MB of an index, in tables or arrays: 8 bytes for each mask word and interval number of every table that a search reads."""
    if isinstance(index, PointGraph):
        return index.index.nbytes / 1e6
    v, words = len(index.cfg.vw), len(index.cfg.vw) + len(index.cfg.lw)
    total = (index.wide.count() + index.near.count() + index.out.count()) * words + (index.inbound.count() + index.own.count()) * v
    return 8 * (total + index.interval.count() * 3 + index.ways.count()) / 1e6


def stored_space(spark: SparkSession, path: str) -> float:
    """MB of the files under a path, such as a saved index."""
    target = spark._jvm.org.apache.hadoop.fs.Path(path)
    return target.getFileSystem(spark._jsc.hadoopConfiguration()).getContentSummary(target).getLength() / 1e6


def query_time(spark: SparkSession, graph: str, method: str, config: str, run: Callable[[DataFrame], DataFrame], queries: DataFrame) -> DataFrame:
    """Seconds of a set, of true and of false queries apart (queries with ``truth``), and wrong answers.

    A few queries are asked before the clock starts, so that what is sent to the tasks once is not part of the time.
    """
    values = {}
    for truth in (True, False):
        part = queries.where(F.col("truth") == truth)
        part = cut(part.drop("truth"), "part")
        n = part.count()
        run(part.limit(64)).collect()
        t = time.time()
        wrong = run(part).where(F.col("answer") != truth).count()
        name = str(truth).lower()
        values |= {f"{name}_s": time.time() - t, f"{name}_n": n, f"{name}_wrong": wrong}
    return rows(spark, graph, method, config, **values, mean_s=(values["true_s"] + values["false_s"]) / 2)


def capped(spark: SparkSession, build: Callable[[], object], seconds: float) -> tuple[str, object]:
    """("ok", result), ("time", None) after the cap, or ("failed", error); jobs still running are cancelled."""
    tag, box = uuid.uuid4().hex, {}
    spark.addTag(tag)
    timer = threading.Timer(seconds, lambda: (box.__setitem__("late", True), spark.interruptTag(tag) if not hasattr(spark, "sparkContext") else spark.sparkContext.cancelJobsWithTag(tag)))
    timer.start()
    try:
        return "ok", build()
    except Exception as e:
        return ("time", None) if box.get("late") else ("failed", e)
    finally:
        timer.cancel()
        spark.removeTag(tag)


def ratios(results: DataFrame, ours: str, metric: str) -> DataFrame:
    """(graph, config, method, ratio): each other method's value over ours."""
    mine = results.where((F.col("method") == ours) & (F.col("metric") == metric)).select("graph", "config", F.col("value").alias("own"))
    return results.where((F.col("method") != ours) & (F.col("metric") == metric)).join(mine, ["graph", "config"]).select("graph", "config", "method", (F.col("value") / F.col("own")).alias("ratio"))


def agreement(a: DataFrame, b: DataFrame) -> float:
    """Share of queries with the same answer in both."""
    both = a.select("qid", F.col("answer").alias("x")).join(b.select("qid", F.col("answer").alias("y")), "qid", "full")
    n, same = both.agg(F.count("*"), F.count_if(F.col("x").eqNullSafe(F.col("y")))).first()
    return same / n if n else 1.0


def effort(traced: DataFrame) -> DataFrame:
    """One row of a trace: rounds, states, candidates, kept."""
    return traced.agg(F.max("round").alias("rounds"), F.sum("states").alias("states"), F.sum("candidates").alias("candidates"), F.sum("kept").alias("kept"))


def prune_rate(unpruned: DataFrame, pruned: DataFrame) -> float:
    """Share of candidate states that the filters spared."""
    a, b = effort(unpruned).first()["candidates"], effort(pruned).first()["candidates"]
    return 1 - (b or 0) / a if a else 0.0


def filter_fpr(g: Graph, index: TwoAxisIndex, sources: DataFrame) -> DataFrame:
    """(n_unreachable, n_passing, rate): of pairs (source, vertex) without a path, those that the vertex masks let pass.

    Sources are a stated, small set; each meets every vertex, as the measure is over all pairs.
    """
    sources = sources.select(F.col("vid").alias("src")).distinct()
    reached = closure_vertices(g, sources.withColumnRenamed("src", "vid")).select("src", "dst")
    vw = index.cfg.vw
    own = index.own.select(F.col("vid").alias("dst"), *[F.col(n).alias("d" + n[1:]) for n in vw])
    out = index.out.select(F.col("vid").alias("src"), *vw)
    pairs = sources.join(out, "src", "left").na.fill(0).crossJoin(own).where("src <> dst").join(reached, ["src", "dst"], "left_anti")
    passing = M.mask_contains([F.col(n) for n in vw], [F.col("d" + n[1:]) for n in vw])
    return pairs.agg(F.count("*").alias("n_unreachable"), F.count_if(passing).alias("n_passing")).withColumn("rate", F.col("n_passing") / F.greatest("n_unreachable", F.lit(1)))


def no_false_negative(g: Graph, index: TwoAxisIndex, sources: DataFrame | None = None) -> DataFrame:
    """One row with the number of reachable pairs that the masks deny: must be 0.

    Two components are tested as a whole first: what all of the first have beyond them against what any of the second has, and the same
    the other way. Only where that fails are their pairs looked at one by one.
    """
    parts, reach = closure_components(g, sources)
    vw = index.cfg.vw
    iw, dw, mw = (["i" + n[1:] for n in vw], ["d" + n[1:] for n in vw], ["m" + n[1:] for n in vw])
    zero = lambda n, to: F.coalesce(F.col(n), F.lit(0)).alias(to)
    own = index.own.select("vid", *[F.col(n).alias(d) for n, d in zip(vw, dw, strict=True)])
    every = parts.join(own, "vid", "left").join(index.out.select("vid", *vw), "vid", "left").join(index.inbound.select("vid", *iw), "vid", "left")
    every = cut(every.select("vid", "scc", *[zero(n, n) for n in (*vw, *dw, *iw)]), "masks")
    up = every if sources is None else every.join(sources.select("vid").distinct(), "vid", "left_semi")
    first = up.groupBy(F.col("scc").alias("a")).agg(*[F.bit_and(n).alias(n) for n in vw], *[F.bit_or(d).alias(m) for d, m in zip(dw, mw, strict=True)])
    second = every.groupBy(F.col("scc").alias("b")).agg(*[F.bit_or(n).alias(n) for n in dw], *[F.bit_and(n).alias(n) for n in iw])
    cs = lambda names: [F.col(n) for n in names]
    good = M.mask_contains(cs(vw), cs(dw)) & M.mask_contains(cs(iw), cs(mw))
    doubtful = cut(reach.join(first, "a").join(second, "b").where(~good).select("a", "b"), "doubtful")
    one = up.select(F.col("scc").alias("a"), *vw, *[F.col(d).alias(m) for d, m in zip(dw, mw, strict=True)])
    other = every.select(F.col("scc").alias("b"), *dw, *iw)
    return doubtful.join(one, "a").join(other, "b").agg(F.count_if(~good).alias("violations"))


def check_monotone(g: Graph, index: TwoAxisIndex) -> DataFrame:
    """One row with the number of edges along which masks shrink the wrong way: must be 0."""
    names = index.cfg.vw + index.cfg.lw
    up = index.out.select(F.col("vid").alias("src"), *[F.col(n).alias("a_" + n) for n in names])
    low = index.out.select(F.col("vid").alias("dst"), *[F.col(n).alias("b_" + n) for n in names])
    ins = ["i" + n[1:] for n in index.cfg.vw]
    i_up = index.inbound.select(F.col("vid").alias("src"), *[F.col(n).alias("c_" + n) for n in ins])
    i_low = index.inbound.select(F.col("vid").alias("dst"), *[F.col(n).alias("e_" + n) for n in ins])
    e = g.edges.select("src", "dst").distinct().join(up, "src", "left").join(low, "dst", "left").join(i_up, "src", "left").join(i_low, "dst", "left").na.fill(0)
    good = M.mask_contains([F.col("a_" + n) for n in names], [F.col("b_" + n) for n in names]) & M.mask_contains([F.col("e_" + n) for n in ins], [F.col("c_" + n) for n in ins])
    return e.agg(F.count_if(~good).alias("violations"))


def mask_fill(index: TwoAxisIndex) -> DataFrame:
    """(vertex_fill, label_fill): mean share of bits set in the wide masks."""
    bits = lambda ns: reduce(lambda a, b: a + b, [F.bit_count(n) for n in ns])
    return index.wide.agg(F.avg(bits(index.cfg.vw) / index.cfg.vertex_bits).alias("vertex_fill"), F.avg(bits(index.cfg.lw) / index.cfg.label_bits).alias("label_fill"))


def collisions(g: Graph, index: TwoAxisIndex) -> DataFrame:
    """(bucket size profile) vertices that share their own mask with others."""
    return index.own.groupBy(*index.cfg.vw).agg(F.count("*").alias("n")).agg(F.count("*").alias("masks"), F.max("n").alias("largest"), F.avg("n").alias("mean"))


def way_profile(index: TwoAxisIndex) -> DataFrame:
    """(n_vertices, mean_ways, median_ways, max_ways)."""
    per = index.wide.groupBy("vid").agg(F.count("*").alias("n"))
    return per.agg(F.count("*").alias("n_vertices"), F.avg("n").alias("mean_ways"), F.expr("percentile_approx(n, 0.5)").alias("median_ways"), F.max("n").alias("max_ways"))


def trend(results: DataFrame, x: str, metric: str) -> DataFrame:
    """(method, slope, corr) of a metric over a numeric column of the results, e.g. degree or labels."""
    return results.where(F.col("metric") == metric).groupBy("method").agg(F.regr_slope("value", x).alias("slope"), F.corr("value", x).alias("corr"))
