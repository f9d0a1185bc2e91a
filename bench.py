"""Headline timings at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

``python bench.py --table NAME`` runs a whole experiment instead and prints its rows: queries (every operator on every graph, or on those named after it), rounds, graphs, index, all, any, none, mixed,
allowed, uniform, preferential, ablation, acyclic, labels.
"""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import SparkSession


def session() -> SparkSession:
    cpus = os.environ.get("BENCH_CPUS", "8")
    builder = SparkSession.builder.master(f"local[{cpus}]").appName("bench").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "12g")
    spark = builder.config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC")
    spark = spark.config("spark.checkpoint.dir", os.environ.get("BENCH_SCRATCH", "/tmp/checkpoints")).getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def tables(spark: SparkSession, sf_dir: str) -> dict:
    from pathsieve.plans import experiments as X

    ops = {op.lower(): (lambda op=op: X.table_queries(spark, sf_dir, op)) for op in ("ALL", "ANY", "NONE", "MIXED")}

    def trends(swept):
        """The sweep's rows, then slope and correlation of each metric."""
        shown = X.check_trends(swept).selectExpr("'trend' AS graph", "method", "x AS config", "metric", "corr AS value", "slope")
        return swept.unionByName(shown, allowMissingColumns=True)

    n = spark.read.parquet(f"{sf_dir}/customer.parquet").count() + spark.read.parquet(f"{sf_dir}/part.parquet").count()
    return ops | {
        "graphs": lambda: X.table_graphs(spark, sf_dir), "index": lambda: X.table_index(spark, sf_dir), "allowed": lambda: X.table_allowed(spark, sf_dir),
        "uniform": lambda: trends(X.sweep(spark, "uniform", n)), "preferential": lambda: trends(X.sweep(spark, "preferential", n)), "ablation": lambda: X.ablation(spark, sf_dir),
        "acyclic": lambda: X.acyclic(spark, sf_dir), "labels": lambda: X.many_labels(spark, sf_dir),
    }


def headline(spark: SparkSession, sf_dir: str) -> dict[str, float]:
    """2,000 pairs a set, with the index and without, on arrays (graphs within the bound), which are sent to all tasks before the clock of a set starts."""
    from pathsieve.loop import cut
    from pathsieve.plans import point
    from pathsieve.plans import workload as W
    from pathsieve.plans.experiments import load
    from pathsieve.plans.index import IndexConfig

    seconds: dict[str, float] = {}

    def clock(name: str, f):
        t = time.time()
        out = f()
        seconds[name] = round(time.time() - t, 3)
        return out

    for name, cfg, patterns in (
        ("page_links", IndexConfig(), {"and": 'ALL{"nav:en","title:en"}', "or": 'ANY{"nav:de","title:de"}', "not": 'NONE{"nav:en"}'}),
        ("supply_star", IndexConfig(order="levels"), {"and": 'ALL{"1-URGENT","R"}', "or": 'ANY{"supplies","A"}', "not": 'NONE{"BUILDING","MACHINERY"}'}),
    ):
        g = clock(f"load_{name}", lambda name=name: load(spark, sf_dir, name))
        arrays = clock(f"arrays_{name}", lambda g=g: point.load(g))
        ix = clock(f"build_{name}", lambda g=g, cfg=cfg, a=arrays: point.build(g, cfg, graph=a))
        pairs = cut(W.sample_pairs(g, 1000).unionByName(W.walk_pairs(g, 1000, 1000)), "asked")
        ask = lambda text: pairs.selectExpr("*", "'" + text.replace("'", "''") + "' AS pattern")
        for p in (ix, arrays):
            point.answer(g, p, ask("FALSE")).count()
        for kind, text in patterns.items():
            found = [clock(f"{kind}_{name}_{how}", lambda g=g, q=ask(text), p=p: point.answer(g, p, q).where("answer").count()) for how, p in (("index", ix), ("plain", arrays))]
            if found[0] != found[1]:
                raise AssertionError(f"{kind} on {name}: {found}")
    return seconds


def rounds(spark: SparkSession, sf_dir: str) -> dict[str, float]:
    """The form for graphs of any size: index tables and searches that move states between tasks, 2,000 pairs on the page graph."""
    from pathsieve.loop import cut
    from pathsieve.plans import search as A
    from pathsieve.plans import workload as W
    from pathsieve.plans.experiments import load
    from pathsieve.plans.index import build_index

    g, cfg = load(spark, sf_dir, "page_links"), A.SearchConfig(place="rounds")
    t = time.time()
    ix = build_index(g)
    seconds = {"build": time.time() - t}
    q = cut(W.sample_pairs(g, 2000), "asked").selectExpr("*", """'ALL{"nav:en","title:en"}' AS pattern""")
    for how, index in (("index", ix), ("plain", None)):
        t = time.time()
        A.answer(g, q, index, cfg).where("answer").count()
        seconds[f"and_{how}"] = time.time() - t
    return seconds


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    spark = session()
    if sys.argv[1:3] == ["--table", "rounds"]:
        print(json.dumps(rounds(spark, sf_dir)))
        return
    if sys.argv[1:3] == ["--table", "queries"]:
        from pathsieve.plans import experiments as X

        chosen = {"names": sys.argv[3].split(",")} if len(sys.argv) > 3 else {}
        for part in X.all_queries(spark, sf_dir, **chosen):
            for row in part.collect():
                print(json.dumps(row.asDict()), flush=True)
        return
    if sys.argv[1:2] == ["--table"]:
        for row in tables(spark, sf_dir)[sys.argv[2]]().collect():
            print(json.dumps(row.asDict()))
        return
    seconds = headline(spark, sf_dir)
    print(json.dumps({"metric": "total_seconds", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": os.path.basename(sf_dir.rstrip("/")).removeprefix("sf")}))


if __name__ == "__main__":
    main()
