"""The experiments: tables of index cost and query time, sweeps over generated graphs, ablations.

Each function returns rows (graph, method, config, metric, value); ``bench.py`` runs them.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathsieve.functions import masks as M
from pathsieve.loop import cut
from pathsieve.operators.graph import Graph, graph_stats, is_acyclic
from pathsieve.plans import baselines as B
from pathsieve.plans import measures as S
from pathsieve.plans import point
from pathsieve.plans import search as A
from pathsieve.plans import workload as W
from pathsieve.plans.index import IndexConfig, build_index
from pathsieve.sources import graphs as T

OURS, PLAIN = "two-axis", "plain"
COVERS = {"full 2-hop": {}, "reduced 2-hop": {"reduce_degree_one": True, "unreachable_filter": True}}
#: Graphs of the tables in order, with uniform labels where the paper's stand-ins have them.
TABLE_GRAPHS = {"page_links": None, "talk_flow": None, "order_relay": None, "order_relay_16": 16, "doc_thread": None, "supply_star": None, "event_flow": None, "part_chain": None, "part_chain_32": 32, "event_many": None}


def load(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    base, _, z = name.rpartition("_")
    if z.isdigit():
        return T.with_uniform_labels(T.BUILDERS[base](spark, sf_dir), int(z)).stored()
    return T.BUILDERS[name](spark, sf_dir).stored()


def _union(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def table_graphs(spark: SparkSession, sf_dir: str, names=TABLE_GRAPHS) -> DataFrame:
    """Statistics of each graph."""
    out = []
    for name in names:
        row = graph_stats(load(spark, sf_dir, name)).first().asDict()
        out.append(S.rows(spark, name, "-", "-", **{k: v or 0 for k, v in row.items()}))
    return _union(out)


def table_index(spark: SparkSession, sf_dir: str, names=TABLE_GRAPHS, cap: float = 60, cfg: IndexConfig | None = None) -> DataFrame:
    """Build time and size of the two-axis index and of both two-hop covers; a cover over the cap is recorded as failed."""
    out = []
    for name in names:
        g = load(spark, sf_dir, name)
        arrays = point.load(g)
        ix, row = S.index_time(spark, name, OURS, "-", lambda g=g, a=arrays: point.build(g, cfg, graph=a))
        out += [row, S.rows(spark, name, OURS, "-", index_mb=S.index_space(ix))]
        for method, options in COVERS.items():
            (status, made), row = S.index_time(spark, name, method, "-", lambda g=g, o=options: S.capped(spark, lambda: B.two_hop_build(g, **o, most_rows=50_000_000), cap))
            out.append(S.rows(spark, name, method, "-", failed=0 if status == "ok" else 1))
            if status == "ok":
                out += [row, S.rows(spark, name, method, "-", index_mb=24 * (made.out.count() + made.into.count()) / 1e6)]
    return _union(out)


def labels_asked(g: Graph) -> int:
    """Labels in a query: two on the dense graphs, four elsewhere."""
    edges, vertices = g.edges.count(), g.vertices().count()
    return 2 if edges > 40 * vertices else 4


def table_queries(spark: SparkSession, sf_dir: str, op: str, names=TABLE_GRAPHS, n: int = 2000, n_labels: int | str | None = None, cfg: IndexConfig | None = None) -> DataFrame:
    """Times of ``n`` true and ``n`` false queries of an operator (ALL, ANY, NONE, MIXED), with and without the index.

    Where a kind can't be found in that number (a dense graph has hardly a false ANY), true_n and false_n tell how many there were.
    """
    out = []
    for name in names:
        g = load(spark, sf_dir, name)
        arrays = point.load(g)
        out.append(query_rows(spark, name, g, arrays, point.build(g, cfg, graph=arrays), op, n, n_labels or labels_asked(g)))
    return _union(out)


def query_rows(spark: SparkSession, name: str, g: Graph, arrays: point.PointGraph, ix: point.PointGraph, op: str, n: int, n_labels: int | str) -> DataFrame:
    """Times and effort of one operator on one graph."""
    q = W.make_queries(g, op, n, n, n_labels, most_tries=5, short=True, solve=lambda x: point.answer(g, ix, x))
    out = [S.query_time(spark, name, OURS, op, lambda x: point.answer(g, ix, x), q), S.query_time(spark, name, PLAIN, op, lambda x: point.answer(g, arrays, x), q)]
    for method, p in ((OURS, ix), (PLAIN, arrays)):
        out.append(S.rows(spark, name, method, op, **{f"effort_{r['measure']}": r["n"] for r in point.effort(g, p, q).collect()}))
    return _union(out)


def all_queries(spark: SparkSession, sf_dir: str, names=TABLE_GRAPHS, ops=("ALL", "ANY", "NONE", "ONLY"), n: int = 2000, n_labels: int | None = None):
    """Rows of every operator on every graph, one table after the other as they are done; allowed sets hold half the labels."""
    for name in names:
        g = load(spark, sf_dir, name)
        arrays = point.load(g)
        ix, row = S.index_time(spark, name, OURS, "-", lambda: point.build(g, graph=arrays))
        yield row.unionByName(S.rows(spark, name, OURS, "-", index_mb=S.index_space(ix)))
        for op in ops:
            yield query_rows(spark, name, g, arrays, ix, op, n, "half" if op == "ONLY" else n_labels or labels_asked(g))


def table_allowed(spark: SparkSession, sf_dir: str, names=TABLE_GRAPHS, n: int = 2000, cap: float = 60) -> DataFrame:
    """Times of ``n`` true and ``n`` false allowed-set queries: ours, an edge filter, and both two-hop covers where they can be built."""
    out = []
    for name in names:
        g = load(spark, sf_dir, name)
        arrays = point.load(g)
        ix = point.build(g, graph=arrays)
        q = W.make_queries(g, "ONLY", n, n, "half", short=True)
        sets = q.withColumn("allowed", F.split(F.regexp_replace("pattern", r'^ONLY\{"|"\}$', ""), '","'))
        out.append(S.query_time(spark, name, OURS, "ONLY", lambda x, g=g, ix=ix: A.answer_allowed(g, x, ix), sets))
        out.append(S.query_time(spark, name, PLAIN, "ONLY", lambda x, g=g, a=arrays: A.answer_allowed(g, x, a), sets))
        if g.labels.count() <= M.WORD:
            for method, options in COVERS.items():
                status, made = S.capped(spark, lambda g=g, o=options: B.two_hop_build(g, **o), cap)
                if status == "ok":
                    out.append(S.query_time(spark, name, method, "ONLY", lambda x, g=g, m=made: B.two_hop_answer(g, m, x), sets))
                else:
                    out.append(S.rows(spark, name, method, "ONLY", failed=1))
    return _union(out)


def sweep(spark: SparkSession, kind: str, n: int, degrees=(2, 4, 6, 8), labels=(8, 16, 32, 64), queries: int = 2000, ops=("ALL", "ANY", "NONE"), cfg: IndexConfig | None = None) -> DataFrame:
    """Build time, size and mean query times over generated graphs; config is "D=..,Z=..", also as columns degree and n_labels.

    Label masks have 62 bits unless ``cfg`` says otherwise, so 64 labels share bits, as in the reference's runs some labels do.
    """
    make = {"uniform": T.uniform_graph, "preferential": T.preferential_graph}[kind]
    out = []
    for d in degrees:
        for z in labels:
            g = make(spark, n, d, z).stored()
            label = f"D={d},Z={z}"
            arrays = point.load(g)
            ix, row = S.index_time(spark, kind, OURS, label, lambda g=g, a=arrays: point.build(g, cfg, graph=a))
            parts = [row, S.rows(spark, kind, OURS, label, index_mb=S.index_space(ix))]
            for op in ops:
                q = W.make_queries(g, op, queries, queries, 2, most_tries=4, short=True, solve=lambda x, g=g, ix=ix: point.answer(g, ix, x))
                got = S.query_time(spark, kind, OURS, label, lambda x, g=g, ix=ix: point.answer(g, ix, x), q)
                parts.append(got.withColumn("metric", F.concat(F.lit(op + "_"), F.col("metric"))))
            out.append(_union(parts).withColumn("degree", F.lit(d)).withColumn("n_labels", F.lit(z)))
    return cut(_union(out), "sweep")


def check_trends(results: DataFrame) -> DataFrame:
    """Slope and correlation of build time, size and query time with degree and with labels."""
    parts = [S.trend(results, x, m).withColumn("x", F.lit(x)).withColumn("metric", F.lit(m)) for x in ("degree", "n_labels") for m in ("build_s", "index_mb", "ALL_mean_s", "ANY_mean_s", "NONE_mean_s")]
    return _union(parts)


def ablation(spark: SparkSession, sf_dir: str, name: str = "page_links", n: int = 500) -> DataFrame:
    """Search effort without each rule, and for k, ways, widths and hash modes; what each rule cut is told by its name."""
    g = load(spark, sf_dir, name)
    arrays = point.load(g)
    q = W.make_queries(g, "MIXED", n, n, short=True)
    cases = {f"k={k}": IndexConfig(k=k) for k in (0, 1, 2, 3)}
    cases |= {f"ways={c}": IndexConfig(way_count=c) for c in ("one", "log2", "sqrt", "linear", "fixed")} | {f"rule={r}": IndexConfig(way_rule=r) for r in ("rank", "overlap", "label")}
    cases |= {f"bits={b}": IndexConfig(vertex_bits=b) for b in (31, 62, 248)} | {"hashes=2": IndexConfig(n_hash=2), "mode=path": IndexConfig(mode="path"), "trees=3": IndexConfig(trees=3)}
    count = lambda p, rules=A.RULES: {r["measure"]: r["n"] for r in point.effort(g, p, q, rules).collect()}
    bare = count(arrays)
    spared = lambda work: 1 - work["edges"] / max(bare["edges"], 1)
    out = [S.rows(spark, name, PLAIN, "-", **bare)]
    for label, cfg in cases.items():
        work = count(point.build(g, cfg, graph=arrays))
        out.append(S.rows(spark, name, OURS, label, prune_rate=spared(work), **work))
    ix = point.build(g, graph=arrays)
    for rule in A.RULES:
        work = count(ix, tuple(r for r in A.RULES if r != rule))
        out.append(S.rows(spark, name, OURS, f"without {rule}", prune_rate=spared(work), **work))
    return _union(out)


def acyclic(spark: SparkSession, sf_dir: str, names=("supply_star", "part_chain_dag", "talk_flow", "doc_thread")) -> DataFrame:
    """Build times on acyclic graphs: on arrays, and, but for the long chains of ``doc_thread``, in rounds level by level and by fixpoint."""
    out = []
    for name in names:
        g = load(spark, sf_dir, name)
        out.append(S.index_time(spark, name, OURS, "arrays", lambda g=g: point.build(g))[1])
        if name == "doc_thread":
            continue
        if not is_acyclic(g):
            raise ValueError(f"{name} has a cycle")
        for order in ("levels", "fixpoint"):
            out.append(S.index_time(spark, name, OURS, order, lambda g=g, o=order: build_index(g, IndexConfig(order=o)))[1])
    return _union(out)


def many_labels(spark: SparkSession, sf_dir: str, n: int = 2000) -> DataFrame:
    """Hundreds of labels: folded masks against masks with a bit for each."""
    g = load(spark, sf_dir, "event_many")
    arrays = point.load(g)
    q = W.make_queries(g, "NONE", n, n, 4, most_tries=3, short=True)
    made = {b: point.build(g, IndexConfig(label_bits=b), graph=arrays) for b in (31, 62, 62 * 9)}
    return _union([S.query_time(spark, "event_many", OURS, f"label_bits={b}", lambda x, p=p: point.answer(g, p, x), q) for b, p in made.items()])
