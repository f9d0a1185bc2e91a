"""Methods to compare with: index-free search, edge filters, label-set closures and two-hop covers."""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathsieve.functions import masks as M
from pathsieve.functions import patterns as P
from pathsieve.loop import Layers, cut
from pathsieve.operators.graph import FEW_LABELS, Graph, closure_label_sets, encode_vertices, minimal_sets, ragged
from pathsieve.plans.search import SearchConfig, answer

SMALL_GRAPH = 2_000_000


def plain(g: Graph, queries: DataFrame) -> DataFrame:
    """(qid, answer) without an index, set at a time, in rounds."""
    return answer(g, queries, None, SearchConfig(rules=(), place="rounds"))


def local_graph(g: Graph, most: int = SMALL_GRAPH) -> dict[int, list[tuple[int, str]]]:
    """Adjacency for one process; a graph of more than ``most`` edges is refused."""
    rows = g.edges.limit(most + 1).toArrow()
    if rows.num_rows > most:
        raise ValueError(f"more than {most} edges: use the batch search")
    out: dict[int, list[tuple[int, str]]] = {}
    for s, d, x in zip(*(rows.column(c).to_pylist() for c in ("src", "dst", "label")), strict=True):
        out.setdefault(s, []).append((d, x))
    return out


def search_one(adjacency: dict, src: int, dst: int, clauses, prune=None) -> bool:
    """Depth-first search over (vertex, labels seen) with a stack of its own."""
    for c in clauses:
        if src == dst and not c.req:
            return True
        stack, seen = [(src, frozenset())], {(src, frozenset())}
        while stack:
            v, have = stack.pop()
            for to, label in adjacency.get(v, ()):
                if label in c.forb:
                    continue
                state = (to, have | {label} if label in c.req else have)
                if to == dst and len(state[1]) == len(c.req):
                    return True
                if state not in seen and (prune is None or prune(to, dst, c.req - state[1])):
                    seen.add(state)
                    stack.append(state)
    return False


def plain_sequential(g: Graph, queries: DataFrame, most: int = SMALL_GRAPH, reach: dict | None = None) -> DataFrame:
    """(qid, answer) by one depth-first search a query, on graphs that fit one process.

    ``reach`` ({vid: (mask of vertices, labels) beyond it}, see :func:`point_masks`) makes it the point form of the indexed search.
    """
    shared = g.edges.sparkSession.sparkContext.broadcast((local_graph(g, most), g.alphabet(), reach))

    def solve(batches):
        adjacency, alphabet, masks = shared.value
        prune = None
        if masks is not None:
            own, out = masks

            def prune(at, dst, missing):
                v, ls = out.get(at, (0, frozenset()))
                bit = own.get(dst, 0)
                return (at == dst and not missing) or (v & bit == bit and missing <= ls)

        for batch in batches:
            rows = zip(*(batch.column(c).to_pylist() for c in ("src", "dst", "pattern")), strict=True)
            got = [search_one(adjacency, s, d, P.to_dnf(P.simplify(P.parse_pattern(p, alphabet), set(alphabet))), prune) for s, d, p in rows]
            yield pa.RecordBatch.from_arrays([batch.column("qid"), pa.array(got, pa.bool_())], names=["qid", "answer"])

    return queries.select("qid", "src", "dst", "pattern").mapInArrow(solve, "qid long, answer boolean")


def point_masks(index, alphabet: list[str], most: int = SMALL_GRAPH):
    """The wide axis for one process: own bits, and bits and labels beyond each vertex. Needs a label bit for each label."""
    if not index.exact:
        raise ValueError("folded labels")
    own_rows, out_rows = index.own.limit(most + 1).collect(), index.out.limit(most + 1).collect()
    if len(own_rows) > most:
        raise ValueError("too many vertices for one process")
    join = lambda r, names: sum(r[n] << (M.WORD * k) for k, n in enumerate(names))
    own = {r["vid"]: join(r, index.cfg.vw) for r in own_rows}
    out = {}
    for r in out_rows:
        bits = join(r, index.cfg.lw)
        out[r["vid"]] = (join(r, index.cfg.vw), frozenset(x for i, x in enumerate(alphabet) if bits >> i & 1))
    return own, out


def allowed_search(g: Graph, queries: DataFrame) -> DataFrame:
    """(qid, answer) of allowed-set queries by breadth-first search over allowed edges."""
    allowed = cut(queries.select("qid", F.explode("allowed").alias("label")).distinct(), "allowed")
    reached = Layers(queries.select("qid", F.col("src").alias("vid"), "dst").distinct(), "frontier")
    while True:
        live = reached.last.join(reached.last.where("vid = dst").select("qid"), "qid", "left_anti")
        step = live.join(g.edges.withColumnRenamed("src", "vid").withColumnRenamed("dst", "to"), "vid").join(allowed, ["qid", "label"], "left_semi").select("qid", F.col("to").alias("vid"), "dst").distinct()
        if not reached.add(step.join(reached.all.select("qid", "vid"), ["qid", "vid"], "left_anti")):
            break
    found = reached.all.where("vid = dst").select("qid")
    return queries.select("qid").distinct().join(found.distinct().withColumn("hit", F.lit(True)), "qid", "left").select("qid", F.coalesce("hit", F.lit(False)).alias("answer"))


def reach(g: Graph, queries: DataFrame) -> DataFrame:
    """(qid, answer) of plain reachability."""
    return answer(g, queries.select("qid", "src", "dst", F.lit("TRUE").alias("pattern")))


def allowed_masks(g: Graph, queries: DataFrame) -> DataFrame:
    """Queries with their allowed labels as a mask of at most 62 bits."""
    bits = g.labels.select("label", M.bit_word(F.col("lid").cast("long"), 0).alias("bit"))
    rows = queries.select("qid", "src", "dst", F.explode_outer("allowed").alias("label")).join(bits, "label", "left")
    return rows.groupBy("qid", "src", "dst").agg(F.coalesce(F.bit_or("bit"), F.lit(0).cast("long")).alias("ok"))


def minimal_closure(g: Graph, sources: DataFrame | None = None) -> DataFrame:
    """(src, dst, mask): all minimal label sets of each reachable pair; the index that is refused as too large."""
    return closure_label_sets(g, sources, minimal=True)


def closure_answer(g: Graph, closure: DataFrame, queries: DataFrame) -> DataFrame:
    """(qid, answer) of allowed-set queries by lookup in a closure of label sets."""
    masks = allowed_masks(g, queries)
    hit = masks.join(closure, ["src", "dst"]).where("(mask & ok) = mask").select("qid").union(masks.where("src = dst").select("qid")).distinct()
    return queries.select("qid").distinct().join(hit.withColumn("hit", F.lit(True)), "qid", "left").select("qid", F.coalesce("hit", F.lit(False)).alias("answer"))


@dataclass(frozen=True)
class TwoHop:
    """Lists of (hub, minimal label set) out of and into each vertex; ``peel`` sends vertices of degree one to their neighbour."""

    out: DataFrame
    into: DataFrame
    peel: DataFrame | None
    filter: object | None


def two_hop_build(g: Graph, reduce_degree_one: bool = False, unreachable_filter: bool = False, batch: int = 64, most_rows: int | None = None) -> TwoHop:
    """A two-hop cover with hubs in falling order of degree.

    Hubs are taken in batches that double; each batch searches both ways with its hubs' label sets at once, and a state that the cover
    of earlier hubs already explains is dropped. ``most_rows`` stops a cover that grows too large. Graphs of checked size and few labels are
    covered on arrays, hub by hub, which keeps the lists short.
    """
    spark = g.edges.sparkSession
    if g.labels.where(f"lid >= {M.WORD}").limit(1).count():
        raise ValueError("more than 62 labels")
    steps = cut(g.edges.join(g.labels, "label").select("src", "dst", M.bit_word(F.col("lid").cast("long"), 0).alias("bit")).where("src <> dst").distinct(), "steps")
    peel = None
    if reduce_degree_one:
        peel, steps = _peel(steps)
    filter_tables = None
    if unreachable_filter:
        from pathsieve.plans.index import IndexConfig, own_bits
        from pathsieve.plans.index import inbound_masks as into_masks

        cfg = IndexConfig()
        filter_tables = (cut(own_bits(g.vertices(), cfg), "own"), into_masks(g, cfg), cfg)
    if not g.labels.where(f"lid >= {FEW_LABELS}").limit(1).count() and (cover := _cover_on_arrays(steps, most_rows)) is not None:
        return TwoHop(*cover, peel, filter_tables)
    both = steps.select(F.col("src").alias("vid")).unionAll(steps.select("dst"))
    ranked = both.groupBy("vid").agg(F.count("*").alias("n")).select(F.struct((-F.col("n")).alias("n"), "vid").alias("ext_id"))
    hubs = cut(encode_vertices(ranked).select("ext_id.vid", (F.col("vid") + 1).alias("rank")), "hubs")
    total = hubs.count()
    kind = "vid long, hub long, mask long"
    out, into = spark.createDataFrame([], kind), spark.createDataFrame([], kind)
    low = 0
    while low < total:
        now = hubs.where(f"rank > {low} AND rank <= {low + batch}").select("vid", "rank")
        new_into = _spread(now, steps, out, into, hubs, forward=True)
        new_out = _spread(now, steps, out, into, hubs, forward=False)
        into, out = cut(into.unionByName(new_into), "into"), cut(out.unionByName(new_out), "out")
        if most_rows is not None and (size := into.count() + out.count()) > most_rows:
            raise MemoryError(f"the cover has {size} rows")
        low, batch = low + batch, batch * 2
    return TwoHop(out, into, peel, filter_tables)


def _cover_on_arrays(steps: DataFrame, most_rows: int | None, most: int = 1_000_000) -> tuple[DataFrame, DataFrame] | None:
    """(vid, hub, mask) out of and into each vertex; None beyond ``most`` edges.

    A hub's search goes on over vertices that were no hubs before: walks over earlier hubs are theirs. So vertices without an edge to such a
    vertex are no hubs. Where a search goes beyond a hub's neighbours, what the lists of earlier hubs of that kind explain is dropped.
    """
    rows = steps.limit(most + 1).toArrow()
    if rows.num_rows > most:
        return None
    src, dst, bit = (rows.column(c).to_numpy().astype(np.int64) for c in ("src", "dst", "bit"))
    vids = np.unique(np.concatenate([src, dst]))
    n = len(vids)
    src, dst = np.searchsorted(vids, src), np.searchsorted(vids, dst)
    sides = []
    for a, b in ((src, dst), (dst, src)):
        order = np.argsort(a, kind="stable")
        sides.append((np.searchsorted(a[order], np.arange(n + 1)), b[order], bit[order]))
    live, wide, lists, size = np.ones(n, bool), [], ([], []), 0
    degree = np.bincount(src, minlength=n) + np.bincount(dst, minlength=n)

    def holds(sets: list[tuple[int, np.ndarray]], v: int) -> list[int]:
        return [m for m, some in sets if (i := int(np.searchsorted(some, v))) < len(some) and some[i] == v]

    for h in np.argsort(-degree, kind="stable").tolist():
        near = [to[at[h] : at[h + 1]] for at, to, _ in sides]
        near = [np.unique(x[live[x]]) for x in near]
        if not len(near[0]) and not len(near[1]):
            continue
        found, far = [], False
        for i, (at, to, bits) in enumerate(sides):
            beyond = to[ragged(at[near[i]], at[near[i] + 1] - at[near[i]])]
            known = []
            if (live[beyond] & (beyond != h)).any():
                far = True
                for earlier in wide:
                    # From h to the earlier hub, and from there on: its sets of the other side and of this one.
                    for m in holds(earlier[1 - i], h):
                        known += [(m | x, some) for x, some in earlier[i]]
            found.append(minimal_sets(at, to, bits, [(0, np.array([h]))], known, live))
        for i, sets in enumerate(found):
            lists[i].extend((h, m, some) for m, some in sets)
            size += sum(len(some) for _, some in sets)
        if most_rows is not None and size > most_rows:
            raise MemoryError(f"the cover has {size} rows")
        if far:
            wide.append(found)
        live[h] = False

    def table(of: list[tuple[int, int, np.ndarray]]) -> DataFrame:
        sizes = [len(some) for _, _, some in of]
        hubs, masks = (np.repeat(np.array([x[k] for x in of], np.int64), sizes) for k in (0, 1))
        members = np.concatenate([some for _, _, some in of]) if of else np.zeros(0, np.int64)
        return cut(steps.sparkSession.createDataFrame(pa.table({"vid": vids[members], "hub": vids[hubs], "mask": masks})), "cover")

    return table(lists[1]), table(lists[0])


def _spread(now: DataFrame, steps: DataFrame, out: DataFrame, into: DataFrame, hubs: DataFrame, forward: bool) -> DataFrame:
    """Minimal label sets between this batch's hubs and the vertices that they reach (or that reach them)."""
    a, b = ("src", "dst") if forward else ("dst", "src")
    states = cut(now.select(F.col("vid").alias("hub"), "vid", F.lit(0).cast("long").alias("mask")), "states")
    done = states
    while True:
        step = states.join(steps.select(F.col(a).alias("vid"), F.col(b).alias("to"), "bit"), "vid").select("hub", F.col("to").alias("vid"), F.col("mask").bitwiseOR(F.col("bit")).alias("mask")).distinct()
        mine, theirs = (out, into) if forward else (into, out)
        known = mine.select(F.col("vid").alias("hub"), F.col("hub").alias("via"), F.col("mask").alias("m1")).join(theirs.select("vid", F.col("hub").alias("via"), F.col("mask").alias("m2")), "via").select(F.col("hub").alias("h"), F.col("vid").alias("x"), F.col("m1").bitwiseOR(F.col("m2")).alias("m"))
        old = done.select(F.col("hub").alias("h"), F.col("vid").alias("x"), F.col("mask").alias("m")).unionByName(known)
        fresh = step.join(old, (F.col("hub") == F.col("h")) & (F.col("vid") == F.col("x")) & (F.col("m").bitwiseAND(F.col("mask")) == F.col("m")), "left_anti")
        other = fresh.select(F.col("hub").alias("h"), F.col("vid").alias("x"), F.col("mask").alias("m"))
        least = fresh.join(other, (F.col("hub") == F.col("h")) & (F.col("vid") == F.col("x")) & (F.col("m") != F.col("mask")) & (F.col("m").bitwiseAND(F.col("mask")) == F.col("m")), "left_anti")
        states = cut(least, "states")
        if states.isEmpty():
            return done.select("vid", "hub", "mask")
        done = done.unionByName(states)


def _peel(steps: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Takes off vertices with one distinct neighbour, once: (vid, anchor, way, bit), and the steps that stay."""
    pairs = steps.select(F.col("src").alias("vid"), F.col("dst").alias("nbr")).union(steps.select("dst", "src")).distinct()
    lone = pairs.groupBy("vid").agg(F.count("*").alias("n"), F.min("nbr").alias("anchor")).where("n = 1").select("vid", "anchor")
    lone = cut(lone.join(lone.select(F.col("vid").alias("anchor"), F.col("anchor").alias("back")), "anchor", "left").where("back IS NULL OR back <> vid OR vid < anchor").select("vid", "anchor"), "lone")
    out = lone.join(steps, (lone.vid == steps.src) & (lone.anchor == steps.dst)).select("vid", "anchor", F.lit("out").alias("way"), "bit")
    into = lone.join(steps, (lone.vid == steps.dst) & (lone.anchor == steps.src)).select("vid", "anchor", F.lit("in").alias("way"), "bit")
    ids = lone.select("vid")
    rest = steps.join(ids.withColumnRenamed("vid", "src"), "src", "left_anti").join(ids.withColumnRenamed("vid", "dst"), "dst", "left_anti")
    return cut(out.unionByName(into), "peel"), cut(rest.select("src", "dst", "bit"), "steps")


def two_hop_answer(g: Graph, index: TwoHop, queries: DataFrame) -> DataFrame:
    """(qid, answer) of allowed-set queries: a common hub with both label sets inside the allowed one."""
    masks = cut(allowed_masks(g, queries), "masks")
    live = masks
    if index.filter is not None:
        own, into, cfg = index.filter
        mine = own.select(F.col("vid").alias("src"), *cfg.vw)
        far = into.select(F.col("vid").alias("dst"), *["i" + n[1:] for n in cfg.vw])
        live = masks.join(mine, "src").join(far, "dst").where(M.mask_contains([F.col("i" + n[1:]) for n in cfg.vw], [F.col(n) for n in cfg.vw])).select("qid", "src", "dst", "ok")
    hit = masks.where("src = dst").select("qid")
    ends = live.select("qid", F.col("src").alias("a"), F.col("dst").alias("b"), "ok")
    if index.peel is not None:
        at = lambda way: index.peel.where(F.col("way") == way)
        lone = index.peel.select("vid").distinct()
        first = ends.join(at("out").select(F.col("vid").alias("a"), "anchor", "bit"), "a").where("(bit & ok) = bit").select("qid", F.col("anchor").alias("a"), "b", "ok")
        ends = ends.join(lone.withColumnRenamed("vid", "a"), "a", "left_anti").select("qid", "a", "b", "ok").unionByName(first).distinct()
        hit = hit.union(ends.where("a = b").select("qid"))
        last = ends.join(at("in").select(F.col("vid").alias("b"), "anchor", "bit"), "b").where("(bit & ok) = bit").select("qid", "a", F.col("anchor").alias("b"), "ok")
        ends = ends.join(lone.withColumnRenamed("vid", "b"), "b", "left_anti").select("qid", "a", "b", "ok").unionByName(last).distinct()
        hit = hit.union(ends.where("a = b").select("qid"))
    left = index.out.select(F.col("vid").alias("a"), "hub", F.col("mask").alias("m1"))
    right = index.into.select(F.col("vid").alias("b"), "hub", F.col("mask").alias("m2"))
    met = ends.join(left, "a").where("(m1 & ok) = m1").join(right, ["b", "hub"]).where("(m2 & ok) = m2").select("qid")
    hit = hit.union(met).distinct()
    return queries.select("qid").distinct().join(hit.withColumn("hit", F.lit(True)), "qid", "left").select("qid", F.coalesce("hit", F.lit(False)).alias("answer"))


# Regular paths, simple paths and witnesses.

_ITEM = re.compile(r"\s*(?:(?P<label>\"[^\"]+\"|[^\s()|*+?\"]+)|(?P<op>[()|*+?]))")


def automaton(text: str) -> tuple[list[tuple[int, str, int]], int, set[int]]:
    """Position automaton of a regular expression over labels (space for sequence, | * + ? and parentheses): moves, start, ends."""
    items, at = [], 0
    while text[at:].strip():
        m = _ITEM.match(text, at)
        if not m:
            raise P.PatternError("unexpected character", at)
        items.append(m["op"] or ("label", m["label"].strip('"')))
        at = m.end()
    labels: dict[int, str] = {}
    follow: dict[int, set[int]] = {}

    def choice():
        parts = [sequence()]
        while items and items[0] == "|":
            items.pop(0)
            parts.append(sequence())
        return any(p[0] for p in parts), set().union(*(p[1] for p in parts)), set().union(*(p[2] for p in parts))

    def sequence():
        empty, first, last = True, set(), set()
        while items and items[0] not in ("|", ")"):
            e, f, x = repeated()
            for p in last:
                follow[p] |= f
            first, last = (first | f if empty else first), (last | x if e else x)
            empty = empty and e
        return empty, first, last

    def repeated():
        item = items.pop(0)
        if item == "(":
            e, f, x = choice()
            if not items or items.pop(0) != ")":
                raise P.PatternError("missing )", len(text))
        elif isinstance(item, tuple):
            p = len(labels) + 1
            labels[p], follow[p] = item[1], set()
            e, f, x = False, {p}, {p}
        else:
            raise P.PatternError(f"unexpected {item}", len(text))
        while items and items[0] in ("*", "+", "?"):
            sign = items.pop(0)
            if sign != "?":
                for p in x:
                    follow[p] |= f
            e = e or sign != "+"
        return e, f, x

    empty, first, last = choice()
    if items:
        raise P.PatternError("unexpected )", len(text))
    moves = [(0, labels[p], p) for p in sorted(first)] + [(p, labels[q], q) for p in sorted(follow) for q in sorted(follow[p])]
    return moves, 0, last | ({0} if empty else set())


def answer_regex(g: Graph, queries: DataFrame) -> DataFrame:
    """(qid, answer) of regular-path queries (qid, src, dst, regex): search over (vertex, automaton state)."""
    spark = g.edges.sparkSession
    texts = [r[0] for r in queries.select("regex").distinct().limit(10_001).collect()]
    if len(texts) > 10_000:
        raise ValueError("more than 10,000 distinct expressions")
    machines = {t: automaton(t) for t in texts}
    moves = spark.createDataFrame([(t, a, x, b) for t, m in machines.items() for a, x, b in m[0]], "regex string, state int, label string, next int")
    ends = spark.createDataFrame([(t, e) for t, m in machines.items() for e in sorted(m[2])], "regex string, state int")
    reached = Layers(queries.select("qid", "regex", F.col("src").alias("vid"), "dst", F.lit(0).alias("state")), "frontier")
    hits = lambda states: states.where("vid = dst").join(F.broadcast(ends), ["regex", "state"], "left_semi").select("qid")
    while True:
        live = reached.last.join(hits(reached.last), "qid", "left_anti").join(F.broadcast(moves), ["regex", "state"])
        step = live.join(g.edges.select(F.col("src").alias("vid"), "label", F.col("dst").alias("to")), ["vid", "label"]).select("qid", "regex", F.col("to").alias("vid"), "dst", F.col("next").alias("state")).distinct()
        if not reached.add(step.join(reached.all.select("qid", "vid", "state"), ["qid", "vid", "state"], "left_anti")):
            break
    found = hits(reached.all)
    return queries.select("qid").distinct().join(found.distinct().withColumn("hit", F.lit(True)), "qid", "left").select("qid", F.coalesce("hit", F.lit(False)).alias("answer"))


def answer_simple(g: Graph, queries: DataFrame, max_hops: int) -> DataFrame:
    """(qid, answer) over paths of at most ``max_hops`` edges that repeat no vertex; exponential, for small graphs."""
    alphabet = set(g.alphabet())
    formulas = {r[0]: P.simplify(P.parse_pattern(r[0], alphabet), alphabet) for r in queries.select("pattern").distinct().collect()}
    paths = cut(queries.select("qid", "dst", "pattern", F.col("src").alias("vid"), F.array("src").alias("seen"), F.array().cast("array<string>").alias("labels")), "paths")
    holds = F.lit(False)
    for text, p in formulas.items():
        holds = holds | ((F.col("pattern") == text) & P.pattern_column(p, F.col("labels")))
    hits = paths.where("vid = dst").where(holds).select("qid")
    for _ in range(max_hops):
        step = paths.join(g.edges.select(F.col("src").alias("vid"), F.col("dst").alias("to"), "label"), "vid").where("NOT array_contains(seen, to)")
        paths = cut(step.select("qid", "dst", "pattern", F.col("to").alias("vid"), F.array_append("seen", F.col("to")).alias("seen"), F.array_sort(F.array_distinct(F.array_append("labels", F.col("label")))).alias("labels")).distinct(), "paths")
        if paths.isEmpty():
            break
        hits = hits.union(paths.where("vid = dst").where(holds).select("qid"))
        paths = paths.where("vid <> dst")
    found = cut(hits.distinct(), "hits").withColumn("hit", F.lit(True))
    return queries.select("qid").distinct().join(found, "qid", "left").select("qid", F.coalesce("hit", F.lit(False)).alias("answer"))


def witness_paths(g: Graph, queries: DataFrame, max_clauses: int = 64) -> DataFrame:
    """(qid, path): for each true query a shortest walk as an array of (src, label, dst); an empty one for the empty path.

    The search keeps, for every new state, one edge and state before it; walks are read backwards, one join a hop.
    """
    from pathsieve.plans.search import compile_queries

    alphabet = g.alphabet()
    words = M.n_words(len(alphabet))
    clauses = cut(compile_queries(queries, alphabet, max_clauses), "clauses")
    s, r, f, e = (M.names(p, words) for p in "srfe")
    edges = cut(g.edges.join(g.labels, "label").select("src", "dst", "label", *[M.bit_word(F.col("lid").cast("long"), w).alias(n) for w, n in enumerate(e)]), "edges")
    key = ["qid", "clause", "vid", *s]
    layer = cut(clauses.select("qid", "clause", F.col("src").alias("vid"), *[F.lit(0).cast("long").alias(n) for n in s]), "layer")
    layers, visited, ends, hop = [layer], layer, [], 0
    while True:
        full = layer.join(clauses, ["qid", "clause"]).where(F.col("vid") == F.col("dst")).where(M.mask_contains([F.col(n) for n in s], [F.col(n) for n in r]))
        ends.append(cut(full.select(*key).withColumn("hop", F.lit(hop)), "ends"))
        live = layer.select(*key).join(ends[-1].select("qid"), "qid", "left_anti").join(clauses, ["qid", "clause"])
        hop += 1
        step = live.withColumnRenamed("vid", "from").join(edges.withColumnRenamed("src", "from").withColumnRenamed("dst", "to"), "from").where(M.mask_disjoint([F.col(n) for n in e], [F.col(n) for n in f]))
        seen = [F.col(a).bitwiseOR(F.col(b).bitwiseAND(F.col(c))).alias("n" + a) for a, b, c in zip(s, e, r, strict=True)]
        step = step.select("qid", "clause", F.col("to").alias("vid"), *seen, F.struct("from", "label", *s).alias("back"))
        best = step.groupBy("qid", "clause", "vid", *["n" + n for n in s]).agg(F.min("back").alias("back"))
        best = best.select("qid", "clause", "vid", *[F.col("n" + n).alias(n) for n in s], "back")
        layer = cut(best.join(visited.select(*key), key, "left_anti"), "layer")
        if layer.isEmpty():
            break
        layers.append(layer)
        visited = visited.select(*key).unionByName(layer.select(*key))
    last = ends[0]
    for x in ends[1:]:
        last = last.unionByName(x)
    chosen = last.groupBy("qid").agg(F.min(F.struct("hop", "clause", "vid", *s)).alias("x")).select("qid", "x.*")
    empty = F.array().cast("array<struct<src:bigint,label:string,dst:bigint>>")
    open_paths, finished = cut(chosen.withColumn("path", empty), "paths"), None
    for h in range(len(layers) - 1, -1, -1):
        here = open_paths.where(f"hop = {h}")
        if h == 0:
            finished = here.select("qid", "path")
            break
        back = here.join(layers[h], key).select("qid", F.lit(h - 1).alias("hop"), "clause", F.col("back.from").alias("vid"), *[F.col(f"back.{n}").alias(n) for n in s], F.concat(F.array(F.struct(F.col("back.from").alias("src"), F.col("back.label").alias("label"), F.col("vid").alias("dst"))), "path").alias("path"))
        open_paths = cut(open_paths.where(f"hop < {h}").unionByName(back), "paths")
    return finished
