"""Answering pattern queries in batches: exact state search with switchable filters.

A state is (query, clause, vertex, required labels seen). A round joins all live states with the edges, drops forbidden
labels, marks required ones, and keeps the states that are new. Filters from the index only remove
states that can't reach an answer, so answers are the same with and without them.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, replace
from functools import reduce

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathsieve.functions import masks as M
from pathsieve.functions import patterns as P
from pathsieve.loop import Layers, cut, cut_counted, scratch
from pathsieve.operators.graph import Graph, closure_components, count_reached, encode_vertices
from pathsieve.plans import point
from pathsieve.plans.index import TwoAxisIndex

RULES = ("way_vertex", "way_required", "way_forbidden", "inbound", "horizon", "certificate")


@dataclass(frozen=True)
class SearchConfig:
    """``rules`` are the filters to use; ``mode`` "clauses" or "mask" (no normal form, formula tested at the target).

    ``place``: "rounds" moves states between tasks, for graphs of any size; "tasks" holds the graph in every task and is
    refused beyond :data:`pathsieve.plans.point.MOST_EDGES`; "auto" takes the latter where the graph is within that bound.
    ``both`` searches in rounds from source and target at once, without an index.
    """

    rules: tuple[str, ...] = RULES
    empty_path: bool = True
    mode: str = "clauses"
    place: str = "auto"
    max_clauses: int = 64
    dominance: bool = False
    both: bool = False
    trace: bool = False
    max_rounds: int | None = None


def _clause_rows(batches, alphabet: list[str], words: int, max_clauses: int):
    lid = {x: i for i, x in enumerate(alphabet)}
    for batch in batches:
        rows = []
        for text in batch.column("pattern").to_pylist():
            formula = P.simplify(P.parse_pattern(text, alphabet), lid)
            try:
                clauses = P.to_dnf(formula, max_clauses)
            except P.TooManyClauses:
                rows.append((text, -1, *[0] * (2 * words)))
                continue
            for k, c in enumerate(clauses):
                rows.append((text, k, *M.to_words([lid[x] for x in c.req], words), *M.to_words([lid[x] for x in c.forb], words)))
        columns = list(zip(*rows, strict=True)) if rows else [[] for _ in range(2 + 2 * words)]
        kinds = [pa.string(), pa.int32()] + [pa.int64()] * (2 * words)
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=["pattern", "clause", *M.names("r", words), *M.names("f", words)])


def compile_queries(queries: DataFrame, alphabet: list[str], max_clauses: int = 64) -> DataFrame:
    """(qid, clause, src, dst, r..., f...): one row for each clause; a contradiction has none. Distinct patterns are parsed once, in tasks.

    A pattern of more than ``max_clauses`` has one row, with clause -1.
    """
    words = M.n_words(len(alphabet))
    kind = "pattern string, clause int, " + ", ".join(f"{n} long" for n in M.names("r", words) + M.names("f", words))
    clauses = queries.select("pattern").distinct().mapInArrow(lambda it: _clause_rows(it, alphabet, words, max_clauses), kind)
    return queries.join(clauses, "pattern").drop("pattern")


def label_edges(g: Graph) -> tuple[DataFrame, int]:
    """(src, dst, e...): each edge with its label's exact bit, and the words of the mask."""
    words = M.n_words(g.labels.agg(F.count("*")).first()[0] or 1)
    rows = g.edges.join(g.labels, "label")
    return rows.select("src", "dst", *[M.bit_word(F.col("lid").cast("long"), w).alias(n) for w, n in enumerate(M.names("e", words))]), words


def _target_columns(clauses: DataFrame, index: TwoAxisIndex) -> DataFrame:
    """Adds the target's own bits (d...), outbound bits (o...), inbound bits (t...) and its intervals' first tree."""
    vw = index.cfg.vw
    own = index.own.select(F.col("vid").alias("dst"), *[F.col(n).alias("d" + n[1:]) for n in vw])
    out = index.out.select(F.col("vid").alias("dst"), *[F.col(n).alias("o" + n[1:]) for n in vw])
    into = index.inbound.select(F.col("vid").alias("dst"), *[F.col("i" + n[1:]).alias("t" + n[1:]) for n in vw])
    joined = clauses.join(own, "dst", "left").join(out, "dst", "left").join(into, "dst", "left")
    zero = {p + n[1:]: 0 for n in vw for p in "dot"}
    return joined.na.fill(zero)


def _cs(prefix: str, n: int) -> list[Column]:
    return [F.col(x) for x in M.names(prefix, n)]


class _Run:
    def __init__(self, g: Graph, index: TwoAxisIndex | None, cfg: SearchConfig) -> None:
        self.index, self.cfg = index, cfg
        edges, self.words = label_edges(g)
        self.rules = set(cfg.rules) if index is not None else set()
        self.state = ["qid", "clause", "vid", *M.names("s", self.words)]
        self.carry = ["dst", *M.names("r", self.words), *M.names("f", self.words)]
        if index is None:
            self.edges = cut(edges, "edges")
        else:
            self.edges = cut(edges.join(index.ways, ["src", "dst"]), "edges")
            vw = index.cfg.vw
            own = index.own.select("vid", *[F.col(n).alias("m" + n[1:]) for n in vw])
            fused = index.fused().join(own, "vid", "left").join(index.inbound, "vid", "left")
            self.fused = cut(fused.na.fill({p + n[1:]: 0 for n in vw for p in "mi"}), "fused")
            self.nv, self.nl = len(index.cfg.vw), len(index.cfg.lw)
            self.carry += [p + n[1:] for p in "dot" for n in index.cfg.vw]
            if not index.exact:
                self.rules.discard("way_forbidden")
        self.trace: list[tuple] = []

    def _folded(self, words: list[Column]) -> list[Column]:
        return M.fold(words, self.index.cfg.label_bits)

    def _missing(self) -> list[Column]:
        return M.mask_minus(_cs("r", self.words), _cs("s", self.words))

    def way_filters(self) -> dict[str, Column]:
        """Conditions for keeping (state, way); each is implied by a walk to the target through the way.

        "inbound" is the same for all ways: the vertex and all before it lie before the target.
        """
        d, wide_v, wide_l = _cs("d", self.nv), _cs("v", self.nv), _cs("l", self.nl)
        missing, forb = self._folded(self._missing()), self._folded(_cs("f", self.words))
        layer_v = [[F.col(f"h{j}{n}") for n in self.index.cfg.vw] for j in range(1, self.index.cfg.k + 1)]
        layer_l = [[F.col(f"h{j}{n}") for n in self.index.cfg.lw] for j in range(1, self.index.cfg.k + 1)]
        out = {"way_vertex": M.mask_contains(wide_v, d) & M.mask_contains(wide_v, _cs("o", self.nv)), "way_required": M.mask_contains(wide_l, missing)}
        forbidden, ended = F.lit(False), F.lit(False)
        for j in range(len(layer_v)):
            nearer = reduce(lambda a, b: a | b, [M.mask_contains(v, d) for v in layer_v[:j]], F.lit(False))
            forbidden = forbidden | (~M.mask_empty(layer_l[j]) & M.mask_contains(forb, layer_l[j]) & ~nearer)
            if j:
                seen = M.mask_or(*layer_l[:j])
                ended = ended | (M.mask_empty(layer_l[j]) & (~nearer | ~M.mask_contains(seen, missing)))
        target = _cs("t", self.nv)
        before = M.mask_contains(target, _cs("i", self.nv)) & M.mask_contains(target, _cs("m", self.nv))
        return out | {"way_forbidden": ~forbidden, "horizon": ~ended, "inbound": before}

    def start(self, clauses: DataFrame) -> DataFrame:
        """The first states: at each clause's source, nothing seen."""
        return clauses.select("qid", "clause", F.col("src").alias("vid"), *[F.lit(0).cast("long").alias(x) for x in M.names("s", self.words)], *self.carry)

    def expand(self, frontier: DataFrame, edges: DataFrame | None = None) -> DataFrame:
        """Distinct states one edge further (of ``edges``, without an index), and whether each answers its query.

        States bring what their clause asks along, so no hop joins the clauses; they are grouped by what makes them distinct, which is
        also how they then meet the visited ones.
        """
        live = frontier
        if self.index is not None:
            live = live.join(self.fused, "vid")
            filters = self.way_filters()
            for name, condition in filters.items():
                if name in self.rules:
                    live = live.where(condition)
            live = live.select(*self.state, "way", *self.carry)
            steps = live.withColumnRenamed("vid", "src").join(self.edges.withColumnRenamed("dst", "to"), ["src", "way"])
        else:
            steps = live.withColumnRenamed("vid", "src").join((self.edges if edges is None else edges).withColumnRenamed("dst", "to"), "src")
        steps = steps.where(M.mask_disjoint(_cs("e", self.words), _cs("f", self.words)))
        seen = [s.bitwiseOR(e.bitwiseAND(r)).alias(n) for s, e, r, n in zip(_cs("s", self.words), _cs("e", self.words), _cs("r", self.words), M.names("s", self.words), strict=True)]
        states = steps.select("qid", "clause", F.col("to").alias("vid"), *seen, *self.carry)
        states = states.groupBy(*self.state).agg(*[F.any_value(c).alias(c) for c in self.carry])
        hit = (F.col("vid") == F.col("dst")) & M.mask_contains(_cs("s", self.words), _cs("r", self.words))
        return states.withColumn("hit", F.coalesce(hit, F.lit(False)))

    def certified(self, states: DataFrame) -> DataFrame:
        """qids with a state from which only reachability is left, proved by a tree interval.

        Nothing is left to see, and no forbidden label lies beyond the vertex: a clear bit proves its absence even where labels are folded.
        """
        out = self.index.out.select("vid", *[F.col(n).alias("b" + n[1:]) for n in self.index.cfg.lw])
        done = states.where(M.mask_empty(self._missing())).join(out, "vid", "left").na.fill({"b" + n[1:]: 0 for n in self.index.cfg.lw})
        free = done.where(M.mask_disjoint(_cs("b", self.nl), self._folded(_cs("f", self.words)))).select("qid", "vid", "dst").distinct()
        at = self.index.interval
        here = at.select("vid", "tree", "root", F.col("enter").alias("e0"), F.col("leave").alias("e1"))
        there = at.select(F.col("vid").alias("dst"), "tree", "root", F.col("enter").alias("x"))
        return free.join(here, "vid").join(there, ["dst", "tree", "root"]).where("e0 <= x AND x <= e1").select("qid").distinct()

    def dominated(self, states: DataFrame, visited: DataFrame) -> DataFrame:
        """Without states that see less than another of the same clause and vertex, new or visited."""
        s = M.names("s", self.words)
        more = states.select(*self.state).unionByName(visited.select(*self.state)).select("qid", "clause", "vid", *[F.col(x).alias("x" + x) for x in s])
        bigger = M.mask_contains([more["x" + x] for x in s], [states[x] for x in s]) & ~M.mask_equal([more["x" + x] for x in s], [states[x] for x in s])
        same = (states.qid == more.qid) & (states.clause == more.clause) & (states.vid == more.vid)
        return states.join(more, same & bigger, "left_anti")

    def run(self, clauses: DataFrame, targets: bool = True) -> tuple[DataFrame, DataFrame]:
        """Hits (qid, hop) and all visited states with their round."""
        if self.index is not None:
            clauses = _target_columns(clauses, self.index)
        clauses = cut(clauses.where("clause >= 0"), "clauses")
        states = Layers(self.start(clauses).select("*", F.lit(False).alias("hit"), F.lit(0).alias("hop")), "states")
        hits, answered, hop = [], None, 0
        if self.cfg.empty_path and targets:
            hits.append(cut(clauses.where(F.col("src") == F.col("dst")).where(M.mask_empty(_cs("r", self.words))).select("qid").distinct().withColumn("hop", F.lit(0)), "hits"))
            answered = hits[0].select("qid")
        while True:
            live = states.last.drop("hit", "hop")
            if answered is not None:
                live = live.join(answered, "qid", "left_anti")
            if "certificate" in self.rules and targets:
                sure = self.certified(live)
                if not self.cfg.empty_path and hop == 0:
                    sure = sure.join(clauses.where(F.col("src") == F.col("dst")).select("qid"), "qid", "left_anti")
                sure = cut(sure.withColumn("hop", F.lit(hop)), "hits")
                hits.append(sure)
                live = live.join(sure.select("qid"), "qid", "left_anti")
            hop += 1
            t = time.time()
            counts = []
            if self.cfg.trace:
                live, _, n = cut_counted(live, "live")
                counts.append(n)
            candidates = self.expand(live)
            if self.cfg.trace:
                candidates, _, n = cut_counted(candidates, "candidates")
                counts.append(n)
            fresh = candidates.join(states.all.select(*self.state), self.state, "left_anti")
            if self.cfg.dominance:
                fresh = self.dominated(fresh, states.all)
            grown = states.add(fresh.withColumn("hop", F.lit(hop)))
            if self.cfg.trace:
                self.trace.append((hop, *counts, states.last.count() if grown else 0, time.time() - t))
            if not grown:
                break
            if targets:
                answered = states.last.where("hit").select("qid")
            if self.cfg.max_rounds is not None and hop >= self.cfg.max_rounds:
                break
        if not targets:
            return clauses.select("qid", F.lit(0).alias("hop")).limit(0), states.all.select(*self.state, "hop")
        hits.append(states.all.where("hit").select("qid", "hop"))
        return reduce(DataFrame.unionByName, hits).groupBy("qid").agg(F.min("hop").alias("hop")), states.all.select(*self.state, "hop")

    def met(self, some: DataFrame, others: DataFrame) -> DataFrame:
        """qids with a state from the source and one from the target at the same vertex that have seen all required labels together."""
        s = M.names("s", self.words)
        others = others.select("qid", "clause", "vid", *[F.col(x).alias("x" + x) for x in s])
        whole = M.mask_contains(M.mask_or(_cs("s", self.words), _cs("xs", self.words)), _cs("r", self.words))
        return some.join(others, ["qid", "clause", "vid"]).where(whole).select("qid")

    def meet(self, clauses: DataFrame) -> DataFrame:
        """qids answered by searching from both ends: with few labels, about the square root of the states of a search from one end.

        In a round, each clause goes on at the end with fewer new states; states of its other end wait. A clause with an end that has
        nothing to go on from has no walk, however far its other end might reach.
        """
        clauses = cut(clauses.where("clause >= 0"), "clauses")
        turned = clauses.withColumns({"src": F.col("dst"), "dst": F.col("src")})
        ways = self.edges, self.edges.withColumns({"src": F.col("dst"), "dst": F.col("src")})
        ends = [Layers(self.start(c), "states") for c in (clauses, turned)]
        fronts = [e.last for e in ends]
        hits = [cut(self.met(*fronts).distinct(), "hits")]
        while True:
            fronts = [f.join(hits[-1], "qid", "left_anti") for f in fronts]
            sizes = [f.groupBy("qid", "clause").agg(F.count("*").alias(n)) for f, n in zip(fronts, ("n", "m"), strict=True)]
            turn = cut(sizes[0].join(sizes[1], ["qid", "clause"]).select("qid", "clause", F.when(F.col("n") > F.col("m"), 1).otherwise(0).alias("end")), "turn")
            moving = {r["end"] for r in turn.select("end").distinct().collect()}
            if not moving:
                return reduce(DataFrame.unionByName, hits)
            fresh: list[DataFrame | None] = [None, None]
            for i in (0, 1):
                of = lambda end: fronts[i].join(turn.where(F.col("end") == end).select("qid", "clause"), ["qid", "clause"], "left_semi")  # noqa: B023, E731
                front = of(1 - i) if 1 - i in moving else None
                if i in moving:
                    new = self.expand(of(i), ways[i]).drop("hit").join(ends[i].all.select(*self.state), self.state, "left_anti")
                    if self.cfg.dominance:
                        new = self.dominated(new, ends[i].all)
                    if ends[i].add(new):
                        fresh[i] = ends[i].last
                        front = fresh[i] if front is None else front.unionByName(fresh[i])
                fronts[i] = ends[i].last.limit(0) if front is None else cut(front, "front")
            found = [self.met(f, ends[1 - i].all) for i, f in enumerate(fresh) if f is not None]
            if not found:
                continue
            hits.append(cut(reduce(DataFrame.unionByName, found).distinct(), "hits"))


def _mask_mode(queries: DataFrame, g: Graph, alphabet: list[str]) -> tuple[DataFrame, dict[str, object]]:
    """Clauses that only mark all labels of the pattern; the formulas are kept for the test at the target."""
    texts = [r[0] for r in queries.select("pattern").distinct().limit(1001).collect()]
    if len(texts) > 1000:
        raise ValueError("mask mode takes at most 1,000 distinct patterns")
    lid = {x: i for i, x in enumerate(alphabet)}
    words = M.n_words(len(alphabet))
    formulas = {t: P.simplify(P.parse_pattern(t, alphabet), lid) for t in texts}
    rows = [(t, 0, *M.to_words([lid[x] for x in P.labels_of(p)], words), *[0] * words) for t, p in formulas.items()]
    kind = "pattern string, clause int, " + ", ".join(f"{n} long" for n in M.names("r", words) + M.names("f", words))
    return queries.join(F.broadcast(queries.sparkSession.createDataFrame(rows, kind)), "pattern"), formulas


def answer(g: Graph, queries: DataFrame, index: TwoAxisIndex | None = None, cfg: SearchConfig | None = None) -> DataFrame:
    """(qid, answer) of pattern queries (qid, src, dst, pattern) with unique qids; walks may repeat vertices and edges.

    Unknown vertices and labels are simply absent. A query with src = dst also has the empty path, which has no label.
    Patterns with too many clauses are answered by their formula. ``index`` may be tables or arrays
    (:func:`pathsieve.plans.point.build`).
    """
    cfg = cfg or SearchConfig()
    if cfg.both and (index is not None or cfg.mode != "clauses" or not cfg.empty_path or cfg.max_rounds is not None):
        raise ValueError("a search from both ends takes no index, clauses only, the empty path and no bound of rounds")
    if cfg.place != "rounds" and cfg.mode == "clauses" and not cfg.dominance and cfg.max_rounds is None:
        try:
            held = point.prepared(g, index)
        except point.TooLarge:
            if cfg.place == "tasks":
                raise
        else:
            return point.answer(g, held, queries, cfg.rules, cfg.empty_path, cfg.max_clauses)
    with scratch(g.edges.sparkSession) as kept:
        return kept.keep(cut(_answer_in_rounds(g, queries, index, cfg), "answers"))


def _answer_in_rounds(g: Graph, queries: DataFrame, index: TwoAxisIndex | None, cfg: SearchConfig) -> DataFrame:
    """As :func:`answer` by states that move between tasks; what the rounds wrote is read by the result."""
    alphabet = g.alphabet()
    if cfg.mode == "mask":
        return _answer_by_mask(g, queries, cfg, alphabet)
    clauses = cut(compile_queries(queries, alphabet, cfg.max_clauses), "clauses")
    many = clauses.where("clause < 0").select("qid")
    if not many.isEmpty():
        plain, formulas = queries.join(many, "qid", "left_anti"), queries.join(many, "qid", "left_semi")
        return answer(g, plain, index, replace(cfg, place="rounds")).unionByName(_answer_by_mask(g, formulas, cfg, alphabet))
    run = _Run(g, index, cfg)
    hits = run.meet(clauses).distinct() if cfg.both else run.run(clauses)[0]
    return queries.select("qid").distinct().join(hits.select("qid", F.lit(True).alias("hit")), "qid", "left").select("qid", F.coalesce("hit", F.lit(False)).alias("answer"))


def _answer_by_mask(g: Graph, queries: DataFrame, cfg: SearchConfig, alphabet: list[str]) -> DataFrame:
    clauses, formulas = _mask_mode(queries, g, alphabet)
    run = _Run(g, None, cfg)
    _, visited = run.run(clauses.drop("pattern"), targets=False)
    bits = {x: i for i, x in enumerate(alphabet)}
    words = _cs("s", run.words)
    holds = F.lit(False)
    for text, p in formulas.items():
        holds = holds | ((F.col("pattern") == text) & P.pattern_mask_column(p, words, bits))
    arrived = visited.join(queries, "qid").where(F.col("vid") == F.col("dst"))
    arrived = arrived if cfg.empty_path else arrived.where("hop > 0")
    hits = arrived.where(holds).select("qid", F.lit(True).alias("hit")).distinct()
    return queries.select("qid").distinct().join(hits, "qid", "left").select("qid", F.coalesce("hit", F.lit(False)).alias("answer"))


def answer_shared(g: Graph, queries: DataFrame, cfg: SearchConfig | None = None) -> DataFrame:
    """(qid, answer) where many patterns are asked from the same sources: one search a source, marking the labels of all patterns.

    For patterns over few labels together; the states of a source are shared by all its queries and targets.
    """
    with scratch(g.edges.sparkSession) as kept:
        return kept.keep(cut(_answer_shared(g, queries, cfg or SearchConfig()), "answers"))


def _answer_shared(g: Graph, queries: DataFrame, cfg: SearchConfig) -> DataFrame:
    alphabet = g.alphabet()
    clauses, formulas = _mask_mode(queries, g, alphabet)
    run = _Run(g, None, cfg)
    marks = [F.bit_or(n).alias(n) for n in M.names("r", run.words)] + [F.lit(0).cast("long").alias(n) for n in M.names("f", run.words)]
    shared = clauses.groupBy("src").agg(*marks).select(F.col("src").alias("qid"), F.lit(0).alias("clause"), "src", F.lit(None).cast("long").alias("dst"), *M.names("r", run.words), *M.names("f", run.words))
    _, visited = run.run(shared, targets=False)
    holds = F.lit(False)
    for text, p in formulas.items():
        holds = holds | ((F.col("pattern") == text) & P.pattern_mask_column(p, _cs("s", run.words), {x: i for i, x in enumerate(alphabet)}))
    states = visited if cfg.empty_path else visited.where("hop > 0")
    hits = queries.join(states.select(F.col("qid").alias("src"), F.col("vid").alias("dst"), *M.names("s", run.words)), ["src", "dst"]).where(holds).select("qid", F.lit(True).alias("hit")).distinct()
    return queries.select("qid").distinct().join(hits, "qid", "left").select("qid", F.coalesce("hit", F.lit(False)).alias("answer"))


def pattern_distance(g: Graph, queries: DataFrame, cfg: SearchConfig | None = None) -> DataFrame:
    """(qid, hops): fewest edges of a walk that satisfies the pattern; null if there is none."""
    with scratch(g.edges.sparkSession) as kept:
        hits, _ = _Run(g, None, cfg or SearchConfig()).run(compile_queries(queries, g.alphabet()))
        hops = queries.select("qid").distinct().join(hits, "qid", "left").select("qid", F.col("hop").alias("hops"))
        return kept.keep(cut(hops, "hops"))


def trace(g: Graph, queries: DataFrame, index: TwoAxisIndex | None = None, rules: tuple[str, ...] = RULES) -> DataFrame:
    """(round, states, candidates, kept, seconds) of a run."""
    with scratch(g.edges.sparkSession):
        run = _Run(g, index, SearchConfig(rules=rules, trace=True))
        run.run(compile_queries(queries, g.alphabet()))
    return g.edges.sparkSession.createDataFrame(run.trace, "round int, states long, candidates long, kept long, seconds double")


def answer_from(g: Graph, sources: DataFrame, pattern: str) -> DataFrame:
    """(src, dst): all targets of each source (vid) under a pattern, by one edge or more."""
    alphabet = g.alphabet()
    queries = sources.select(F.col("vid").alias("qid"), F.col("vid").alias("src"), F.lit(None).cast("long").alias("dst"), F.lit(pattern).alias("pattern")).distinct()
    with scratch(g.edges.sparkSession) as kept:
        run = _Run(g, None, SearchConfig())
        clauses = compile_queries(queries, alphabet)
        _, visited = run.run(clauses, targets=False)
        full = visited.where("hop > 0").join(clauses.drop("src", "dst"), ["qid", "clause"]).where(M.mask_empty(run._missing()))
        return kept.keep(cut(full.select(F.col("qid").alias("src"), F.col("vid").alias("dst")).distinct(), "targets"))


def _counts_by_components(g: Graph, sources: DataFrame, clause: P.Clause) -> DataFrame:
    """(src, n): targets under one clause. Vertices with the required labels seen make a graph of their own; what a component of it reaches is counted once."""
    req, width = sorted(clause.req), 1 << len(clause.req)
    ids = cut(encode_vertices(g.vertices().withColumnRenamed("vid", "ext_id")), "ids")
    a, b = (ids.select(F.col("ext_id").alias(v), F.col("vid").alias(c)) for v, c in (("src", "a"), ("dst", "b")))
    bit = reduce(lambda x, i: F.when(F.col("label") == req[i], 1 << i).otherwise(x), range(len(req)), F.lit(0)).cast("long")
    edges = g.edges.where(~F.col("label").isin(sorted(clause.forb))) if clause.forb else g.edges
    moves = edges.select("src", "dst", bit.alias("bit")).distinct().join(a, "src").join(b, "dst").withColumn("s", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(width - 1).cast("long"))))
    moves = moves.select((F.col("a") * width + F.col("s")).alias("src"), (F.col("b") * width + F.col("s").bitwiseOR(F.col("bit"))).alias("dst"), F.lit("").alias("label")).distinct()
    starts = sources.select(F.col("vid").alias("src")).distinct().join(a, "src").select("src", (F.col("a") * width).alias("vid"))
    states = Graph(cut(moves, "moves"), g.labels)
    if (told := count_reached(states, (width, width - 1))) is not None:
        return starts.join(cut(told.where("n > 0"), "counts"), "vid").select("src", "n")
    parts, reach = closure_components(states, starts.select("vid"))
    full = parts.where(F.col("vid") % width == width - 1).groupBy(F.col("scc").alias("b")).agg(F.count("*").alias("n"))
    counts = reach.join(full, "b").groupBy("a").agg(F.sum("n").alias("n"))
    return starts.join(parts, "vid").join(counts, F.col("scc") == F.col("a")).select("src", "n")


def reach_counts(g: Graph, sources: DataFrame, pattern: str, top: int | None = None) -> DataFrame:
    """(src, n) targets under a pattern, or the ``top`` largest.

    A pattern of one clause is counted by components; of several, whose targets may be the same, from all its targets.
    """
    alphabet = g.alphabet()
    clauses = P.to_dnf(P.simplify(P.parse_pattern(pattern, alphabet), {x: i for i, x in enumerate(alphabet)}), SearchConfig.max_clauses)
    if len(clauses) == 1 and len(clauses[0].req) <= 8:
        counts = _counts_by_components(g, sources, clauses[0])
    else:
        counts = answer_from(g, sources, pattern).groupBy("src").agg(F.count("*").alias("n"))
    return counts if top is None else counts.orderBy(F.desc("n"), "src").limit(top)


def answer_allowed(g: Graph, queries: DataFrame, index: TwoAxisIndex | None = None, cfg: SearchConfig | None = None) -> DataFrame:
    """(qid, answer) of allowed-set queries (qid, src, dst, allowed), translated to patterns."""
    quoted = F.transform("allowed", lambda x: F.concat(F.lit('"'), x, F.lit('"')))
    texts = queries.select("qid", "src", "dst", F.concat(F.lit("ONLY{"), F.array_join(F.array_sort(quoted), ","), F.lit("}")).alias("pattern"))
    return answer(g, texts, index, cfg)


def quick(g: Graph, queries: DataFrame, index: TwoAxisIndex) -> DataFrame:
    """(qid, answer) of the queries that the index alone decides: refuted at the source, or certified with nothing to check."""
    run = _Run(g, index, SearchConfig())
    clauses = cut(_target_columns(compile_queries(queries, g.alphabet()), index), "clauses")
    start = run.start(clauses)
    loops = queries.where("src = dst").select("qid")
    open_states = start.join(run.fused, "vid")
    for name, condition in run.way_filters().items():
        if name in run.rules:
            open_states = open_states.where(condition)
    left = open_states.select("qid").distinct()
    true = run.certified(start).join(loops, "qid", "left_anti")
    false = queries.select("qid").distinct().join(left, "qid", "left_anti").join(loops, "qid", "left_anti")
    return true.withColumn("answer", F.lit(True)).unionByName(false.join(true, "qid", "left_anti").withColumn("answer", F.lit(False)))
