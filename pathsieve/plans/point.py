"""Pattern queries on graphs of a checked size: index and edges as arrays in every task, each query answered by one task.

The batch search of :mod:`pathsieve.plans.search` moves states between tasks and has no bound on the graph. Where the graph fits
every task, shuffling states costs more than it spares: here a task walks its queries over arrays, with the same states and the
same filters, and only queries and answers move. Masks have the words of :mod:`pathsieve.functions.masks`.
"""

from __future__ import annotations

import weakref
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathsieve.functions import masks as M
from pathsieve.functions import patterns as P
from pathsieve.operators.graph import Graph
from pathsieve.plans.index import IndexConfig, TwoAxisIndex, assign_ways

#: Edges up to which a graph is held by every task: some 100 MB with its index.
MOST_EDGES = 2_000_000
#: Entries of a group's table of visited states, edges followed at once, and labels that a clause can watch.
_VISITED, _STEP, _WATCHED = 1 << 25, 1 << 21, 20
RULES = ("way_vertex", "way_required", "way_forbidden", "inbound", "horizon", "certificate")


class TooLarge(ValueError):
    """The graph needs the batch search."""


@dataclass(frozen=True)
class PointGraph:
    """Vertices, the slots (vertex and way) of each, and the edges of each slot."""

    vids: np.ndarray
    labels: list[str]
    slot_at: np.ndarray
    way: np.ndarray
    edge_at: np.ndarray
    dst: np.ndarray
    label: np.ndarray
    index: PointIndex | None = None

    def vertex(self, ids: np.ndarray) -> np.ndarray:
        """Numbers of vertices, -1 for unknown ones."""
        if not len(self.vids):
            return np.full(len(ids), -1, np.int64)
        at = np.minimum(np.searchsorted(self.vids, ids), len(self.vids) - 1)
        return np.where(self.vids[at] == ids, at, -1)

    @property
    def src(self) -> np.ndarray:
        """The first vertex of each edge."""
        slot = np.repeat(np.arange(len(self.edge_at) - 1), np.diff(self.edge_at))
        return np.repeat(np.arange(len(self.slot_at) - 1), np.diff(self.slot_at))[slot]


@dataclass(frozen=True)
class PointIndex:
    """The two-axis index as arrays: by slot, by hop and slot, and by vertex."""

    cfg: IndexConfig
    exact: bool
    wide_v: np.ndarray
    wide_l: np.ndarray
    near_v: np.ndarray
    near_l: np.ndarray
    own: np.ndarray
    out_v: np.ndarray
    out_l: np.ndarray
    into: np.ndarray
    trees: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = field(default_factory=list)

    @property
    def nbytes(self) -> int:
        every = [self.wide_v, self.wide_l, self.near_v, self.near_l, self.own, self.out_v, self.out_l, self.into, *(a for t in self.trees for a in t)]
        return sum(a.nbytes for a in every)


def _grouped(n: int, key: np.ndarray) -> np.ndarray:
    return np.concatenate([[0], np.cumsum(np.bincount(key, minlength=n))]).astype(np.int64)


def _ragged(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    at = np.cumsum(sizes) - sizes
    return np.repeat(starts - at, sizes) + np.arange(int(sizes.sum()))


def load(g: Graph, most: int = MOST_EDGES) -> PointGraph:
    """The graph as arrays, one slot a vertex; :class:`TooLarge` beyond ``most`` edges."""
    rows = g.edges.select("src", "dst", "label").limit(most + 1).toArrow()
    if rows.num_rows > most:
        raise TooLarge(f"more than {most} edges")
    labels = g.alphabet()
    src, dst = (rows.column(c).to_numpy().astype(np.int64) for c in ("src", "dst"))
    kinds = rows.column("label").combine_chunks().dictionary_encode()
    kinds = kinds.combine_chunks() if isinstance(kinds, pa.ChunkedArray) else kinds
    lid = {x: i for i, x in enumerate(labels)}
    label = np.array([lid[x] for x in kinds.dictionary.to_pylist()], np.int64)[kinds.indices.to_numpy(zero_copy_only=False)] if len(src) else np.zeros(0, np.int64)
    vids = np.unique(np.concatenate([src, dst]))
    s, d = np.searchsorted(vids, src), np.searchsorted(vids, dst)
    order = np.lexsort((label, d, s))
    n = len(vids)
    edge_at = _grouped(n, s)
    return PointGraph(vids, labels, np.arange(n + 1), np.ones(n, np.int64), edge_at, d[order], label[order])


def _with_ways(g: PointGraph, way: np.ndarray) -> PointGraph:
    """The same edges, in order of source and way; ``way`` is given for each edge."""
    order = np.lexsort((g.label, g.dst, way, g.src))
    src, way = g.src[order], way[order]
    new = np.ones(len(src), bool)
    new[1:] = (src[1:] != src[:-1]) | (way[1:] != way[:-1])
    at = np.flatnonzero(new)
    return replace(g, slot_at=_grouped(len(g.vids), src[at]), way=way[at], edge_at=np.append(at, len(src)), dst=g.dst[order], label=g.label[order])


def _or_by(values: np.ndarray, at: np.ndarray) -> np.ndarray:
    """The OR of the rows of each group; groups are the non-empty runs that start at ``at``."""
    return np.bitwise_or.reduceat(values, at[:-1], axis=0) if len(at) > 1 else np.zeros((0, values.shape[1]), np.int64)


def _bits(bit: np.ndarray, words: int) -> np.ndarray:
    out = np.zeros((len(bit), words), np.int64)
    out[np.arange(len(bit)), bit // M.WORD] = np.int64(1) << (bit % M.WORD)
    return out


def _hash(ids: np.ndarray, bits: int, j: int) -> np.ndarray:
    a, b = M.HASHES[j]
    return ((ids * a + b) % M._PRIME) % bits


def _closed(n: int, src: np.ndarray, dst: np.ndarray, seed: np.ndarray) -> np.ndarray:
    """Masks of all vertices under out(u) = seed(u) OR out of all successors; only changed masks are sent on."""
    order = np.argsort(src, kind="stable")
    src, dst = src[order], dst[order]
    out, changed = seed.copy(), _some(seed)
    while changed.any():
        use = np.flatnonzero(changed[dst])
        s = src[use]
        if not len(s):
            break
        first = np.flatnonzero(np.concatenate([[True], s[1:] != s[:-1]]))
        sent = np.bitwise_or.reduceat(out[dst[use]], first, axis=0)
        at = s[first]
        new = out[at] | sent
        moved = _some(new ^ out[at])
        out[at] = new
        changed = np.zeros(n, bool)
        changed[at[moved]] = True
    return out


def _forest(vids: np.ndarray, src: np.ndarray, dst: np.ndarray, tree: int, seed: int = 0) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(root, enter, leave) of each vertex, by the rules of :func:`pathsieve.plans.index.tree_intervals`."""
    n = len(vids)
    keep = src != dst
    src, dst = src[keep], dst[keep]
    mix = _hash(vids + seed + 31 * tree, M._PRIME, tree % 4) if tree else vids
    is_target = np.zeros(n, bool)
    is_target[dst] = True
    level = np.flatnonzero(~is_target)
    level = level if len(level) else np.arange(min(n, 1))
    root, parent = np.full(n, -1, np.int64), np.full(n, -1, np.int64)
    root[level] = level
    at = _grouped(n, src)
    to = dst[np.argsort(src, kind="stable")]
    levels = [level]
    while len(level):
        size = at[level + 1] - at[level]
        via, found = np.repeat(level, size), to[_ragged(at[level], size)]
        fresh = root[found] < 0
        via, found = via[fresh], found[fresh]
        order = np.lexsort((vids[via], mix[via], found))
        via, found = via[order], found[order]
        first = np.concatenate([[True], found[1:] != found[:-1]]) if len(found) else np.zeros(0, bool)
        level = found[first]
        parent[level], root[level] = via[first], root[via[first]]
        if len(level):
            levels.append(level)
    size = np.ones(n, np.int64)
    for level in reversed(levels[1:]):
        np.add.at(size, parent[level], size[level])
    enter = np.zeros(n, np.int64)
    for level in levels[1:]:
        order = np.lexsort((level, parent[level]))
        level = level[order]
        total = np.cumsum(size[level]) - size[level]
        head = np.concatenate([[True], parent[level][1:] != parent[level][:-1]])
        enter[level] = enter[parent[level]] + 1 + total - total[np.maximum.accumulate(np.where(head, np.arange(len(level)), 0))]
    alone = root < 0
    root[alone] = np.flatnonzero(alone)
    return vids[root], enter, enter + size - 1


def build(g: Graph, cfg: IndexConfig | None = None, most: int = MOST_EDGES, graph: PointGraph | None = None) -> PointGraph:
    """The graph with its index, computed on arrays; equal to :func:`pathsieve.plans.index.build_index` row by row."""
    cfg = cfg or IndexConfig()
    p = graph or load(g, most)
    n, words = len(p.vids), len(cfg.lw)
    if len(p.edge_at) != n + 1:
        raise ValueError("a graph as loaded is needed, one slot a vertex")
    src, dst = p.src, p.dst
    trees = [_forest(p.vids, src, dst, t) for t in range(cfg.trees)]
    if cfg.vertex_hash is not None:
        hashed = np.array([cfg.vertex_hash.get(int(v), -1) for v in p.vids], np.int64)
        own = _bits(np.maximum(hashed, 0), len(cfg.vw)) * (hashed >= 0)[:, None]
    elif cfg.mode == "path":
        if not trees:
            raise ValueError("mode path needs the intervals")
        root, enter, leave = trees[0]
        _, group = np.unique(root, return_inverse=True)
        largest = np.zeros(n, np.int64)
        np.maximum.at(largest, group, leave)
        own = _bits(np.minimum(enter * cfg.vertex_bits // (largest[group] + 1), cfg.vertex_bits - 1), len(cfg.vw))
    else:
        own = np.zeros((n, len(cfg.vw)), np.int64)
        for j in range(cfg.n_hash):
            own |= _bits(_hash(p.vids, cfg.vertex_bits, j), len(cfg.vw))
    marks = _bits(np.arange(len(p.labels)) % cfg.label_bits, words)
    both = np.hstack([own[dst], marks[p.label]]) if n else np.zeros((0, len(cfg.vw) + words), np.int64)
    seed = np.zeros((n, both.shape[1]), np.int64)
    full = np.flatnonzero(np.diff(p.edge_at))
    seed[full] = _or_by(both, np.append(p.edge_at[:-1][full], len(src)))
    out = _closed(n, src, dst, seed)
    back = np.argsort(dst, kind="stable")
    into_seed = np.zeros((n, len(cfg.vw)), np.int64)
    if len(back):
        first = np.flatnonzero(np.concatenate([[True], dst[back][1:] != dst[back][:-1]]))
        into_seed[dst[back][first]] = np.bitwise_or.reduceat(own[src[back]], first, axis=0)
    into = _closed(n, dst, src, into_seed)
    p = _with_ways(p, _ways(g, p, cfg, src, dst, out[:, : len(cfg.vw)]))
    dst, v = p.dst, len(cfg.vw)
    here = np.hstack([own[dst], marks[p.label]]) if n else both
    wide = _or_by(np.hstack([own[dst], marks[p.label]]) | out[dst], p.edge_at) if n else both
    slot_of = np.repeat(np.arange(n), np.diff(p.slot_at))
    if cfg.include_self and n:
        wide[:, :v] |= own[slot_of]
    layers, below = [], _or_by(here, p.edge_at)
    for _ in range(cfg.k):
        layers.append(below)
        whole = np.zeros((n, v + words), np.int64)
        full = np.flatnonzero(np.diff(p.slot_at))
        whole[full] = _or_by(below, np.append(p.slot_at[:-1][full], len(below)))
        below = _or_by(whole[dst], p.edge_at)
    near = np.stack(layers) if layers else np.zeros((0, len(wide), v + words), np.int64)
    cut = np.ascontiguousarray
    index = PointIndex(cfg, len(p.labels) <= cfg.label_bits, cut(wide[:, :v]), cut(wide[:, v:]), cut(near[:, :, :v]), cut(near[:, :, v:]), own, cut(out[:, :v]), cut(out[:, v:]), into, trees)
    return replace(p, index=index)


def _ways(g: Graph, p: PointGraph, cfg: IndexConfig, src: np.ndarray, dst: np.ndarray, out: np.ndarray) -> np.ndarray:
    """The way of each edge."""
    if not len(src):
        return np.zeros(0, np.int64)
    if cfg.way_rule == "hash" and cfg.ways is None:
        new = np.concatenate([[True], (src[1:] != src[:-1]) | (dst[1:] != dst[:-1])])
        degree = np.bincount(src[new], minlength=len(p.vids))
        raw = {
            "log2": np.floor(np.log2(np.maximum(degree, 1))) + 1, "sqrt": np.ceil(np.sqrt(degree)), "linear": degree,
            "fixed": np.full(len(degree), cfg.max_ways), "one": np.ones(len(degree)),
        }[cfg.way_count]
        count = np.maximum(np.minimum(np.minimum(raw, cfg.max_ways), degree), 1).astype(np.int64)
        return _hash(p.vids[dst], M._PRIME, 1) % count[src] + 1
    spark = g.edges.sparkSession
    masks = spark.createDataFrame(pa.table({"vid": p.vids, **{x: out[:, w] for w, x in enumerate(cfg.vw)}})) if cfg.way_rule == "overlap" else None
    rows = assign_ways(g, cfg, masks.where(" OR ".join(f"{x} <> 0" for x in cfg.vw)) if masks is not None else None).toArrow()
    s, d, w = (rows.column(c).to_numpy().astype(np.int64) for c in ("src", "dst", "way"))
    key = np.searchsorted(p.vids, s) * len(p.vids) + np.searchsorted(p.vids, d)
    order = np.argsort(key)
    return w[order][np.searchsorted(key[order], src * len(p.vids) + dst)]


def from_index(g: Graph, index: TwoAxisIndex, most: int = MOST_EDGES) -> PointGraph:
    """The arrays of an index that lies in tables."""
    p, cfg = load(g, most), index.cfg
    rows = index.ways.toArrow()
    s, d, w = (rows.column(c).to_numpy().astype(np.int64) for c in ("src", "dst", "way"))
    key = p.vertex(s) * max(len(p.vids), 1) + p.vertex(d)
    order = np.argsort(key)
    p = _with_ways(p, w[order][np.searchsorted(key[order], p.src * max(len(p.vids), 1) + p.dst)] if len(key) else np.zeros(0, np.int64))
    slot_key = np.repeat(np.arange(len(p.vids)), np.diff(p.slot_at)) * (1 << 20) + p.way

    def placed(df: DataFrame, names: list[str], by_slot: bool) -> np.ndarray:
        got = df.toArrow()
        out = np.zeros((len(slot_key) if by_slot else len(p.vids), len(names)), np.int64)
        at = p.vertex(got.column("vid").to_numpy().astype(np.int64))
        if by_slot:
            at = np.searchsorted(slot_key, at * (1 << 20) + got.column("way").to_numpy().astype(np.int64))
        for i, name in enumerate(names):
            out[at, i] = got.column(name).to_numpy()
        return out

    near = [placed(index.near.where(f"hop = {hop}"), cfg.vw + cfg.lw, True) for hop in range(1, cfg.k + 1)]
    wide, out, v = placed(index.wide, cfg.vw + cfg.lw, True), placed(index.out, cfg.vw + cfg.lw, False), len(cfg.vw)
    near = np.stack(near) if near else np.zeros((0, len(slot_key), v + len(cfg.lw)), np.int64)
    trees = [tuple(placed(index.interval.where(f"tree = {t}"), ["root", "enter", "leave"], False).T) for t in range(cfg.trees)]
    into = placed(index.inbound, ["i" + x[1:] for x in cfg.vw], False)
    return replace(p, index=PointIndex(cfg, index.exact, wide[:, :v], wide[:, v:], near[:, :, :v], near[:, :, v:], placed(index.own, cfg.vw, False), out[:, :v], out[:, v:], into, trees))


def tables(spark: SparkSession, p: PointGraph) -> TwoAxisIndex:
    """The index as the tables that the batch search joins."""
    x, cfg = p.index, p.index.cfg
    slot_v = p.vids[np.repeat(np.arange(len(p.vids)), np.diff(p.slot_at))]
    frame = lambda **c: spark.createDataFrame(pa.table(c))
    words = lambda names, a: {n: a[:, i] for i, n in enumerate(names)}
    far = np.flatnonzero(x.out_l.any(axis=1) | x.out_v.any(axis=1))
    reached = np.flatnonzero(x.into.any(axis=1))
    near = None
    for hop in range(cfg.k):
        some = np.flatnonzero(x.near_v[hop].any(axis=1) | x.near_l[hop].any(axis=1))
        part = frame(vid=slot_v[some], way=p.way[some].astype(np.int32), hop=np.full(len(some), hop + 1, np.int32), **words(cfg.vw, x.near_v[hop][some]), **words(cfg.lw, x.near_l[hop][some]))
        near = part if near is None else near.unionByName(part)
    wide = frame(vid=slot_v, way=p.way.astype(np.int32), **words(cfg.vw, x.wide_v), **words(cfg.lw, x.wide_l))
    near = wide.limit(0).withColumn("hop", F.lit(0)).select("vid", "way", "hop", *cfg.vw, *cfg.lw) if near is None else near
    pairs = spark.createDataFrame(pa.table({"src": p.vids[p.src], "dst": p.vids[p.dst], "way": np.repeat(p.way, np.diff(p.edge_at)).astype(np.int32)})).distinct()
    interval = None
    for t, (root, enter, leave) in enumerate(x.trees):
        part = frame(vid=p.vids, tree=np.full(len(p.vids), t, np.int32), root=root, enter=enter, leave=leave)
        interval = part if interval is None else interval.unionByName(part)
    if interval is None:
        interval = spark.createDataFrame([], "vid long, tree int, root long, enter long, leave long")
    own = frame(vid=p.vids, **words(cfg.vw, x.own))
    out = frame(vid=p.vids[far], **words(cfg.vw, x.out_v[far]), **words(cfg.lw, x.out_l[far]))
    inbound = frame(vid=p.vids[reached], **words(["i" + n[1:] for n in cfg.vw], x.into[reached]))
    return TwoAxisIndex(cfg, own, pairs, wide, near, out, inbound, interval, x.exact)


class _Clauses:
    """Clauses of distinct patterns as look-up tables: what a label adds to the labels seen, what is missing, and whether that will do.

    A pattern with too many clauses is one that watches all its labels and is tested as a whole. Patterns that watch so many labels
    that the look-up tables would be large are kept as formulas in ``wide``. ``plain`` is a clause that asks for nothing.
    """

    def __init__(self, texts: list[str], labels: list[str], max_clauses: int, fold: int) -> None:
        lid = {x: i for i, x in enumerate(labels)}
        words, width = M.n_words(fold), max(len(labels), 1)
        self.of: dict[str, list[int]] = {}
        self.wide: dict[str, object] = {}
        adds, forb, forb_words, size, accept, missing, whole = [], [], [], [], [], [], []
        for text in texts:
            formula = P.simplify(P.parse_pattern(text, labels), lid)
            try:
                clauses = P.to_dnf(formula, max_clauses)
            except P.TooManyClauses:
                clauses = [None]
            if any(len(P.labels_of(formula) if c is None else c.req) > _WATCHED for c in clauses):
                self.wide[text] = formula
                clauses = []
            for c in clauses:
                watched = sorted(lid[x] for x in (P.labels_of(formula) if c is None else c.req))
                never = sorted(lid[x] for x in c.forb) if c is not None else []
                add, no = np.zeros(width, np.int64), np.zeros(width, bool)
                add[watched], no[never] = np.int64(1) << np.arange(len(watched)), True
                seen = np.arange(1 << len(watched))
                left = np.zeros((len(seen), words), np.int64)
                if c is None:
                    names = [labels[i] for i in watched]
                    good = np.array([P.holds(formula, {names[b] for b in range(len(names)) if m >> b & 1}) for m in seen.tolist()])
                else:
                    good = seen == len(seen) - 1
                    for b, i in enumerate(watched):
                        lacks = (seen >> b & 1) == 0
                        left[lacks, i % fold // M.WORD] |= np.int64(1) << (i % fold % M.WORD)
                line = np.zeros(words, np.int64)
                for i in never:
                    line[i % fold // M.WORD] |= np.int64(1) << (i % fold % M.WORD)
                self.of.setdefault(text, []).append(len(size))
                adds.append(add), forb.append(no), forb_words.append(line), size.append(len(seen)), accept.append(good), missing.append(left), whole.append(c is None)
            self.of.setdefault(text, [])
        self.plain = len(size)
        adds.append(np.zeros(width, np.int64)), forb.append(np.zeros(width, bool)), forb_words.append(np.zeros(words, np.int64))
        size.append(1), accept.append(np.ones(1, bool)), missing.append(np.zeros((1, words), np.int64)), whole.append(False)
        self.at = np.cumsum(size) - size if size else np.zeros(0, np.int64)
        self.size, self.whole = np.array(size, np.int64), np.array(whole, bool)
        stack = lambda a, shape, kind: np.stack(a) if a else np.zeros(shape, kind)
        self.adds, self.forb, self.forb_words = stack(adds, (0, width), np.int64), stack(forb, (0, width), bool), stack(forb_words, (0, words), np.int64)
        self.accept = np.concatenate(accept) if accept else np.zeros(0, bool)
        self.missing = np.concatenate(missing) if missing else np.zeros((0, words), np.int64)


def _has(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Rows of ``a`` that hold every bit of the row of ``b``, word by word."""
    out = (a[:, 0] & b[:, 0]) == b[:, 0]
    for w in range(1, a.shape[1]):
        out &= (a[:, w] & b[:, w]) == b[:, w]
    return out


def _some(a: np.ndarray) -> np.ndarray:
    """Rows with any bit."""
    out = a[:, 0] != 0
    for w in range(1, a.shape[1]):
        out |= a[:, w] != 0
    return out


class _Walk:
    """One task's queries over the arrays; ``effort`` counts states, slots, edges followed, new states, and what each rule cut."""

    def __init__(self, p: PointGraph, rules: tuple[str, ...], empty_path: bool, max_clauses: int) -> None:
        self.p, self.x, self.empty_path, self.max_clauses = p, p.index, empty_path, max_clauses
        self.rules = set(rules) if p.index is not None else set()
        if p.index is not None and not p.index.exact:
            self.rules.discard("way_forbidden")
        self.effort: dict[str, int] = dict.fromkeys(("rounds", "states", "slots", "edges", "kept", "label_done", *RULES), 0)

    def answers(self, src: np.ndarray, dst: np.ndarray, texts: list[str]) -> np.ndarray:
        fold = self.x.cfg.label_bits if self.x is not None else M.WORD * M.n_words(max(len(self.p.labels), 1))
        known = _Clauses(sorted(set(texts)), self.p.labels, self.max_clauses, fold)
        pairs = [(q, c) for q, t in enumerate(texts) for c in known.of[t]]
        found = np.zeros(len(texts), bool)
        for q in [q for q, t in enumerate(texts) if t in known.wide]:
            found[q] = self._alone(int(src[q]), int(dst[q]), known.wide[texts[q]])
        if not pairs:
            return found
        query, clause = np.array(pairs, np.int64).T
        if self.empty_path:
            found[query[(src == dst)[query] & known.accept[known.at[clause]]]] = True
        a, b = self.p.vertex(src)[query], self.p.vertex(dst)[query]
        use = (a >= 0) & (b >= 0) & ~found[query]
        query, clause, a, b = query[use], clause[use], a[use], b[use]
        order = np.argsort(known.size[clause], kind="stable")
        query, clause, a, b = query[order], clause[order], a[order], b[order]
        n, i = len(self.p.vids), 0
        while i < len(query):
            j = i + 1
            while j < len(query) and 2 * (j + 1 - i) * n * int(known.size[clause[j]]) <= _VISITED:
                j += 1
            self._group(known, query[i:j], clause[i:j], a[i:j], b[i:j], found)
            i = j
        return found

    def _alone(self, src: int, dst: int, formula) -> bool:
        """One query over sets of labels, for patterns of many labels."""
        if src == dst and self.empty_path and P.holds(formula, ()):
            return True
        (a, b), names = self.p.vertex(np.array([src, dst])).tolist(), P.labels_of(formula)
        if min(a, b) < 0:
            return False
        stack, seen = [(a, frozenset())], {(a, frozenset())}
        while stack:
            v, have = stack.pop()
            first, last = (int(self.p.edge_at[self.p.slot_at[x]]) for x in (v, v + 1))
            for to, label in zip(self.p.dst[first:last].tolist(), self.p.label[first:last].tolist(), strict=True):
                name = self.p.labels[label]
                state = (to, have | {name} if name in names else have)
                if to == b and P.holds(formula, state[1]):
                    return True
                if state not in seen:
                    seen.add(state)
                    stack.append(state)
        return False

    def _group(self, known: _Clauses, query, clause, a, b, found: np.ndarray) -> None:
        n, width, own = len(self.p.vids), int(known.size[clause].max()), len(query)
        free = None
        if self.x is not None:
            # States with nothing left to see and nothing forbidden beyond go on as plain reach, one for a query and vertex.
            again, first, inverse = np.unique(query, return_index=True, return_inverse=True)
            free = own + inverse
            query, clause, a, b = (np.concatenate(x) for x in ((query, again), (clause, np.full(len(again), known.plain)), (a, a[first]), (b, b[first])))
        visited = np.zeros(len(query) * n * width, bool)
        c, v, s = np.arange(own), a[:own].copy(), np.zeros(own, np.int64)
        visited[(c * n + v) * width + s] = True
        hop = 0
        while True:
            live = ~found[query[c]]
            c, v, s = c[live], v[live], s[live]
            if free is not None and len(c):
                done = self._label_done(known, clause, c, v, s) & (c < own)
                c, s = np.where(done, free[np.minimum(c, own - 1)], c), np.where(done, 0, s)
                key = (c * n + v) * width + s
                key = np.unique(np.concatenate([key[~done], key[done & ~visited[key]]]))
                visited[key] = True
                self.effort["label_done"] += int(done.sum())
                c, rest = np.divmod(key, n * width)
                v, s = np.divmod(rest, width)
            if "certificate" in self.rules and len(c):
                live = ~self._certified(known, query, clause, b, c, v, s, hop, found)
                live &= ~found[query[c]]
                self.effort["certificate"] += int((~live).sum())
                c, v, s = c[live], v[live], s[live]
            if "inbound" in self.rules and len(c):
                before = _has(self.x.into[b[c]], self.x.into[v] | self.x.own[v])
                self.effort["inbound"] += int((~before).sum())
                c, v, s = c[before], v[before], s[before]
            if not len(c):
                return
            self.effort["rounds"] += 1
            self.effort["states"] += len(c)
            hop += 1
            state, slot = self._slots(known, clause, b, c, v, s)
            size = self.p.edge_at[slot + 1] - self.p.edge_at[slot]
            ends = np.cumsum(size)
            fresh, i = [], 0
            while i < len(slot):
                j = max(i + 1, int(np.searchsorted(ends, (ends[i - 1] if i else 0) + _STEP, side="right")))
                part = np.repeat(state[i:j], size[i:j])
                edge = _ragged(self.p.edge_at[slot[i:j]], size[i:j])
                self.effort["edges"] += len(edge)
                fresh.append(self._steps(known, query, clause, b, c[part], s[part], edge, found, visited, width))
                i = j
            key = np.concatenate(fresh) if fresh else np.zeros(0, np.int64)
            self.effort["kept"] += len(key)
            c, rest = np.divmod(key, n * width)
            v, s = np.divmod(rest, width)

    def _steps(self, known, query, clause, b, c, s, edge, found, visited, width) -> np.ndarray:
        """Follow edges; the keys of the states that are new."""
        label, to = self.p.label[edge], self.p.dst[edge]
        live = ~known.forb[clause[c], label] & ~found[query[c]]
        c, s, label, to = c[live], s[live], label[live], to[live]
        s = s | known.adds[clause[c], label]
        hit = (to == b[c]) & known.accept[known.at[clause[c]] + s]
        found[query[c[hit]]] = True
        key = (c * len(self.p.vids) + to) * width + s
        key = np.unique(key[~visited[key]])
        visited[key] = True
        return key

    def _slots(self, known, clause, b, c, v, s) -> tuple[np.ndarray, np.ndarray]:
        """(state, slot) of the ways that may lead to an answer."""
        size = self.p.slot_at[v + 1] - self.p.slot_at[v]
        state, slot = np.repeat(np.arange(len(c)), size), _ragged(self.p.slot_at[v], size)
        self.effort["slots"] += len(slot)
        x = self.x
        if x is None:
            return state, slot

        def keep(rule: str, good: np.ndarray) -> None:
            nonlocal state, slot
            self.effort[rule] += int((~good).sum())
            state, slot = state[good], slot[good]

        if "way_vertex" in self.rules:
            target = x.own[b] | x.out_v[b]
            keep("way_vertex", _has(x.wide_v[slot], target[c[state]]))
        need = lambda: known.missing[known.at[clause[c[state]]] + s[state]]
        if "way_required" in self.rules:
            keep("way_required", _has(x.wide_l[slot], need()))
        for rule in ("way_forbidden", "horizon"):
            if rule not in self.rules or not len(x.near_v) or (rule == "way_forbidden" and not known.forb_words[clause].any()):
                continue
            target, bad, nearer = x.own[b[c[state]]], np.zeros(len(slot), bool), np.zeros(len(slot), bool)
            missing, forb, seen = need(), known.forb_words[clause[c[state]]], np.zeros_like(known.forb_words[clause[c[state]]])
            for hop in range(len(x.near_v)):
                layer = x.near_l[hop][slot]
                if rule == "way_forbidden":
                    bad |= _some(layer) & _has(forb, layer) & ~nearer
                elif hop:
                    bad |= ~_some(layer) & (~nearer | ~_has(seen, missing))
                nearer |= _has(x.near_v[hop][slot], target)
                seen = seen | layer
            keep(rule, ~bad)
        return state, slot

    def _label_done(self, known, clause, c, v, s) -> np.ndarray:
        """States with all labels seen and no forbidden label beyond."""
        clean = ~_some(self.x.out_l[v] & known.forb_words[clause[c]])
        return ~known.whole[clause[c]] & (s == known.size[clause[c]] - 1) & clean

    def _certified(self, known, query, clause, b, c, v, s, hop, found) -> np.ndarray:
        """States that prove their query: nothing left but plain reach, and the target in a tree interval."""
        x = self.x
        done = self._label_done(known, clause, c, v, s)
        if not self.empty_path and hop == 0:
            done &= v != b[c]
        inside = np.zeros(len(c), bool)
        for root, enter, leave in x.trees:
            inside |= (root[v] == root[b[c]]) & (enter[v] <= enter[b[c]]) & (enter[b[c]] <= leave[v])
        done &= inside
        found[query[c[done]]] = True
        return done


def _solve(batches, shared, rules, empty_path, max_clauses, counted: bool):
    for batch in batches:
        walk = _Walk(shared.value, rules, empty_path, max_clauses)
        columns = [batch.column(x) for x in ("src", "dst")]
        ends = [x.fill_null(-1).to_numpy(zero_copy_only=False).astype(np.int64) for x in columns]
        texts = batch.column("pattern").to_pylist()
        got = walk.answers(*ends, texts)
        null = np.array([x is None for c in columns for x in c.to_pylist()], bool).reshape(2, -1).any(axis=0)
        if counted:
            yield pa.RecordBatch.from_arrays([pa.array(list(walk.effort)), pa.array(list(walk.effort.values()), pa.int64())], names=["measure", "n"])
        else:
            yield pa.RecordBatch.from_arrays([batch.column("qid"), pa.array(got & ~null)], names=["qid", "answer"])


_kept: weakref.WeakKeyDictionary = weakref.WeakKeyDictionary()


def shared(g: Graph, p: PointGraph):
    """The broadcast of a graph's arrays, made once."""
    held = _kept.setdefault(g, {})
    if id(p) not in held:
        held[id(p)] = (p, g.edges.sparkSession.sparkContext.broadcast(p))
    return held[id(p)][1]


def prepared(g: Graph, index: TwoAxisIndex | PointGraph | None) -> PointGraph:
    """The arrays of a graph, with those of its index where there is one, made once."""
    if isinstance(index, PointGraph):
        return index
    held = _kept.setdefault(g, {})
    if ("made", id(index)) not in held:
        held["made", id(index)] = (index, load(g) if index is None else from_index(g, index))
    return held["made", id(index)][1]


def _dealt(queries: DataFrame) -> DataFrame:
    """Queries dealt to as many tasks as there are cores, for work that doesn't show in their number."""
    cores = queries.sparkSession.sparkContext.defaultParallelism
    return queries.select("qid", "src", "dst", "pattern").repartition(cores)


def answer(g: Graph, p: PointGraph, queries: DataFrame, rules: tuple[str, ...] = RULES, empty_path: bool = True, max_clauses: int = 64) -> DataFrame:
    """(qid, answer) of pattern queries (qid, src, dst, pattern), the same as the batch search gives; one row for each row of ``queries``."""
    held = shared(g, p)
    return _dealt(queries).mapInArrow(lambda it: _solve(it, held, rules, empty_path, max_clauses, False), f"qid {dict(queries.dtypes)['qid']}, answer boolean")


def effort(g: Graph, p: PointGraph, queries: DataFrame, rules: tuple[str, ...] = RULES, empty_path: bool = True, max_clauses: int = 64) -> DataFrame:
    """(measure, n): states, slots, edges followed and new states of a run, and how many states or slots each rule cut."""
    held = shared(g, p)
    rows = _dealt(queries).mapInArrow(lambda it: _solve(it, held, rules, empty_path, max_clauses, True), "measure string, n long")
    return rows.groupBy("measure").agg(F.sum("n").alias("n"))
