"""The two-axis index: masks of all that lies beyond each way, and of the next few hops."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pathsieve.functions import masks as M
from pathsieve.loop import Layers, cut, cut_counted, cut_with_path, remove, scratch
from pathsieve.operators.graph import Graph, condense, levels, scc


@dataclass(frozen=True)
class IndexConfig:
    """Widths, hashing and grouping.

    ``label_bits`` is 31 or a multiple of 62. ``mode`` "path" takes a vertex's bit from its place in the first tree, so it needs ``trees``. ``vertex_hash`` ({vid: bit}) and ``ways`` ({(src, dst): way}) replace the
    arithmetic rules in small worked examples.
    """

    vertex_bits: int = 124
    label_bits: int = 62
    k: int = 2
    way_rule: str = "hash"
    way_count: str = "log2"
    max_ways: int = 4
    n_hash: int = 1
    include_self: bool = False
    order: str = "fixpoint"
    trees: int = 1
    mode: str = "id"
    vertex_hash: dict | None = field(default=None, hash=False)
    ways: dict | None = field(default=None, hash=False)

    @property
    def vw(self) -> list[str]:
        return M.names("v", M.n_words(self.vertex_bits))

    @property
    def lw(self) -> list[str]:
        return M.names("l", M.n_words(self.label_bits))


def _cols(names: list[str], prefix: str = "") -> list[Column]:
    return [F.col(prefix + n) for n in names]


def own_bits(vertices: DataFrame, cfg: IndexConfig, interval: DataFrame | None = None) -> DataFrame:
    """(vid, v...): each vertex's own bits, by id, by a given table, or by place in a depth-first forest (mode "path")."""
    if cfg.vertex_hash is not None:
        rows = vertices.sparkSession.createDataFrame([(int(k), int(b)) for k, b in cfg.vertex_hash.items()], "vid long, bit long")
        return vertices.join(F.broadcast(rows), "vid", "left").select("vid", *[F.coalesce(M.bit_word(F.col("bit"), w), F.lit(0).cast("long")).alias(n) for w, n in enumerate(cfg.vw)])
    if cfg.mode == "path":
        if interval is None:
            raise ValueError("mode path needs the intervals")
        first = interval.where("tree = 0").groupBy("root").agg(F.max("leave").alias("size"))
        placed = interval.where("tree = 0").join(first, "root").select("vid", F.least(F.floor(F.col("enter") * cfg.vertex_bits / (F.col("size") + 1)), F.lit(cfg.vertex_bits - 1)).cast("long").alias("bit"))
        return vertices.join(placed, "vid").select("vid", *[M.bit_word(F.col("bit"), w).alias(n) for w, n in enumerate(cfg.vw)])
    return vertices.select("vid", *[c.alias(n) for c, n in zip(M.vertex_words(F.col("vid"), cfg.vertex_bits, cfg.n_hash), cfg.vw, strict=True)])


def label_words(labels: DataFrame, cfg: IndexConfig) -> DataFrame:
    """(label, l...): one bit for each label, folded where there are more labels than bits."""
    return labels.select("label", *[M.bit_word((F.col("lid") % cfg.label_bits).cast("long"), w).alias(n) for w, n in enumerate(cfg.lw)])


def adjacency(g: Graph, cfg: IndexConfig) -> DataFrame:
    """(src, dst, l...): one row for each pair, label bits ORed."""
    marked = g.edges.join(label_words(g.labels, cfg), "label")
    return marked.groupBy("src", "dst").agg(*[F.bit_or(n).alias(n) for n in cfg.lw])


def _fixpoint(adj: DataFrame, own: DataFrame, names: list[str], seed: DataFrame, first: DataFrame | None = None) -> DataFrame:
    """out(u) = seed(u) OR out of all successors; only rows with new bits are sent on, at the start those of ``first``."""
    state, path = cut_with_path(seed, "masks")
    delta = state if first is None else first
    pairs = cut(adj.select("src", "dst"), "pairs")
    while True:
        sent = pairs.join(delta.withColumnRenamed("vid", "dst"), "dst").groupBy(F.col("src").alias("vid")).agg(*[F.bit_or(n).alias("n_" + n) for n in names])
        merged = state.join(sent, "vid", "left").select(
            "vid", *[F.col(n).bitwiseOR(F.coalesce("n_" + n, F.lit(0).cast("long"))).alias(n) for n in names],
            reduce(lambda a, b: a | b, [F.coalesce("n_" + n, F.lit(0).cast("long")).bitwiseAND(F.bitwise_not(n)) != 0 for n in names]).alias("changed"),
        )
        new, new_path, changed = cut_counted(merged, "masks", F.col("changed"))
        delta = new.where("changed").drop("changed")
        last, path, state = path, new_path, new.drop("changed")
        remove(state.sparkSession, last)
        if not changed:
            return state


def _seed(adj: DataFrame, own: DataFrame, cfg: IndexConfig, labels: bool) -> DataFrame:
    kept = cfg.vw + (cfg.lw if labels else [])
    rows = adj.join(own.withColumnRenamed("vid", "dst"), "dst")
    return rows.groupBy(F.col("src").alias("vid")).agg(*[F.bit_or(n).alias(n) for n in kept])


def outbound_masks(g: Graph, cfg: IndexConfig, labels: bool = True, own: DataFrame | None = None, adj: DataFrame | None = None, at: DataFrame | None = None) -> DataFrame:
    """(vid, v..., l...): bits of all vertices and labels beyond each vertex that has successors.

    ``order``: "fixpoint" (any graph), "levels" (acyclic: one step a level, each edge once), "scc" (masks of the condensed graph,
    which is acyclic, shared by a component's members). Own bits, adjacency and levels can be given, so that they are made once.
    """
    adj = cut(adjacency(g, cfg), "adj") if adj is None else adj
    own = cut(own_bits(g.vertices(), cfg, _placed(g, cfg)), "own") if own is None else own
    names = cfg.vw + (cfg.lw if labels else [])
    if cfg.order == "fixpoint":
        return _fixpoint(adj, own, names, _seed(adj, own, cfg, labels))
    if cfg.order == "levels":
        return _by_levels(adj, own, names, _seed(adj, own, cfg, labels), graph_levels(g) if at is None else at)
    if cfg.order == "scc":
        return _by_components(g, cfg, adj, own, names)
    raise ValueError(f"unknown order {cfg.order}")


def _placed(g: Graph, cfg: IndexConfig) -> DataFrame | None:
    """The intervals, where own bits come from them."""
    return cut(tree_intervals(g, 1), "interval") if cfg.mode == "path" else None


def graph_levels(g: Graph) -> DataFrame:
    """The levels of an acyclic graph."""
    at = cut(levels(g), "levels")
    if not g.vertices().join(at, "vid", "left_anti").isEmpty():
        raise ValueError("order levels needs an acyclic graph")
    return at


def _by_levels(adj: DataFrame, own: DataFrame, names: list[str], seed: DataFrame, at: DataFrame, falling: bool = False) -> DataFrame:
    """Masks level by level, each made from finished ones; ``falling`` starts with the highest level, for predecessors."""
    seed = cut(seed.join(at, "vid"), "seed")
    steps = cut(adj.select("src", "dst").join(at.withColumnRenamed("vid", "src"), "src"), "steps")
    top = at.agg(F.max("level")).first()[0] or 0
    done = Layers(seed.limit(0).drop("level"), "level")
    for level in range(top, -1, -1) if falling else range(top + 1):
        below = steps.where(f"level = {level}").join(done.all.withColumnRenamed("vid", "dst"), "dst").groupBy(F.col("src").alias("vid")).agg(*[F.bit_or(n).alias("n_" + n) for n in names])
        done.add(seed.where(f"level = {level}").join(below, "vid", "left").select("vid", *[F.col(n).bitwiseOR(F.coalesce("n_" + n, F.lit(0).cast("long"))).alias(n) for n in names]))
    return done.all


def _by_components(g: Graph, cfg: IndexConfig, adj: DataFrame, own: DataFrame, names: list[str]) -> DataFrame:
    c = cut(scc(g), "scc")
    s, d = c.select(F.col("vid").alias("src"), F.col("scc").alias("s")), c.select(F.col("vid").alias("dst"), F.col("scc").alias("d"))
    whole = adj.join(own.withColumnRenamed("vid", "dst"), "dst").join(s, "src").join(d, "dst")
    seed = whole.groupBy(F.col("s").alias("vid")).agg(*[F.bit_or(n).alias(n) for n in names])
    above = whole.where("s <> d").select(F.col("s").alias("src"), F.col("d").alias("dst")).distinct()
    closed = _fixpoint(above, own, names, seed)
    return c.join(closed.withColumnRenamed("vid", "scc"), "scc").select("vid", *names)


def extend_masks(state: DataFrame, g: Graph, added: DataFrame, cfg: IndexConfig) -> DataFrame:
    """Outbound masks after edges (src, dst, label) were added to ``g``, which already holds them.

    Masks only grow under insertion, so the masks of the new edges' sources are widened and the new bits sent on. Labels must keep
    their numbers: new ones come last.
    """
    adj = cut(adjacency(g, cfg), "adj")
    own = cut(own_bits(g.vertices(), cfg, _placed(g, cfg)), "own")
    names = cfg.vw + cfg.lw
    touched = added.select(F.col("src").alias("vid")).distinct()
    seed = _seed(adj.join(touched.withColumnRenamed("vid", "src"), "src", "left_semi"), own, cfg, labels=True)
    beyond = adj.join(touched.withColumnRenamed("vid", "src"), "src", "left_semi").select("src", "dst").join(state.withColumnRenamed("vid", "dst"), "dst").select(F.col("src").alias("vid"), *names)
    merged = cut(state.unionByName(seed).unionByName(beyond).groupBy("vid").agg(*[F.bit_or(n).alias(n) for n in names]), "masks")
    return _fixpoint(adj, own, names, merged, merged.join(touched, "vid", "left_semi"))


def inbound_masks(g: Graph, cfg: IndexConfig, own: DataFrame | None = None, adj: DataFrame | None = None, at: DataFrame | None = None) -> DataFrame:
    """(vid, i...): bits of the vertices that reach each vertex; vertices without a predecessor have no row."""
    own = cut(own_bits(g.vertices(), cfg, _placed(g, cfg)), "own") if own is None else own
    if cfg.order == "scc":
        out = outbound_masks(g.reverse(), cfg, labels=False, own=own)
    else:
        adj = cut(g.edges.select("src", "dst").distinct(), "pairs") if adj is None else adj
        back = adj.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
        seed = _seed(back, own, cfg, labels=False)
        if cfg.order == "levels":
            out = _by_levels(back, own, cfg.vw, seed, graph_levels(g) if at is None else at, falling=True)
        else:
            out = _fixpoint(back, own, cfg.vw, seed)
    return out.select("vid", *[F.col(n).alias("i" + n[1:]) for n in cfg.vw])


def assign_ways(g: Graph, cfg: IndexConfig, out: DataFrame | None = None) -> DataFrame:
    """(src, dst, way): the group of each out-branch; all labels of a pair share it.

    Rules: "hash" of the successor, "rank" (equal runs by id), "overlap" (equal runs by mask, so branches that share vertices
    fall together; needs ``out``), "label" (runs by smallest label). The number of ways follows the out-degree.
    """
    spark = g.edges.sparkSession
    if cfg.ways is not None:
        rows = spark.createDataFrame([(int(s), int(d), int(w)) for (s, d), w in cfg.ways.items()], "src long, dst long, way int")
        return g.edges.select("src", "dst").distinct().join(rows, ["src", "dst"], "left").select("src", "dst", F.coalesce("way", F.lit(1)).alias("way"))
    pairs = g.edges.groupBy("src", "dst").agg(F.min("label").alias("label"))
    count = way_count(F.col("deg"), cfg)
    sized = pairs.join(pairs.groupBy("src").agg(F.count("*").alias("deg")), "src").withColumn("g", count)
    if cfg.way_rule == "hash":
        return sized.select("src", "dst", (M.hash_bit(F.col("dst"), 2147483647, 1) % F.col("g") + 1).cast("int").alias("way"))
    if cfg.way_rule == "overlap":
        if out is None:
            raise ValueError("way rule overlap needs the outbound masks")
        sized = sized.join(out.select(F.col("vid").alias("dst"), *cfg.vw), "dst", "left")
    by = {"rank": ["dst"], "label": ["label", "dst"], "overlap": [*cfg.vw, "dst"]}[cfg.way_rule]
    place = F.row_number().over(Window.partitionBy("src").orderBy(*by)) - 1
    return sized.select("src", "dst", (F.floor(place * F.col("g") / F.col("deg")) + 1).cast("int").alias("way"))


def way_count(degree: Column, cfg: IndexConfig) -> Column:
    """Ways of a vertex by its out-degree: "log2", "sqrt", "linear", "fixed" or "one", at most ``max_ways`` and the degree."""
    raw = {"log2": F.floor(F.log2(degree)) + 1, "sqrt": F.ceil(F.sqrt(degree)), "linear": degree, "fixed": F.lit(cfg.max_ways), "one": F.lit(1)}[cfg.way_count]
    return F.greatest(F.least(raw, F.lit(cfg.max_ways), degree), F.lit(1)).cast("int")


def wide_index(g: Graph, cfg: IndexConfig, ways: DataFrame, out: DataFrame, own: DataFrame, adj: DataFrame | None = None) -> DataFrame:
    """(vid, way, v..., l...): bits beyond each way."""
    adj = adjacency(g, cfg) if adj is None else adj
    zero = F.lit(0).cast("long")
    child = out.select(F.col("vid").alias("dst"), *[F.col(n).alias("o_" + n) for n in cfg.vw + cfg.lw])
    mine = own.select(F.col("vid").alias("dst"), *[F.col(n).alias("w_" + n) for n in cfg.vw])
    rows = adj.join(ways, ["src", "dst"]).join(child, "dst", "left").join(mine, "dst")
    merged = rows.groupBy(F.col("src").alias("vid"), "way").agg(
        *[F.bit_or(F.col("w_" + n).bitwiseOR(F.coalesce("o_" + n, zero))).alias(n) for n in cfg.vw],
        *[F.bit_or(F.col(n).bitwiseOR(F.coalesce("o_" + n, zero))).alias(n) for n in cfg.lw],
    )
    if not cfg.include_self:
        return merged
    return merged.join(own.select("vid", *[F.col(n).alias("s_" + n) for n in cfg.vw]), "vid").select("vid", "way", *[F.col(n).bitwiseOR(F.col("s_" + n)).alias(n) for n in cfg.vw], *cfg.lw)


def near_index(g: Graph, cfg: IndexConfig, ways: DataFrame, own: DataFrame, adj: DataFrame | None = None) -> DataFrame:
    """(vid, way, hop, v..., l...): vertices and labels exactly ``hop`` edges away through each way, hops 1 to k.

    Each layer is the children's layer before, merged over all their ways; a missing layer is empty.
    """
    adj = cut((adjacency(g, cfg) if adj is None else adj).join(ways, ["src", "dst"]), "ways")
    names = cfg.vw + cfg.lw
    first = adj.join(own.withColumnRenamed("vid", "dst"), "dst").groupBy(F.col("src").alias("vid"), "way").agg(*[F.bit_or(n).alias(n) for n in names])
    layers = [cut(first.withColumn("hop", F.lit(1)), "layer")] if cfg.k else []
    for hop in range(2, cfg.k + 1):
        below = layers[-1].groupBy(F.col("vid").alias("dst")).agg(*[F.bit_or(n).alias(n) for n in names])
        up = adj.select("src", "dst", "way").join(below, "dst").groupBy(F.col("src").alias("vid"), "way").agg(*[F.bit_or(n).alias(n) for n in names])
        layers.append(cut(up.withColumn("hop", F.lit(hop)), "layer"))
    out = first.limit(0).withColumn("hop", F.lit(0)) if not layers else layers[0]
    for x in layers[1:]:
        out = out.unionByName(x)
    return out.select("vid", "way", "hop", *names)


def tree_intervals(g: Graph, trees: int = 1, seed: int = 0) -> DataFrame:
    """(vid, tree, root, enter, leave): intervals in breadth-first forests; containment under one root proves a path.

    Roots are vertices without predecessors, or the least vertex where there are none; a vertex that no root reaches is a tree of its own.
    Sizes are summed from the deepest level up, and places dealt out from the roots down.
    """
    out = None
    pairs = cut(g.edges.select("src", "dst").where("src <> dst").distinct(), "pairs")
    for tree in range(trees):
        mix = M.hash_bit(F.col("src") + seed + 31 * tree, 2147483647, tree % 4) if tree else F.col("src")
        targets = pairs.select(F.col("dst").alias("vid")).distinct()
        starts = cut(g.vertices().join(targets, "vid", "left_anti"), "roots")
        if starts.isEmpty():
            starts = g.vertices().agg(F.min("vid").alias("vid")).where("vid IS NOT NULL")
        forest = Layers(starts.select("vid", F.col("vid").alias("root"), F.lit(None).cast("long").alias("parent")), "forest")
        while True:
            step = pairs.join(forest.last.select(F.col("vid").alias("src"), "root"), "src").join(forest.all.select(F.col("vid").alias("dst")), "dst", "left_anti")
            best = step.groupBy(F.col("dst").alias("vid")).agg(F.min_by(F.struct("src", "root"), F.struct(mix, "src")).alias("x"))
            if not forest.add(best.select("vid", "x.root", F.col("x.src").alias("parent"))):
                break
        sized, size_of = [], None
        for level in reversed(forest.each):
            here = level.withColumn("own", F.lit(1).cast("long"))
            if size_of is not None:
                sums = size_of.groupBy(F.col("parent").alias("vid")).agg(F.sum("size").alias("below"))
                here = here.join(sums, "vid", "left")
            else:
                here = here.withColumn("below", F.lit(0).cast("long"))
            size_of = cut(here.select("vid", "root", "parent", (F.col("own") + F.coalesce("below", F.lit(0))).alias("size")), "sizes")
            sized.append(size_of)
        sized.reverse()
        placed = Layers(sized[0].select("vid", "root", F.lit(0).cast("long").alias("enter"), "size"), "places")
        for level in sized[1:]:
            w = Window.partitionBy("parent").orderBy("vid").rowsBetween(Window.unboundedPreceding, -1)
            ranked = level.withColumn("before", F.coalesce(F.sum("size").over(w), F.lit(0)))
            up = placed.last.select(F.col("vid").alias("parent"), F.col("enter").alias("up"))
            placed.add(ranked.join(up, "parent").select("vid", "root", (F.col("up") + 1 + F.col("before")).alias("enter"), "size"))
        every = placed.all
        alone = g.vertices().join(every, "vid", "left_anti").select("vid", F.col("vid").alias("root"), F.lit(0).cast("long").alias("enter"), F.lit(1).cast("long").alias("size"))
        made = cut(every.unionByName(alone).select("vid", F.lit(tree).alias("tree"), "root", "enter", (F.col("enter") + F.col("size") - 1).alias("leave")), "intervals")
        out = made if out is None else out.unionByName(made)
    return out


def walk_intervals(g: Graph) -> DataFrame:
    """The same table by one depth-first walk in one task, counting pushes and pops as the reference does; for small graphs and tests.

    Roots are walked in order of id, successors too; what no root reaches is walked from its least vertex.
    """
    import pandas as pd

    def walk(frames):
        rows = pd.concat([pd.DataFrame({"src": [], "dst": []}, dtype="int64"), *frames])
        nexts: dict[int, list[int]] = {}
        for s, d in sorted(set(zip(rows["src"], rows["dst"], strict=True))):
            nexts.setdefault(int(s), []).append(int(d))
        vertices = sorted({int(v) for v in rows["src"]} | {int(v) for v in rows["dst"]})
        targets = {d for s, ds in nexts.items() for d in ds if d != s}
        enter, leave, made = {}, {}, []
        for start in [v for v in vertices if v not in targets] + vertices:
            if start in enter:
                continue
            clock, stack = 0, [(start, iter(nexts.get(start, ())))]
            enter[start], own = clock, [start]
            while stack:
                v, rest = stack[-1]
                to = next((x for x in rest if x not in enter), None)
                clock += 1
                if to is None:
                    leave[v] = clock
                    stack.pop()
                else:
                    enter[to] = clock
                    own.append(to)
                    stack.append((to, iter(nexts.get(to, ()))))
            made += [(v, 0, start, enter[v], leave[v]) for v in own]
        yield pd.DataFrame(made, columns=["vid", "tree", "root", "enter", "leave"])

    return g.edges.select("src", "dst").repartition(1).mapInPandas(walk, "vid long, tree int, root long, enter long, leave long")


def claimed_pairs(intervals: DataFrame) -> DataFrame:
    """(src, dst): each vertex with those whose place lies in its interval (vid, tree, root, enter, leave) after its own.

    An interval is the union of at most two blocks of each power of two, and a place lies in one block of each: so both meet on equal
    blocks, and the join makes the pairs that hold and no others.
    """
    top = intervals.agg(F.max("leave")).first()[0] or 0
    levels = F.explode(F.sequence(F.lit(0), F.lit(int(top + 1).bit_length())))
    low, high = F.expr("-shiftright(-(enter + 1), level)"), F.expr("shiftright(leave + 1, level)")
    up = intervals.where("enter < leave").select("tree", "root", F.col("vid").alias("src"), "enter", "leave", levels.alias("level"))
    up = up.select("tree", "root", "src", "level", low.alias("low"), high.alias("high")).where("low < high")
    ends = F.expr("filter(array(IF(low % 2 = 1, low, NULL), IF(high % 2 = 1, high - 1, NULL)), x -> x IS NOT NULL)")
    up = up.select("tree", "root", "src", "level", F.explode(ends).alias("block"))
    at = intervals.select("tree", "root", F.col("vid").alias("dst"), "enter", levels.alias("level"))
    at = at.select("tree", "root", "dst", "level", F.expr("shiftright(enter, level)").alias("block"))
    return up.join(at, ["tree", "root", "level", "block"]).select("src", "dst")


@dataclass(frozen=True)
class TwoAxisIndex:
    """All tables of an index; ``exact`` tells whether each label has a bit of its own."""

    cfg: IndexConfig
    own: DataFrame
    ways: DataFrame
    wide: DataFrame
    near: DataFrame
    out: DataFrame
    inbound: DataFrame
    interval: DataFrame
    exact: bool

    _TABLES = ("own", "ways", "wide", "near", "out", "inbound", "interval")

    def fused(self) -> DataFrame:
        """One row for each (vid, way): wide masks and the layers side by side, absent ones empty."""
        out = self.wide
        for hop in range(1, self.cfg.k + 1):
            layer = self.near.where(f"hop = {hop}").select("vid", "way", *[F.col(n).alias(f"h{hop}{n}") for n in self.cfg.vw + self.cfg.lw])
            out = out.join(layer, ["vid", "way"], "left")
        return out.na.fill(0)

    def save(self, path: str, buckets: int | None = None) -> None:
        """Write the tables under ``path`` with a description; rows of a vertex lie together."""
        spark = self.wide.sparkSession
        for t in self._TABLES:
            df = getattr(self, t)
            key = "src" if t == "ways" else "vid"
            (df.repartition(buckets, key) if buckets else df.repartition(key)).sortWithinPartitions(key).write.parquet(f"{path}/{t}")
        cfg = asdict(self.cfg) | {"vertex_hash": None, "ways": None}
        spark.createDataFrame([(json.dumps(cfg), self.exact)], "cfg string, exact boolean").coalesce(1).write.parquet(f"{path}/meta")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> TwoAxisIndex:
        meta = spark.read.parquet(f"{path}/meta").first()
        return cls(IndexConfig(**json.loads(meta["cfg"])), *[spark.read.parquet(f"{path}/{t}") for t in cls._TABLES], meta["exact"])

    def save_tables(self, prefix: str, buckets: int) -> None:
        """As tables of the catalogue, bucketed and sorted by vertex, so that joins between them on the vertex shuffle nothing."""
        spark = self.wide.sparkSession
        for t in self._TABLES:
            key = "src" if t == "ways" else "vid"
            getattr(self, t).write.bucketBy(buckets, key).sortBy(key).mode("errorifexists").format("parquet").saveAsTable(f"{prefix}_{t}")
        cfg = asdict(self.cfg) | {"vertex_hash": None, "ways": None}
        spark.createDataFrame([(json.dumps(cfg), self.exact)], "cfg string, exact boolean").coalesce(1).write.format("parquet").saveAsTable(f"{prefix}_meta")

    @classmethod
    def load_tables(cls, spark: SparkSession, prefix: str) -> TwoAxisIndex:
        meta = spark.table(f"{prefix}_meta").first()
        return cls(IndexConfig(**json.loads(meta["cfg"])), *[spark.table(f"{prefix}_{t}") for t in cls._TABLES], meta["exact"])

    def register_views(self, prefix: str) -> None:
        for t in self._TABLES:
            getattr(self, t).createOrReplaceTempView(f"{prefix}_{t}")


def build_index(g: Graph, cfg: IndexConfig | None = None) -> TwoAxisIndex:
    """Build every table once, on shared storage; adjacency, own bits and levels are shared by all steps."""
    cfg = cfg or IndexConfig()
    with scratch(g.edges.sparkSession) as held:
        none = g.vertices().limit(0).select("vid", F.lit(0).alias("tree"), F.col("vid").alias("root"), F.col("vid").alias("enter"), F.col("vid").alias("leave"))
        interval = held.keep(cut(tree_intervals(g, cfg.trees) if cfg.trees else none, "interval"))
        adj = cut(adjacency(g, cfg), "adj")
        own = held.keep(cut(own_bits(g.vertices(), cfg, interval if cfg.trees else None), "own"))
        at = graph_levels(g) if cfg.order == "levels" else None
        out = held.keep(cut(outbound_masks(g, cfg, own=own, adj=adj, at=at), "out"))
        ways = held.keep(cut(assign_ways(g, cfg, out), "ways"))
        wide = held.keep(cut(wide_index(g, cfg, ways, out, own, adj), "wide"))
        near = held.keep(cut(near_index(g, cfg, ways, own, adj), "near"))
        inbound = held.keep(cut(inbound_masks(g, cfg, own, adj, at), "inbound"))
    exact = (g.labels.agg(F.count("*")).first()[0] or 0) <= cfg.label_bits
    return TwoAxisIndex(cfg, own, ways, wide, near, out, inbound, interval, exact)
