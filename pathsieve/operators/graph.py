"""The graph model and its elementary operators."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pathsieve.functions import masks as M
from pathsieve.loop import Layers, cut, cut_counted, cut_with_path, remove, scratch

_EDGES = "src bigint, dst bigint, label string"


@dataclass(frozen=True)
class Graph:
    """Distinct edges (src, dst, label) and the label dictionary (label, lid)."""

    edges: DataFrame
    labels: DataFrame

    @classmethod
    def from_edges(cls, df: DataFrame, src: str = "src", dst: str = "dst", label: str = "label", loops: bool = True) -> Graph:
        """A graph from any table; rows with a null in a key column are no edges."""
        rows = df.select(F.col(src).cast("long").alias("src"), F.col(dst).cast("long").alias("dst"), F.col(label).cast("string").alias("label")).na.drop()
        rows = rows if loops else rows.where("src <> dst")
        edges = rows.dropDuplicates(["src", "dst", "label"])
        return cls(edges, encode_labels(edges))

    @classmethod
    def from_sql(cls, spark: SparkSession, sql: str) -> Graph:
        return cls.from_edges(spark.sql(sql))

    @classmethod
    def of(cls, spark: SparkSession, rows) -> Graph:
        """A small graph from (src, dst, label) tuples."""
        return cls.from_edges(spark.createDataFrame(list(rows), _EDGES))

    def stored(self) -> Graph:
        """The same graph read from tables on shared storage."""
        edges = cut(self.edges, "graph")
        return Graph(edges, cut(encode_labels(edges), "alphabet"))

    def reverse(self) -> Graph:
        return Graph(self.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "label"), self.labels)

    def where(self, condition: str | Column) -> Graph:
        edges = self.edges.where(condition)
        return Graph(edges, encode_labels(edges))

    def vertices(self) -> DataFrame:
        return self.edges.select(F.col("src").alias("vid")).union(self.edges.select("dst")).distinct()

    def alphabet(self) -> list[str]:
        """Labels by lid; an alphabet is small by nature, and more than 100,000 labels are refused."""
        rows = self.labels.orderBy("lid").limit(100_001).collect()
        if len(rows) > 100_000:
            raise ValueError("more than 100,000 labels")
        return [r["label"] for r in rows]


def split_labels(df: DataFrame, column: str = "labels") -> DataFrame:
    """One row for each label of an array column."""
    rest = [c for c in df.columns if c != column]
    return df.select(*rest, F.explode(column).alias("label")).distinct()


def encode_labels(edges: DataFrame, order: str = "name") -> DataFrame:
    """(label, lid) with dense numbers by name or by falling frequency; one row for each label."""
    counts = edges.groupBy("label").agg(F.count("*").alias("n"))
    by = [F.desc("n"), F.col("label")] if order == "freq" else [F.col("label")]
    return counts.select("label", (F.row_number().over(Window.orderBy(*by)) - 1).cast("int").alias("lid"))


def encode_vertices(df: DataFrame, column: str = "ext_id") -> DataFrame:
    """(ext_id, vid) with dense ids in the order of ``column``, without a single-task window.

    Rows are range-partitioned; each partition numbers its rows and adds the rows before it, one number a partition.
    """
    ranged = df.select(F.col(column).alias("ext_id")).na.drop().distinct().repartitionByRange("ext_id").sortWithinPartitions("ext_id")
    placed = cut(ranged.withColumn("part", F.spark_partition_id()).withColumn("seq", F.monotonically_increasing_id()), "ids")
    sizes = placed.groupBy("part").agg(F.count("*").alias("n"), F.min("seq").alias("low"))
    before = sizes.select("part", "low", (F.sum("n").over(Window.orderBy("part")) - F.col("n")).alias("before"))
    return placed.join(F.broadcast(before), "part").select("ext_id", (F.col("before") + F.col("seq") - F.col("low")).cast("long").alias("vid"))


def successors(g: Graph) -> DataFrame:
    return g.edges.select(F.col("src").alias("vid"), F.col("dst").alias("nbr")).distinct()


def predecessors(g: Graph) -> DataFrame:
    return successors(g.reverse())


def degrees(g: Graph) -> DataFrame:
    """(vid, n_out, n_in): distinct successors and predecessors."""
    pairs = g.edges.select("src", "dst").distinct()
    out = pairs.groupBy(F.col("src").alias("vid")).agg(F.count("*").alias("n_out"))
    into = pairs.groupBy(F.col("dst").alias("vid")).agg(F.count("*").alias("n_in"))
    return out.join(into, "vid", "full").select("vid", F.coalesce("n_out", F.lit(0)).alias("n_out"), F.coalesce("n_in", F.lit(0)).alias("n_in"))


def roots(g: Graph) -> DataFrame:
    return g.edges.select(F.col("src").alias("vid")).distinct().join(g.edges.select(F.col("dst").alias("vid")), "vid", "left_anti")


def leaves(g: Graph) -> DataFrame:
    return roots(g.reverse())


def approximate_stats(g: Graph, error: float = 0.02) -> DataFrame:
    """(n_vertices, n_pairs, n_labels) within about ``error``, by sketches that merge before the shuffle."""
    ends = g.edges.select(F.explode(F.array("src", "dst")).alias("vid")).agg(F.approx_count_distinct("vid", error).alias("n_vertices"))
    rest = g.edges.agg(F.approx_count_distinct(F.struct("src", "dst"), error).alias("n_pairs"), F.approx_count_distinct("label", error).alias("n_labels"))
    return ends.crossJoin(rest)


def graph_stats(g: Graph) -> DataFrame:
    """One row: vertices, edges, labels, pairs, roots, leaves, largest out-degree, edges a vertex, and the skew of out-degrees.

    Skew is the largest out-degree over the mean one.
    """
    d = degrees(g)
    a = g.edges.agg(F.count("*").alias("n_edges"), F.count_distinct("label").alias("n_labels"))
    b = d.agg(F.count("*").alias("n_vertices"), F.sum("n_out").alias("n_pairs"), F.count_if(F.col("n_in") == 0).alias("n_roots"), F.count_if(F.col("n_out") == 0).alias("n_leaves"), F.max("n_out").alias("max_out"))
    mean, skew = F.col("n_edges") / F.col("n_vertices"), F.col("max_out") * F.col("n_vertices") / F.col("n_pairs")
    return a.crossJoin(b).select("n_vertices", "n_edges", "n_labels", "n_pairs", "n_roots", "n_leaves", "max_out", mean.alias("mean_degree"), skew.alias("skew"))


def assign_labels(edges: DataFrame, z: int, seed: int = 7) -> DataFrame:
    """Uniform labels L0..L(z-1) by an arithmetic mix of the pair, equal in any engine."""
    mix = ((F.col("src") * 48271 + F.col("dst") * 69621 + seed * 7919) % 2147483647 * 16807) % 2147483647 % z
    return edges.select("src", "dst", F.concat(F.lit("L"), mix.cast("string")).alias("label")).distinct()


def label_set(path: Column) -> Column:
    """Distinct labels of an array of edge structs, sorted."""
    return F.array_sort(F.array_distinct(F.transform(path, lambda e: e["label"])))


def closure_vertices(g: Graph, sources: DataFrame | None = None, max_rounds: int | None = None) -> DataFrame:
    """(src, dst, hops): all vertices that each source reaches over one edge or more, with the fewest hops."""
    pairs = cut(g.edges.select("src", "dst").distinct(), "pairs")
    start = pairs if sources is None else pairs.join(sources.select(F.col("vid").alias("src")).distinct(), "src", "left_semi")
    found, step = Layers(start.withColumn("hops", F.lit(1)), "reach"), 1
    while max_rounds is None or step < max_rounds:
        step += 1
        onward = found.last.select("src", F.col("dst").alias("via")).join(pairs.withColumnRenamed("src", "via"), "via").select("src", "dst").distinct()
        if not found.add(onward.join(found.all, ["src", "dst"], "left_anti").withColumn("hops", F.lit(step))):
            break
    return found.all


#: Edges and pairs of components up to which the closure of components is taken on arrays.
SMALL_EDGES, SMALL_PAIRS = 2_000_000, 8_000_000
#: The same of counts, for which no pair is made: edges, and entries of different sets, four bytes each.
COUNT_EDGES, COUNT_ENTRIES = 8_000_000, 40_000_000


def _strong(at: list[int], to: list[int] | memoryview) -> np.ndarray:
    """The number of each vertex's strongly connected component by one depth-first walk; what a component reaches has smaller numbers."""
    n, clock, count = len(at) - 1, 0, 0
    seen, low, part, nexts, held = [-1] * n, [0] * n, [-1] * n, at[:-1], []
    for start in range(n):
        if seen[start] >= 0:
            continue
        walk = [start]
        while walk:
            v = walk[-1]
            if seen[v] < 0:
                seen[v] = low[v] = clock
                clock += 1
                held.append(v)
            i, end = nexts[v], at[v + 1]
            while i < end and seen[to[i]] >= 0:
                if part[to[i]] < 0 and seen[to[i]] < low[v]:
                    low[v] = seen[to[i]]
                i += 1
            nexts[v] = i + 1
            if i < end:
                walk.append(to[i])
                continue
            walk.pop()
            if walk and low[v] < low[walk[-1]]:
                low[walk[-1]] = low[v]
            if low[v] == seen[v]:
                while part[v] < 0:
                    part[held.pop()] = count
                count += 1
    return np.array(part, np.int64)


def _parts_on_arrays(g: Graph, most: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, int] | None:
    """Vertices, ends of the distinct edges, the component of each vertex and their number; None beyond ``most`` edges."""
    rows = g.edges.select("src", "dst").distinct().limit(most + 1).toArrow()
    if rows.num_rows > most:
        return None
    src, dst = (rows.column(c).to_numpy().astype(np.int64) for c in ("src", "dst"))
    vids = np.unique(np.concatenate([src, dst]))
    src, dst = np.searchsorted(vids, src), np.searchsorted(vids, dst)
    order = np.argsort(src, kind="stable")
    src, dst = src[order], dst[order]
    part = _strong(np.searchsorted(src, np.arange(len(vids) + 1)).tolist(), memoryview(dst.astype(np.int32)))
    return vids, src, dst, part, int(part.max()) + 1 if len(part) else 0


def count_reached(g: Graph, asked: tuple[int, int], most: int | None = None, most_rows: int | None = None) -> DataFrame | None:
    """(vid, n): how many vertices of id ``asked[1]`` modulo ``asked[0]`` each vertex reaches over one edge or more; None beyond the bounds.

    Components that reach the same share one set, so ``most_rows`` bounds the sizes of different sets together.
    """
    most_rows = COUNT_ENTRIES if most_rows is None else most_rows
    held = _parts_on_arrays(g, COUNT_EDGES if most is None else most)
    if held is None:
        return None
    vids, src, dst, part, count = held
    weight = np.bincount(part[vids % asked[0] == asked[1]], minlength=count)
    a, b = np.divmod(np.unique(part[src] * max(count, 1) + part[dst]), max(count, 1))
    first, b = np.searchsorted(a, np.arange(count + 1)).tolist(), b.astype(np.int32)
    near_of, asks = b.tolist(), (weight > 0).tolist()
    # Sets of components with a vertex asked for.
    sets, beyond, total = [np.zeros(0, np.int32)], [0] * count, 0
    for c in range(count):
        near = near_of[first[c] : first[c + 1]]
        parts = sorted({beyond[x] for x in near})
        own = [x for x in near if asks[x]]
        if not own and len(parts) < 2:
            beyond[c] = parts[0] if parts else 0
            continue
        largest = max(parts, key=lambda x: len(sets[x]), default=0)
        union = np.unique(np.concatenate([np.array(own, np.int32), *(sets[x] for x in parts)]))
        beyond[c] = largest
        if len(union) > len(sets[largest]):
            beyond[c] = len(sets)
            sets.append(union)
            total += len(union)
        if total > most_rows:
            return None
    sizes = np.array([weight[x].sum() for x in sets], np.int64)
    return g.edges.sparkSession.createDataFrame(pa.table({"vid": vids, "n": sizes[np.array(beyond, np.int64)[part]] if count else vids}))


def _components_on_arrays(g: Graph, most: int, most_pairs: int) -> tuple[DataFrame, DataFrame] | None:
    """As :func:`closure_components` for all sources; None beyond ``most`` edges or ``most_pairs`` pairs."""
    held = _parts_on_arrays(g, most)
    if held is None:
        return None
    vids, src, dst, part, count = held
    name = np.full(count, np.iinfo(np.int64).max)
    np.minimum.at(name, part, vids)
    between = np.unique(part[src] * max(count, 1) + part[dst])
    a, b = np.divmod(between, max(count, 1))
    first, beyond, total = np.searchsorted(a, np.arange(count + 1)), [], 0
    for c in range(count):
        near = b[first[c] : first[c + 1]]
        own = np.unique(np.concatenate([near, *(beyond[x] for x in near[near != c].tolist())])).astype(np.int32) if len(near) else np.zeros(0, np.int32)
        beyond.append(own)
        total += len(own)
        if total > most_pairs:
            return None
    froms = np.repeat(name, [len(x) for x in beyond]) if count else name
    tos = name[np.concatenate(beyond)] if count else name
    frame = g.edges.sparkSession.createDataFrame
    return frame(pa.table({"vid": vids, "scc": name[part] if count else vids})), frame(pa.table({"a": froms, "b": tos}))


def closure_components(g: Graph, sources: DataFrame | None = None, most: int = SMALL_EDGES, most_pairs: int = SMALL_PAIRS) -> tuple[DataFrame, DataFrame]:
    """(vid, scc) of all vertices, and (a, b): the components that each component (of a source) reaches over one edge or more.

    All vertices of a component reach the same vertices, so the closure is taken over components; one on a cycle reaches itself.
    Graphs of a checked size are closed on arrays, which gives every source; larger ones in rounds.
    """
    small = _components_on_arrays(g, most, most_pairs)
    if small is not None:
        return cut(small[0], "parts"), cut(small[1], "between")
    with scratch(g.edges.sparkSession) as held:
        parts = held.keep(cut(scc(g), "parts"))
        a, b = (parts.select(F.col("vid").alias(v), F.col("scc").alias(c)) for v, c in (("src", "a"), ("dst", "b")))
        pairs = cut(g.edges.select("src", "dst").distinct().join(a, "src").join(b, "dst").select("a", "b").distinct(), "between")
        dag = Graph(pairs.where("a <> b").select(F.col("a").alias("src"), F.col("b").alias("dst"), F.lit("").alias("label")), g.labels)
        loops, starts = pairs.where("a = b"), None
        if sources is not None:
            starts = cut(parts.join(sources.select("vid").distinct(), "vid", "left_semi").select(F.col("scc").alias("vid")).distinct(), "starts")
            loops = loops.join(starts.select(F.col("vid").alias("a")), "a", "left_semi")
        reach = closure_vertices(dag, starts).select(F.col("src").alias("a"), F.col("dst").alias("b"))
        reach = held.keep(cut(reach.union(loops.select("a", "b")), "between"))
    return parts, reach


def _of(parts: DataFrame, sources: DataFrame | None) -> DataFrame:
    return parts if sources is None else parts.join(sources.select("vid").distinct(), "vid", "left_semi")


def closure_pairs(g: Graph, sources: DataFrame | None = None) -> DataFrame:
    """(src, dst): all vertices that each source reaches over one edge or more, by components.

    Members of components are sent to all tasks, eight bytes a vertex, and each source meets them in the task that its id is dealt to.
    """
    parts, reach = closure_components(g, sources)
    spark = g.edges.sparkSession
    tasks = max(4 * spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))
    rows = reach.join(_of(parts, sources).select(F.col("scc").alias("a"), F.col("vid").alias("src")), "a").select("src", "b").repartition(tasks, "src")
    members = parts.groupBy(F.col("scc").alias("b")).agg(F.collect_list("vid").alias("members"))
    return rows.join(F.broadcast(members), "b").select("src", F.explode("members").alias("dst"))


def unreached(g: Graph, pairs: DataFrame) -> DataFrame:
    """(violations): how many of the pairs (src, dst) the closure denies; pairs of the same two components are looked up once."""
    parts, reach = closure_components(g)
    a, b = (parts.select(F.col("vid").alias(v), F.col("scc").alias(c)) for v, c in (("src", "a"), ("dst", "b")))
    asked = pairs.join(a, "src").join(b, "dst").groupBy("a", "b").agg(F.count("*").alias("n"))
    return asked.join(reach, ["a", "b"], "left_anti").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("violations"))


def closure_labels(g: Graph, sources: DataFrame | None = None) -> DataFrame:
    """(vid, label): labels on any walk that starts in a vertex."""
    return label_profile(g, sources).select("vid", "label")


def closure_label_sets(g: Graph, sources: DataFrame | None = None, minimal: bool = False) -> DataFrame:
    """(src, dst, mask): label sets of the walks between each pair, at most 62 labels.

    With ``minimal``, only sets of which no other set of the same pair is a part: the full information that allowed-set
    queries need. Both grow with the square of the vertices. Minimal sets of a graph of checked size and few labels are searched on arrays.
    """
    lid = g.labels.where(f"lid < {M.WORD}")
    if g.labels.where(f"lid >= {M.WORD}").limit(1).count():
        raise ValueError("more than 62 labels")
    step = cut(g.edges.join(F.broadcast(lid), "label").select("src", "dst", M.bit_word(F.col("lid"), 0).alias("bit")).distinct(), "steps")
    if minimal and not g.labels.where(f"lid >= {FEW_LABELS}").limit(1).count() and (found := _minimal_on_arrays(step, sources)) is not None:
        return found
    start = step if sources is None else step.join(sources.select(F.col("vid").alias("src")).distinct(), "src", "left_semi")
    trim = (lambda df: _antichain(df)) if minimal else (lambda df: df)
    found = Layers(trim(start.withColumnRenamed("bit", "mask")), "sets")
    while True:
        onward = found.last.withColumnRenamed("dst", "via").join(step.withColumnRenamed("src", "via"), "via").select("src", "dst", F.col("mask").bitwiseOR(F.col("bit")).alias("mask")).distinct()
        if minimal:
            old = found.all.select("src", "dst", F.col("mask").alias("old"))
            onward = _antichain(onward.join(old, (onward.src == old.src) & (onward.dst == old.dst) & (F.col("old").bitwiseAND(F.col("mask")) == F.col("old")), "left_anti"))
        else:
            onward = onward.join(found.all, ["src", "dst", "mask"], "left_anti")
        if not found.add(onward):
            return _antichain(found.all) if minimal else found.all


#: Labels up to which minimal label sets are searched set by set.
FEW_LABELS = 16


def ragged(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The places of runs, one run after another."""
    return np.repeat(starts - np.cumsum(sizes) + sizes, sizes) + np.arange(int(sizes.sum()))


def minimal_sets(at: np.ndarray, to: np.ndarray, bit: np.ndarray, first: list[tuple[int, np.ndarray]], known: list[tuple[int, np.ndarray]] = (), live: np.ndarray | None = None) -> list[tuple[int, np.ndarray]]:
    """Minimal label sets of walks that go on from ``first``: (mask, vertices in order), sets in order of size.

    Edges of vertex v are ``at[v]`` to ``at[v + 1]``. A set comes after all its parts, so what it reaches newly is minimal. Vertices that
    ``known`` has with a part of a set are not reached with it, nor those that are not ``live``.
    """
    waiting: dict[int, list[np.ndarray]] = {}
    for mask, some in first:
        waiting.setdefault(mask, []).append(some)
    out = []
    while waiting:
        mask = min(waiting, key=lambda m: (m.bit_count(), m))
        new = np.unique(np.concatenate(waiting.pop(mask)))
        done = np.zeros(len(at) - 1, bool) if live is None else ~live
        for m, some in (*known, *out):
            if m & mask == m:
                done[some] = True
        mine, new = [], new[~done[new]]
        while len(new):
            mine.append(new)
            done[new] = True
            edge = ragged(at[new], at[new + 1] - at[new])
            reached, more = to[edge], bit[edge] & ~mask
            for x in np.unique(more).tolist():
                if x:
                    waiting.setdefault(mask | x, []).append(np.unique(reached[more == x]))
            new = np.unique(reached[more == 0])
            new = new[~done[new]]
        if mine:
            out.append((mask, np.sort(np.concatenate(mine))))
    return out


def _classes(key: np.ndarray, a: np.ndarray, b: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """The class of each of n vertices by its set of (a, b), and the first vertex of each class."""
    order = np.lexsort((b, a, key))
    both, ends = np.stack([a[order], b[order]], axis=1), np.searchsorted(key[order], np.arange(n + 1)).tolist()
    number: dict[bytes, int] = {}
    of = np.array([number.setdefault(both[ends[v] : ends[v + 1]].tobytes(), len(number)) for v in range(n)], np.int64)
    return of, np.unique(of, return_index=True)[1]


def _minimal_on_arrays(step: DataFrame, sources: DataFrame | None, most: int | None = None) -> DataFrame | None:
    """As :func:`closure_label_sets` with ``minimal``; None beyond ``most`` edges.

    Vertices with the same edges into them are reached alike and searched as one class; sources with the same edges to classes are searched once.
    Tasks search a class of sources each, and members are put in where the result is made.
    """
    most = SMALL_EDGES if most is None else most
    spark, rows = step.sparkSession, step.limit(most + 1).toArrow()
    if rows.num_rows > most:
        return None
    src, dst, bit = (rows.column(c).to_numpy().astype(np.int64) for c in ("src", "dst", "bit"))
    vids = np.unique(np.concatenate([src, dst]))
    n = len(vids)
    src, dst = np.searchsorted(vids, src), np.searchsorted(vids, dst)
    target, _ = _classes(dst, src, bit, n)
    edges = np.unique(np.stack([target[src], target[dst], bit], axis=1), axis=0)
    at = np.searchsorted(edges[:, 0], np.arange(target.max(initial=-1) + 2))
    starts = np.unique(np.stack([src, target[dst], bit], axis=1), axis=0)
    source, example = _classes(starts[:, 0], starts[:, 1], starts[:, 2], n)
    low, high = (np.searchsorted(starts[:, 0], example, side) for side in ("left", "right"))
    held = spark.sparkContext.broadcast((at, edges[:, 1].copy(), edges[:, 2].copy(), starts[:, 1].copy(), starts[:, 2].copy(), low, high))

    def search(batches):
        at, to, bit, near, bits, low, high = held.value
        for batch in batches:
            for c in batch.column("a").to_pylist():
                here, mark = near[low[c] : high[c]], bits[low[c] : high[c]]
                found = minimal_sets(at, to, bit, [(x, here[mark == x]) for x in np.unique(mark).tolist()])
                sizes = [len(v) for _, v in found]
                if found:
                    masks = np.repeat(np.array([m for m, _ in found], np.int64), sizes)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(masks), c)), pa.array(np.concatenate([v for _, v in found])), pa.array(masks)], names=["a", "b", "mask"])

    froms = spark.createDataFrame(pa.table({"a": source, "src": vids}))
    froms = cut(froms if sources is None else froms.join(sources.select(F.col("vid").alias("src")).distinct(), "src", "left_semi").select("a", "src"), "froms")
    members = cut(spark.createDataFrame(pa.table({"b": target, "dst": vids})).groupBy("b").agg(F.collect_list("dst").alias("dst")), "members")
    tasks = max(4 * spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))
    sets = froms.select("a").distinct().repartition(tasks, F.xxhash64("a")).mapInArrow(search, "a long, b long, mask long")
    froms = froms.groupBy("a").agg(F.collect_list("src").alias("src"))
    pairs = sets.join(F.broadcast(members), "b").join(F.broadcast(froms), "a")
    return pairs.select(F.explode("src").alias("src"), "dst", "mask").select("src", F.explode("dst").alias("dst"), "mask")


def _antichain(df: DataFrame) -> DataFrame:
    other = df.select(F.col("src").alias("s"), F.col("dst").alias("d"), F.col("mask").alias("less")).distinct()
    inside = (df.src == F.col("s")) & (df.dst == F.col("d")) & (F.col("less") != F.col("mask")) & (F.col("less").bitwiseAND(F.col("mask")) == F.col("less"))
    return df.distinct().join(other, inside, "left_anti")


def levels(g: Graph) -> DataFrame:
    """(vid, level): longest distance to a leaf, by peeling leaves; vertices on or above cycles have none."""
    pairs = cut(g.edges.select("src", "dst").distinct(), "pairs")
    rest, parts, level = cut(g.vertices(), "rest"), [], 0
    while True:
        blocked = pairs.select(F.col("src").alias("vid")).distinct()
        now = cut(rest.join(blocked, "vid", "left_anti").withColumn("level", F.lit(level)), "level")
        if now.isEmpty():
            break
        parts.append(now)
        pairs = cut(pairs.join(now.select(F.col("vid").alias("dst")), "dst", "left_anti").select("src", "dst"), "pairs")
        rest = cut(rest.join(now, "vid", "left_anti"), "rest")
        level += 1
    out = parts[0] if parts else rest.limit(0).withColumn("level", F.lit(0))
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def is_acyclic(g: Graph) -> bool:
    return g.vertices().join(levels(g), "vid", "left_anti").isEmpty()


def scc(g: Graph) -> DataFrame:
    """(vid, scc): the least vertex of each strongly connected component.

    Vertices without a predecessor or successor in what remains are components of their own and go first. Then each vertex
    takes the least id that reaches it; those with the same id that also reach that vertex are its component.
    """
    pairs = cut(g.edges.select("src", "dst").where("src <> dst").distinct(), "pairs")
    rest = cut(g.vertices(), "rest")
    found: list[DataFrame] = []
    while True:
        while True:
            single = rest.join(pairs.select(F.col("src").alias("vid")), "vid", "left_anti").union(rest.join(pairs.select(F.col("dst").alias("vid")), "vid", "left_anti")).distinct()
            single = cut(single.withColumn("scc", F.col("vid")), "single")
            if single.isEmpty():
                break
            found.append(single)
            rest, pairs = _without(rest, pairs, single)
        if rest.isEmpty():
            break
        color = _least(rest.withColumn("c", F.col("vid")), pairs)
        inside = pairs.join(color.select(F.col("vid").alias("src"), F.col("c").alias("cs")), "src").join(color.select(F.col("vid").alias("dst"), F.col("c").alias("cd")), "dst").where("cs = cd").select("src", "dst", F.col("cs").alias("scc"))
        inside = cut(inside, "inside")
        delta = cut(color.where("vid = c").select("vid", F.col("c").alias("scc")), "back")
        whole = delta
        while True:
            back = inside.join(delta.select(F.col("vid").alias("dst"), "scc"), ["dst", "scc"]).select(F.col("src").alias("vid"), "scc").distinct()
            delta = cut(back.join(whole, "vid", "left_anti"), "back")
            if delta.isEmpty():
                break
            whole = whole.unionByName(delta)
        whole = cut(whole, "component")
        found.append(whole)
        rest, pairs = _without(rest, pairs, whole)
    out = found[0] if found else rest.withColumn("scc", F.col("vid"))
    for f in found[1:]:
        out = out.unionByName(f)
    return out


def _without(rest: DataFrame, pairs: DataFrame, gone: DataFrame) -> tuple[DataFrame, DataFrame]:
    rest = cut(rest.join(gone, "vid", "left_anti"), "rest")
    pairs = pairs.join(gone.select(F.col("vid").alias("src")), "src", "left_anti").join(gone.select(F.col("vid").alias("dst")), "dst", "left_anti")
    return rest, cut(pairs.select("src", "dst"), "pairs")


def _least(color: DataFrame, pairs: DataFrame) -> DataFrame:
    """The least color that reaches each vertex, sending changed colors only."""
    color, path = cut_with_path(color, "color")
    delta = color
    while True:
        sent = pairs.join(delta.select(F.col("vid").alias("src"), "c"), "src").groupBy(F.col("dst").alias("vid")).agg(F.min("c").alias("low"))
        new = color.join(sent, "vid", "left").select("vid", F.least("c", F.coalesce("low", "c")).alias("c"), (F.coalesce("low", "c") < F.col("c")).alias("changed"))
        new, new_path, changed = cut_counted(new, "color", F.col("changed"))
        delta = new.where("changed")
        last, path, color = path, new_path, new.select("vid", "c")
        remove(color.sparkSession, last)
        if not changed:
            return color


def condense(g: Graph, components: DataFrame | None = None) -> Graph:
    """The graph of components; edges within one are left out."""
    c = scc(g) if components is None else components
    joined = g.edges.join(c.select(F.col("vid").alias("src"), F.col("scc").alias("s")), "src").join(c.select(F.col("vid").alias("dst"), F.col("scc").alias("d")), "dst")
    return Graph.from_edges(joined.where("s <> d").select(F.col("s").alias("src"), F.col("d").alias("dst"), "label"))


def label_profile(g: Graph, sources: DataFrame | None = None) -> DataFrame:
    """(vid, label, n): how many distinct edges of each label lie on walks from a vertex."""
    parts, reach = closure_components(g, sources)
    own = g.edges.join(parts.select(F.col("vid").alias("src"), F.col("scc").alias("b")), "src").groupBy("b", "label").agg(F.count("*").alias("n"))
    here = _of(parts, sources)
    every = reach.union(here.select(F.col("scc").alias("a"), F.col("scc").alias("b"))).distinct()
    counts = every.join(own, "b").groupBy("a", "label").agg(F.sum("n").alias("n"))
    return here.join(counts, here.scc == counts.a).select("vid", "label", "n")


def label_map(labels: DataFrame) -> DataFrame:
    """One row: the dictionary as a map from label to number, of an alphabet that :meth:`Graph.alphabet` would take."""
    return labels.agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("label", "lid")))).alias("lid_of"))


def k_hop(g: Graph, sources: DataFrame, k: int, allowed: list[str] | None = None) -> DataFrame:
    """(src, dst, hops) within k hops over allowed labels."""
    return closure_vertices(g if allowed is None else g.where(F.col("label").isin(allowed)), sources, max_rounds=k)
