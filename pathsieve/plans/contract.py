"""Pattern queries on graphs beyond the point form's bound: strongly connected vertices taken as one, then the point form on what is left.

Vertices are arrays on the driver and in every task; edges stay in a table that each round scans, without a shuffle of edges. For each set of
forbidden labels the graph without them is contracted. What a walk may see within a component it can see on its way through, so labels
of inner edges stay as loops, and walks between components stay as they are.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathsieve.functions import patterns as P
from pathsieve.loop import cut, scratch
from pathsieve.operators.graph import Graph
from pathsieve.plans import point
from pathsieve.plans.index import IndexConfig

#: Vertices held as arrays, distinct patterns, and sets of forbidden labels.
MOST_VERTICES, MOST_PATTERNS, MOST_SETS = 4_000_000, 1000, 8
#: Edges that a task goes over until nothing changes; the more a task has, the fewer rounds there are.
TASK_EDGES = 6_000_000


def _whole(batches, *names: str) -> list[np.ndarray]:
    """Columns of all of a task's rows."""
    parts = [[b.column(c).to_numpy(zero_copy_only=False) for c in names] for b in batches]
    return [np.concatenate([np.zeros(0, np.int32), *(p[i] for p in parts)]) for i in range(len(names))]


def _rows(**columns: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(x) for x in columns.values()], names=list(columns))


def _coded(edges: DataFrame, vids: np.ndarray, alphabet: list[str]) -> DataFrame:
    """(a, b, x): edges by places of vertices and labels; loops and all."""
    held = edges.sparkSession.sparkContext.broadcast((vids, {x: i for i, x in enumerate(alphabet)}))

    def code(batches):
        vids, lid = held.value
        for batch in batches:
            kinds = batch.column("label").dictionary_encode()
            labels = np.array([lid[x] for x in kinds.dictionary.to_pylist()], np.int32)
            a, b = (np.searchsorted(vids, batch.column(c).to_numpy()).astype(np.int32) for c in ("src", "dst"))
            yield _rows(a=a, b=b, x=labels[kinds.indices.to_numpy()] if len(a) else a)

    return edges.select("src", "dst", "label").mapInArrow(code, "a int, b int, x int")


def _told(coded: DataFrame, state, task, kind: str, how) -> tuple[np.ndarray, ...]:
    """What the tasks' edges say about vertices, one row a vertex."""
    held = coded.sparkSession.sparkContext.broadcast(state)
    rows = coded.select("a", "b").mapInArrow(lambda it: task(_whole(it, "a", "b"), held.value), kind).groupBy("v").agg(*how).toArrow()
    held.unpersist()
    return tuple(rows.column(c).to_numpy() for c in rows.column_names)


def _degrees(ends, n):
    a, b = (np.bincount(x, minlength=n) for x in ends)
    at = np.flatnonzero(a + b)
    yield _rows(v=at.astype(np.int32), a=a[at], b=b[at])


def _colors(ends, old):
    (a, b), new = ends, old.copy()
    while len(use := np.flatnonzero(new[a] > new[b])):
        np.maximum.at(new, b[use], new[a[use]])
    at = np.flatnonzero(new != old)
    yield _rows(v=at.astype(np.int32), c=new[at])


def _members(ends, state):
    (a, b), (color, old) = ends, state
    inside = color[a] == color[b]
    a, b, new = a[inside], b[inside], old.copy()
    while len(more := a[new[b] & ~new[a]]):
        new[more] = True
    yield _rows(v=np.flatnonzero(new & ~old).astype(np.int32))


def components(coded: DataFrame, n: int) -> np.ndarray:
    """For each vertex one of its strongly connected component, or itself; a component that no color's vertex lies in stays apart.

    Each vertex takes the largest rank (by degree) that reaches it. Those that reach the vertex of their color over vertices of
    that color are its component.
    """
    degree = np.zeros(n, np.int64)
    v, into, out = _told(coded, n, _degrees, "v int, a long, b long", [F.sum("a").alias("a"), F.sum("b").alias("b")])
    degree[v] = np.minimum(into, out)
    order = np.argsort(degree, kind="stable").astype(np.int32)
    rank = np.empty(n, np.int32)
    rank[order] = np.arange(n, dtype=np.int32)
    color = rank.copy()
    while True:
        v, c = _told(coded, color, _colors, "v int, c int", [F.max("c").alias("c")])
        if not len(v):
            break
        color[v] = c
    member = color == rank
    while True:
        v, _ = _told(coded, (color, member), _members, "v int", [F.count("*").alias("n")])
        if not len(v):
            break
        member[v] = True
    return np.where(member, order[color], np.arange(n, dtype=np.int32))


def _joined(coded: DataFrame, part: np.ndarray, kinds: int) -> DataFrame:
    """Distinct edges between components."""
    held = coded.sparkSession.sparkContext.broadcast(part)

    def join(batches):
        a, b, x = _whole(batches, "a", "b", "x")
        part = held.value
        key = np.unique((part[a].astype(np.int64) * len(part) + part[b]) * kinds + x)
        key, x = np.divmod(key, kinds)
        a, b = np.divmod(key, len(part))
        yield _rows(a=a.astype(np.int32), b=b.astype(np.int32), x=x.astype(np.int32))

    return coded.mapInArrow(join, "a int, b int, x int").distinct()


def contracted(edges: DataFrame, vids: np.ndarray, alphabet: list[str], most: int) -> tuple[Graph, np.ndarray] | None:
    """A graph of at most ``most`` edges and the place of the vertex that stands for each; None where contraction doesn't lead there."""
    n, part, last = len(vids), np.arange(len(vids), dtype=np.int32), None
    coded = cut(_coded(edges, vids, alphabet), "coded")
    while (size := coded.count()) > most:
        if last is not None and size > 0.9 * last or coded.where("a >= b").isEmpty():
            return None
        last, more = size, components(coded.coalesce(-(-size // TASK_EDGES)), n)
        part, coded = more[part], cut(_joined(coded, more, max(len(alphabet), 1)), "coded")
    held = edges.sparkSession.sparkContext.broadcast((vids, np.array(alphabet, object)))

    def named(batches):
        vids, alphabet = held.value
        for batch in batches:
            a, b, x = (batch.column(c).to_numpy() for c in ("a", "b", "x"))
            yield pa.RecordBatch.from_arrays([pa.array(vids[a]), pa.array(vids[b]), pa.array(alphabet[x], pa.string())], names=["src", "dst", "label"])

    return Graph.from_edges(coded.mapInArrow(named, "src long, dst long, label string")).stored(), part


def _moved(queries: DataFrame, vids: np.ndarray, part: np.ndarray) -> DataFrame:
    """Queries between the vertices that stand for theirs; unknown vertices stay."""
    held = queries.sparkSession.sparkContext.broadcast((vids, part))

    def move(batches):
        vids, part = held.value
        for batch in batches:
            columns = []
            for c in ("src", "dst"):
                ids, null = batch.column(c).fill_null(-1).to_numpy(), batch.column(c).is_null().to_numpy(zero_copy_only=False)
                at = np.minimum(np.searchsorted(vids, ids), max(len(vids) - 1, 0))
                columns.append(pa.array(np.where(vids[at] == ids, vids[part[at]], ids) if len(vids) else ids, mask=null))
            yield pa.RecordBatch.from_arrays([batch.column("qid"), *columns, batch.column("pattern")], names=["qid", "src", "dst", "pattern"])

    rows = queries.select("qid", F.col("src").cast("long"), F.col("dst").cast("long"), "pattern")
    return rows.mapInArrow(move, rows.schema)


def _within(small: Graph, queries: DataFrame, wants: dict[str, list[frozenset]]) -> DataFrame:
    """qids of moved queries whose ends are the same component and whose labels are all among those of its inner edges."""
    rows = queries.sparkSession.createDataFrame([(t, sorted(r)) for t, some in wants.items() for r in some], "pattern string, req array<string>")
    own = small.edges.where("src = dst").groupBy("src").agg(F.collect_set("label").alias("own"))
    inside = queries.where("src = dst").join(F.broadcast(rows), "pattern").join(own, "src")
    return inside.where(F.size(F.array_except("req", "own")) == 0).select("qid").distinct()


def _text(reqs: list[frozenset]) -> str:
    return " OR ".join("ALL{" + ",".join(f'"{x}"' for x in sorted(r)) + "}" if r else "TRUE" for r in reqs)


def _by_forbidden(texts: list[str], alphabet: list[str]) -> dict[frozenset, dict[str, list[frozenset]]] | None:
    """For each set of forbidden labels, the sets of labels one of which each pattern asks of the graph without them; None where that is too much."""
    lid, out = {x: i for i, x in enumerate(alphabet)}, {}
    for text in texts:
        try:
            clauses = P.to_dnf(P.simplify(P.parse_pattern(text, alphabet), lid))
        except P.TooManyClauses:
            return None
        for c in clauses:
            if any('"' in x for x in c.req):
                return None
            out.setdefault(frozenset(c.forb), {}).setdefault(text, []).append(frozenset(c.req))
    return out if len(out) <= MOST_SETS else None


def answer(g: Graph, vertices: DataFrame, queries: DataFrame, index: bool = True, cfg: IndexConfig | None = None) -> DataFrame | None:
    """(qid, answer) as :func:`point.answer` with or without an index; ``vertices`` has the graph's (vid). None beyond the bounds."""
    texts = [r[0] for r in queries.select("pattern").distinct().limit(MOST_PATTERNS + 1).collect()]
    alphabet = g.alphabet()
    asked = _by_forbidden(texts, alphabet) if len(texts) <= MOST_PATTERNS else None
    if asked is None or vertices.limit(MOST_VERTICES + 1).count() > MOST_VERTICES:
        return None
    vids, spark = np.sort(vertices.select("vid").toArrow().column("vid").to_numpy()), g.edges.sparkSession
    out = queries.select("qid", F.lit(False).alias("answer"))
    with scratch(spark) as kept:
        for forbidden, wants in asked.items():
            edges = g.edges.where(~F.col("label").isin(sorted(forbidden))) if forbidden else g.edges
            found = contracted(edges, vids, alphabet, point.MOST_EDGES)
            if found is None:
                return None
            small, part = found
            rows = spark.createDataFrame([(t, _text(w)) for t, w in wants.items()], "pattern string, want string")
            some = cut(_moved(queries.join(F.broadcast(rows.select("pattern")), "pattern"), vids, part), "moved")
            sure = cut(_within(small, some, wants), "within")
            rest = some.join(F.broadcast(sure), "qid", "left_anti").join(F.broadcast(rows), "pattern").select("qid", "src", "dst", F.col("want").alias("pattern"))
            held = point.load(small, point.MOST_EDGES)
            held = point.build(small, cfg, graph=held) if index else held
            out = out.unionByName(sure.withColumn("answer", F.lit(True))).unionByName(cut(point.answer(small, held, rest), "part"))
        return kept.keep(cut(out.groupBy("qid").agg(F.bool_or("answer").alias("answer")), "answers"))
