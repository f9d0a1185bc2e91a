"""Query sets with known truth values."""

from __future__ import annotations

import weakref

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pathsieve.loop import cut
from pathsieve.operators.graph import Graph, encode_vertices
from pathsieve.plans.search import SearchConfig, answer

#: Fixed values of the sampling rule: multipliers and offsets of source, target and labels.
SRC, DST, LAB = (7919, 13), (104736, 3), (15485863, 11)


_made: weakref.WeakKeyDictionary = weakref.WeakKeyDictionary()


def _once(g: Graph, name: str, make) -> tuple[DataFrame, int]:
    """A table of a graph and its rows, made once for all sets drawn from it."""
    held = _made.setdefault(g, {})
    if name not in held:
        table = make()
        held[name] = (table, table.count())
    return held[name]


def numbered_vertices(g: Graph) -> DataFrame:
    """(i, vid): vertices numbered in order of id."""
    return encode_vertices(g.vertices().withColumnRenamed("vid", "ext_id")).select(F.col("vid").alias("i"), F.col("ext_id").alias("vid"))


def vertices(g: Graph) -> DataFrame:
    """(vid): the vertices, read from the table that the pairs are drawn from."""
    return _once(g, "vertices", lambda: cut(numbered_vertices(g), "numbered"))[0].select("vid")


def sample_pairs(g: Graph, n: int, first: int = 0) -> DataFrame:
    """(qid, src, dst) for qid first..first+n-1 by an arithmetic rule on vertex numbers; the same in any engine."""
    v, total = _once(g, "vertices", lambda: cut(numbered_vertices(g), "numbered"))
    q = g.edges.sparkSession.range(first, first + n).withColumnRenamed("id", "qid")
    if total == 0:
        return q.select("qid", F.lit(0).cast("long").alias("src"), F.lit(0).cast("long").alias("dst")).limit(0)
    q = q.select("qid", ((F.col("qid") * SRC[0] + SRC[1]) % total).alias("a"), ((F.col("qid") * DST[0] + DST[1]) % total).alias("b"))
    return q.join(v.select(F.col("i").alias("a"), F.col("vid").alias("src")), "a").join(v.select(F.col("i").alias("b"), F.col("vid").alias("dst")), "b").select("qid", "src", "dst")


def walk_pairs(g: Graph, n: int, first: int = 0, hops: int = 6) -> DataFrame:
    """As :func:`sample_pairs`, but the target lies 1 to ``hops`` edges beyond the source, by an arithmetic choice at each step.

    A walk that can go no further ends there. Sources without successors are replaced by those with.
    """
    pairs, _ = _once(g, "pairs", lambda: cut(g.edges.select("src", "dst").distinct(), "pairs"))
    v, total = _once(g, "sources", lambda: cut(encode_vertices(pairs.select(F.col("src").alias("ext_id"))), "numbered"))
    total = max(total, 1)
    q = g.edges.sparkSession.range(first, first + n).select(F.col("id").alias("qid"), ((F.col("id") * SRC[0] + SRC[1]) % total).alias("vid"))
    at = q.join(v, "vid").select("qid", F.col("ext_id").alias("src"), F.col("ext_id").alias("dst"))
    for step in range(hops):
        chosen = ((F.col("qid") * LAB[0] + F.col("to") * DST[0] + step * SRC[0]) % 2147483647 * 48271) % 2147483647
        moves = at.where((F.col("qid") * 31 + 7) % hops >= step).join(pairs.select(F.col("src").alias("dst"), F.col("dst").alias("to")), "dst")
        best = moves.groupBy("qid").agg(F.min_by("to", F.struct(chosen, "to")).alias("to"))
        at = cut(at.join(best, "qid", "left").select("qid", "src", F.coalesce("to", "dst").alias("dst")), "walks")
    return at


def pattern_text(op: str, labels: list[str]) -> str:
    """ALL, ANY, NONE or ONLY over quoted labels."""
    return f"{op}{{{','.join(f'"{x}"' for x in labels)}}}"


def mixed(alphabet: list[str], depth: int, seed: int) -> str:
    """A random nested formula over at most four labels."""
    import random

    rng = random.Random(seed)
    few = rng.sample(alphabet, min(4, len(alphabet)))

    def build(d: int) -> str:
        if d == 0 or rng.random() < 0.25:
            return ("NOT " if rng.random() < 0.3 else "") + f'"{rng.choice(few)}"'
        return f"({build(d - 1)} {rng.choice(['AND', 'OR'])} {build(d - 1)})"

    return build(depth)


def stratified_edges(g: Graph, shares: dict[str, float], seed: int = 1) -> DataFrame:
    """A sample of the edges with a share of its own for each label; labels that are not named have none."""
    return g.edges.sampleBy("label", shares, seed)


class ShortSet(ValueError):
    """Not enough true or false queries were found."""


def candidates(g: Graph, op: str, n: int, n_labels: int | str = 2, first: int = 0, seed: int = 1, walked: bool = False) -> DataFrame:
    """(qid, src, dst, pattern): pairs with patterns of ``n_labels`` labels (a number, or "quarter" or "half" of the alphabet)."""
    alphabet = g.alphabet()
    z = len(alphabet)
    share = {"quarter": z // 4, "half": z // 2}
    k = max(1, share[n_labels]) if n_labels in share else min(int(n_labels), z)
    kinds = min(32, z)
    texts = [mixed(alphabet, 2, seed + i) if op == "MIXED" else pattern_text(op, sorted({alphabet[(i * LAB[1] + j * max(1, z // k)) % z] for j in range(k)})) for i in range(kinds)]
    rows = g.edges.sparkSession.createDataFrame(list(enumerate(texts)), "kind int, pattern string")
    pairs = (walk_pairs if walked else sample_pairs)(g, n, first).withColumn("kind", ((F.col("qid") * LAB[0] + LAB[1] + seed) % kinds).cast("int"))
    return pairs.join(F.broadcast(rows), "kind").drop("kind")


def make_queries(g: Graph, op: str, n_true: int, n_false: int, n_labels: int | str = 2, seed: int = 1, most_tries: int = 8, short: bool = False, solve=None) -> DataFrame:
    """(qid, src, dst, pattern, truth): a set with ``n_true`` true and ``n_false`` false queries.

    Candidates are answered exactly, without an index unless ``solve`` (queries -> qid, answer) is given, in rounds until both kinds
    suffice: pairs of any two vertices, and, while true ones are lacking, pairs with a walk between them. :class:`ShortSet` is raised
    if a kind is still short at the end; with ``short``, the fewer that there are come back.
    """
    batch, first, out, have = n_true + n_false, 0, None, {}
    solve = solve or (lambda some: answer(g, some, None, SearchConfig(rules=())))
    for attempt in range(most_tries):
        walked = have.get(True, n_true) < n_true and (attempt % 3 != 2 or have.get(False, 0) >= n_false)
        some = cut(candidates(g, op, batch, n_labels, first, seed, walked), "candidates")
        solved = some.join(solve(some), "qid").withColumnRenamed("answer", "truth")
        solved = cut(solved, "solved")
        out = solved if out is None else out.unionByName(solved)
        have = {r["truth"]: r["n"] for r in out.groupBy("truth").agg(F.count("*").alias("n")).collect()}
        if have.get(True, 0) >= n_true and have.get(False, 0) >= n_false:
            break
        first += batch
    else:
        if not short:
            raise ShortSet(f"{have.get(True, 0)} true and {have.get(False, 0)} false {op} queries of {n_true} and {n_false}")
    ranked = out.withColumn("r", F.row_number().over(Window.partitionBy("truth").orderBy("qid")))
    return cut(ranked.where(F.when(F.col("truth"), F.col("r") <= n_true).otherwise(F.col("r") <= n_false)).drop("r"), "queries")
