"""SQL surface: mask functions, pattern functions and table functions."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

from pathsieve.functions import patterns as P

#: SQL scalar functions on mask words.
SCALARS = {
    "mask_contains": "(a BIGINT, b BIGINT) RETURNS BOOLEAN RETURN (a & b) = b",
    "mask_disjoint": "(a BIGINT, b BIGINT) RETURNS BOOLEAN RETURN (a & b) = 0",
    "mask_minus": "(a BIGINT, b BIGINT) RETURNS BIGINT RETURN a & ~b",
    "mask_size": "(a BIGINT) RETURNS INT RETURN bit_count(a)",
}


@udtf(returnType="clause int, label string, required boolean")
class ParseClauses:
    """Rows of a pattern's normal form."""

    def eval(self, pattern: str):
        if pattern is not None:
            for k, c in enumerate(P.to_dnf(P.parse_pattern(pattern))):
                yield from ((k, x, True) for x in sorted(c.req))
                yield from ((k, x, False) for x in sorted(c.forb))


@udtf(returnType="qid bigint, answer boolean")
class PatternReachLocal:
    """Answers over one partition's edges: arguments TABLE(src, dst, label) and queries as JSON [[qid, src, dst, pattern], ...]."""

    def __init__(self) -> None:
        self.adjacency, self.queries, self.labels = {}, "[]", set()

    def eval(self, edge, queries: str):
        self.queries = queries
        self.labels.add(edge["label"])
        self.adjacency.setdefault(edge["src"], []).append((edge["dst"], edge["label"]))

    def terminate(self):
        from pathsieve.plans.baselines import search_one

        for qid, src, dst, text in json.loads(self.queries):
            yield qid, search_one(self.adjacency, src, dst, P.to_dnf(P.simplify(P.parse_pattern(text, self.labels), self.labels)))


def register(spark: SparkSession) -> None:
    """Make all functions known to SQL in this session."""
    for name, body in SCALARS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
    spark.udtf.register("parse_clauses", ParseClauses)
    spark.udtf.register("pattern_reach_local", PatternReachLocal)


def pattern_reach_local(edges: DataFrame, queries: list[tuple]) -> DataFrame:
    """(qid, answer) through the table function, for small graphs."""
    spark = edges.sparkSession
    spark.udtf.register("pattern_reach_local", PatternReachLocal)
    edges.select("src", "dst", "label").createOrReplaceTempView("local_edges")
    return spark.sql(f"SELECT * FROM pattern_reach_local(TABLE(SELECT * FROM local_edges) WITH SINGLE PARTITION, '{json.dumps(queries).replace(chr(39), chr(39) * 2)}')")
