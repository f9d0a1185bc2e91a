from itertools import combinations

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from pathsieve.functions import patterns as P

LABELS = "abcd"
SETS = [set(c) for n in range(5) for c in combinations(LABELS, n)]
FORMULAS = st.recursive(st.sampled_from([P.Label(x) for x in LABELS] + [P.TRUE, P.FALSE]), lambda s: st.one_of(s.map(P.Not), st.lists(s, min_size=1, max_size=3).map(lambda x: P.And(tuple(x))), st.lists(s, min_size=1, max_size=3).map(lambda x: P.Or(tuple(x)))), max_leaves=8)


@settings(max_examples=200, deadline=None)
@given(FORMULAS)
def test_normal_forms_keep_meaning(p):
    dnf, cnf, small = P.to_dnf(p, 1000), P.to_cnf(p, 1000), P.simplify(p, set(LABELS))
    for s in SETS:
        want = P.holds(p, s)
        assert any(c.holds(s) for c in dnf) == want
        assert all(bool(c.req & s) or bool(c.forb - s) for c in cnf) == want
        assert P.holds(small, s) == want and P.holds(P.to_nnf(p), s) == want


def test_parser():
    p = P.parse_pattern('a AND ("b c" OR NOT d) & NONE{x, y}')
    assert P.labels_of(p) == {"a", "b c", "d", "x", "y"}
    assert P.holds(p, {"a", "b c"}) and not P.holds(p, {"a", "b c", "x"}) and not P.holds(p, {"a", "d"})
    assert P.parse_pattern("¬a ∧ b ∨ c") == P.parse_pattern("(NOT a AND b) OR c")
    assert P.holds(P.parse_pattern("ONLY{a,b}", LABELS), {"a"}) and not P.holds(P.parse_pattern("ONLY{a,b}", LABELS), {"c"})
    for bad in ("", "a AND", "(a", "a b", "a)", "ONLY{a}", "AND a", "{"):
        with pytest.raises(P.PatternError):
            P.parse_pattern(bad)


def test_negated_conjunction_and_none_differ():
    assert P.holds(P.parse_pattern("NOT (a AND b)"), {"b"}) and not P.holds(P.parse_pattern("NONE{a,b}"), {"b"})


def test_allowed_forms_agree():
    plain, wide = P.allowed_to_pattern("ab", LABELS), P.allowed_to_pattern("ab", LABELS, expanded=True)
    assert all(P.holds(plain, s) == P.holds(wide, s) == (s <= set("ab")) for s in SETS)
    with pytest.raises(ValueError):
        P.allowed_to_pattern(map(str, range(20)), map(str, range(30)), expanded=True)


def test_clause_bound_residual_and_unknown_labels():
    big = P.And(tuple(P.Or((P.Label(f"x{i}"), P.Label(f"y{i}"))) for i in range(8)))
    with pytest.raises(P.TooManyClauses):
        P.to_dnf(big, 64)
    assert P.Clause(frozenset("ab"), frozenset()).residual("a") == {"b"}
    assert P.simplify(P.parse_pattern("a OR NOT z"), {"a"}) == P.TRUE


def test_columns_and_sql(spark):
    from pyspark.sql import functions as F

    p = P.parse_pattern("(a OR b) AND NOT c")
    bits = {x: i for i, x in enumerate(LABELS)}
    rows = [(sorted(s), sum(1 << bits[x] for x in s)) for s in SETS]
    P.register_pattern(spark, "wanted", "(a OR b) AND NOT c")
    df = spark.createDataFrame(rows, "labels array<string>, mask long").select("labels", P.pattern_column(p, F.col("labels")).alias("x"), P.pattern_mask_column(p, [F.col("mask")], bits).alias("y"), F.expr("wanted(labels)").alias("z"))
    for r in df.collect():
        assert r.x == r.y == r.z == P.holds(p, set(r.labels))


def test_mask_positions(spark):
    from pathsieve.functions import masks as M

    rows = spark.createDataFrame([(0, 0), (5, 1 << 61), ((1 << 61) | 1, 6)], "a long, b long")
    assert [r[0] for r in rows.select(M.mask_to_bits([F.col("a"), F.col("b")])).collect()] == [[], [0, 2, 123], [0, 61, 63, 64]]
