import random
from itertools import product

import pytest
from pyspark.sql import functions as F

from pathsieve.functions import masks as M
from pathsieve.functions import patterns as P
from pathsieve.functions import sql
from pathsieve.operators import graph as G
from pathsieve.plans import baselines as B
from pathsieve.plans import measures as S
from pathsieve.plans import search as A
from pathsieve.plans.index import IndexConfig, TwoAxisIndex, build_index, inbound_masks, outbound_masks, tree_intervals

EXAMPLE = {0: "1:ac 2:ab 7:b 8:e", 1: "3:d", 2: "3:c", 3: "5:b", 4: "5:ad 6:b", 7: "2:a 8:a 9:be", 8: "4:b"}
HASH = {1: 3, 2: 2, 3: 3, 4: 1, 5: 1, 6: 2, 7: 5, 8: 4, 9: 4}
WAYS = {(0, 1): 1, (0, 2): 1, (0, 7): 2, (0, 8): 2, (7, 2): 1, (7, 8): 1, (7, 9): 2}
ROWS = {(0, 1): ("123", "11110", "23", "11100"), (0, 2): ("12345", "11111", "45", "01001"), (4, 1): ("12", "11010", "12", "11010"), (7, 1): ("1234", "11110", "24", "10000"), (7, 2): ("4", "01001", "4", "01001"), (8, 1): ("12", "11010", "1", "01000")}
ROUNDS = A.SearchConfig(place="rounds")
ASKED = [(1, 0, 5, "b AND d", True), (2, 0, 4, "NONE{a,b}", False), (3, 0, 4, "NOT (a AND b)", True), (4, 0, 5, "NONE{b}", False), (5, 7, 4, "NOT a", False), (6, 0, 6, "b AND e", True)]


def edges_of(spec):
    return [(s, int(d), x) for s, text in spec.items() for d, ls in (y.split(":") for y in text.split()) for x in ls]


def brute(rows, src, dst, p):
    """All label sets of walks, closed over (vertex, set)."""
    seen, stack = {(src, frozenset())}, [(src, frozenset())]
    while stack:
        v, s = stack.pop()
        for a, b, x in rows:
            if a == v and (b, s | {x}) not in seen:
                seen.add((b, s | {x}))
                stack.append((b, s | {x}))
    return any(v == dst and P.holds(p, s) for v, s in seen)


def asked(spark, rows):
    return spark.createDataFrame(rows, "qid long, src long, dst long, pattern string")


def got(df):
    return {r["qid"]: r["answer"] for r in df.collect()}


@pytest.fixture(scope="module")
def example(spark):
    g = G.Graph.of(spark, edges_of(EXAMPLE)).stored()
    return g, build_index(g, IndexConfig(vertex_bits=5, k=1, vertex_hash={v: b - 1 for v, b in HASH.items()}, ways=WAYS))


def test_golden_index(example):
    _, ix = example
    word = lambda c, n: M.mask_string([F.col(c)], n)
    near = ix.near.select("vid", "way", word("v0", 5).alias("nv"), word("l0", 5).alias("nl"))
    rows = {(r.vid, r.way): r for r in ix.wide.select("vid", "way", word("v0", 5).alias("wv"), word("l0", 5).alias("wl")).join(near, ["vid", "way"]).collect()}
    assert {k[0] for k in rows} == {0, 1, 2, 3, 4, 7, 8}
    want = ROWS
    for key, (wv, wl, nv, nl) in want.items():
        r = rows[key]
        at = lambda s: "".join(str(i + 1) for i, c in enumerate(s) if c == "1")
        assert (at(r.wv), r.wl, at(r.nv), r.nl) == (wv, wl, nv, nl), key


def test_golden_answers_by_every_method(spark, example):
    g, ix = example
    q = asked(spark, [r[:4] for r in ASKED])
    want = {r[0]: r[4] for r in ASKED}
    assert got(A.answer(g, q, ix, ROUNDS)) == got(A.answer(g, q, None, ROUNDS)) == got(B.plain_sequential(g, q)) == want
    assert got(A.answer(g, q, None, A.SearchConfig(mode="mask"))) == want
    assert got(B.plain_sequential(g, q, reach=B.point_masks(ix, g.alphabet()))) == want
    assert got(B.answer_simple(g, q, 6)) == want
    assert got(sql.pattern_reach_local(g.edges, [r[:4] for r in ASKED])) == want
    paths = {r.qid: [(e.src, e.label, e.dst) for e in r.path] for r in B.witness_paths(g, q).collect()}
    assert set(paths) == {k for k, v in want.items() if v}
    for qid, src, dst, text, _ in ASKED:
        if qid in paths:
            p = paths[qid]
            assert p[0][0] == src and p[-1][2] == dst and all(a[2] == b[0] for a, b in zip(p, p[1:])) and {(a, b, x) for a, x, b in p} <= set(edges_of(EXAMPLE))
            assert P.holds(P.parse_pattern(text), {x for _, x, _ in p})


TRAPS = [
    ("ring", "0-a-1 1-b-2 2-c-0 2-d-3", 1, 3, "a", True), ("revisit", "0-a-1 0-b-1 1-c-2", 0, 2, "ALL{b,c}", True), ("mixed", "0-a-1 0-b-2 1-c-3 2-c-3", 0, 3, "NONE{a}", True),
    ("skip", "0-a-1 1-b-2", 0, 2, "a AND NOT b", False), ("short", "0-a-1 1-b-2", 0, 1, "NONE{b}", True), ("through", "0-a-1 1-b-2 2-c-1", 0, 1, "c", True),
    ("self ring", "0-a-1 1-b-0", 0, 0, "b", True), ("empty", "0-a-1", 0, 0, "NONE{a}", True), ("empty needs", "0-a-1", 0, 0, "ALL{a}", False), ("unknown", "0-a-1", 0, 9, "TRUE", False),
]


def test_traps_in_one_graph(spark):
    rows, queries, want = [], [], {}
    for i, (_, text, s, d, p, truth) in enumerate(TRAPS):
        rows += [(100 * i + int(a), 100 * i + int(b), x) for a, x, b in (e.split("-") for e in text.split())]
        queries.append((i, 100 * i + s, 100 * i + d, p))
        want[i] = truth
    g = G.Graph.of(spark, rows).stored()
    q = asked(spark, queries)
    ix = build_index(g, IndexConfig(vertex_bits=7, k=3, way_count="one"))
    assert got(A.answer(g, q, None, ROUNDS)) == want == got(A.answer(g, q, ix, ROUNDS))
    assert S.no_false_negative(g, ix).first()[0] == 0 == S.check_monotone(g, ix).first()[0]


def test_folded_labels_stay_exact(spark):
    rows = [(0, 1, "L62"), (3, 4, "L0")] + [(2, 3, f"L{i}") for i in range(70)]
    g = G.Graph.of(spark, rows).stored()
    ix = build_index(g, IndexConfig(label_bits=31, k=2))
    assert not ix.exact
    q = asked(spark, [(1, 0, 1, "NONE{L0}"), (2, 2, 4, "L1 AND NOT L9"), (3, 2, 3, "NONE{L1}"), (4, 2, 4, "NONE{L0}"), (5, 2, 4, "ALL{L1,L69}")])
    assert got(A.answer(g, q, ix)) == got(A.answer(g, q)) == {1: True, 2: True, 3: True, 4: False, 5: False}


def test_random_graphs_agree_with_brute_force(spark):
    rng = random.Random(11)
    rows, queries, want = [], [], {}
    for i in range(20):
        n = rng.randint(2, 5)
        own = {(rng.randrange(n), rng.randrange(n), rng.choice("abcd")) for _ in range(rng.randint(1, 10))}
        rows += [(10 * i + a, 10 * i + b, x) for a, b, x in own]
        for _ in range(6):
            s, d = rng.randrange(n), rng.randrange(n)
            text = rng.choice(["ALL{a,b}", "ANY{c,d}", "NONE{a}", "NONE{b,c}", "a AND NOT b", "(a OR c) AND NOT (b AND d)", "NOT (a OR b)", "ALL{a,b,c}"])
            qid = len(queries)
            queries.append((qid, 10 * i + s, 10 * i + d, text))
            want[qid] = brute(own, s, d, P.parse_pattern(text))
    g = G.Graph.of(spark, rows).stored()
    q = asked(spark, queries)
    assert got(A.answer(g, q, None, ROUNDS)) == want == got(A.answer(g, q, None, A.SearchConfig(place="rounds", dominance=True)))
    for cfg in (IndexConfig(vertex_bits=9, k=2, n_hash=2), IndexConfig(vertex_bits=16, k=1, way_rule="overlap", include_self=True, trees=0)):
        assert got(A.answer(g, q, build_index(g, cfg), ROUNDS)) == want, cfg
    sets = [(i, s, d, list("ab")) for i, (_, s, d, _) in enumerate(queries[:60])]
    qa = spark.createDataFrame(sets, "qid long, src long, dst long, allowed array<string>")
    truth = {i: brute([r for r in rows if r[2] in "ab"], s, d, P.TRUE) for i, s, d, _ in sets}
    assert got(A.answer_allowed(g, qa)) == got(B.allowed_search(g, qa)) == truth
    assert got(B.two_hop_answer(g, B.two_hop_build(g, True, True, batch=128), qa)) == truth


def test_two_hop_and_closure_agree_with_the_edge_filter(spark, example):
    g, ix = example
    qa = spark.createDataFrame([(i, s, d, ls) for i, (s, d, ls) in enumerate(product([0, 2, 7], [4, 5, 6], [["a", "b"], ["b", "e"], list("abcde")]))], "qid long, src long, dst long, allowed array<string>")
    truth = got(B.allowed_search(g, qa))
    assert got(B.two_hop_answer(g, B.two_hop_build(g, batch=4), qa)) == truth == got(B.closure_answer(g, B.minimal_closure(g), qa)) and len(set(truth.values())) == 2
    assert got(A.answer_allowed(g, qa, ix)) == truth


def test_index_survives_storage(spark, example, tmp_path):
    g, _ = example
    build_index(g, IndexConfig(k=2)).save(str(tmp_path / "ix"))
    ix = TwoAxisIndex.load(spark, str(tmp_path / "ix"))
    assert got(A.answer(g, asked(spark, [r[:4] for r in ASKED]), ix)) == {r[0]: r[4] for r in ASKED}
    assert S.index_space(ix) > 0 and S.way_profile(ix).first()["n_vertices"] == 7


def test_bucketed_tables_join_without_a_shuffle(spark, example):
    g, _ = example
    build_index(g, IndexConfig(k=1)).save_tables("bucketed_example", 2)
    ix = TwoAxisIndex.load_tables(spark, "bucketed_example")
    assert got(A.answer(g, asked(spark, [r[:4] for r in ASKED]), ix)) == {r[0]: r[4] for r in ASKED}
    plan = ix.own.hint("merge").join(ix.out.hint("merge"), "vid")._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan and "Exchange" not in plan
    for t in (*TwoAxisIndex._TABLES, "meta"):
        spark.sql(f"DROP TABLE bucketed_example_{t}")


def test_statistics_and_samples(spark, example):
    g, _ = example
    exact, near = G.graph_stats(g).first(), G.approximate_stats(g).first()
    assert (near.n_vertices, near.n_pairs, near.n_labels) == (exact.n_vertices, exact.n_pairs, exact.n_labels) == (10, 13, 5)
    assert exact.mean_degree == pytest.approx(1.7) and exact.skew == pytest.approx(4 * 10 / 13)
    from pathsieve.plans import workload as W

    assert {r.label for r in W.stratified_edges(g, {"a": 1.0, "b": 0.0}).collect()} == {"a"}
    walks = {(r.src, r.dst) for r in W.walk_pairs(g, 40, hops=3).collect()}
    reach = {(r.src, r.dst) for r in G.closure_vertices(g).collect()}
    assert walks <= reach and len(walks) > 5
    with pytest.raises(W.ShortSet):
        W.make_queries(G.Graph.of(spark, [(0, 1, "a")]).stored(), "ANY", 5, 500, 1, most_tries=1)


def test_orders_agree_and_components(spark):
    dag = G.Graph.of(spark, edges_of(EXAMPLE)).stored()
    rows = lambda g, o: {tuple(r) for r in outbound_masks(g, IndexConfig(order=o)).collect()}
    assert rows(dag, "fixpoint") == rows(dag, "levels") == rows(dag, "scc") and G.is_acyclic(dag)
    into = lambda o: {tuple(r) for r in inbound_masks(dag, IndexConfig(order=o)).collect()}
    assert into("fixpoint") == into("levels") == into("scc")
    ring = G.Graph.of(spark, [(0, 1, "a"), (1, 2, "a"), (2, 0, "b"), (2, 3, "c"), (3, 4, "a"), (4, 3, "b"), (5, 5, "a")]).stored()
    assert rows(ring, "fixpoint") == rows(ring, "scc") and not G.is_acyclic(ring)
    assert {tuple(r) for r in G.scc(ring).collect()} == {(0, 0), (1, 0), (2, 0), (3, 3), (4, 3), (5, 5)}
    assert {tuple(r) for r in G.condense(ring).edges.collect()} == {(0, 3, "c")}
    with pytest.raises(ValueError):
        outbound_masks(ring, IndexConfig(order="levels"))


def test_intervals_nest_and_prove_paths(spark, example):
    g, _ = example
    t = [(r.tree, r.root, r.vid, r.enter, r.leave) for r in tree_intervals(g, trees=2).collect()]
    reach = {(r.src, r.dst) for r in G.closure_vertices(g).collect()}
    for a, b in product(t, t):
        if a[:2] == b[:2] and a[2] != b[2]:
            assert a[4] < b[3] or b[4] < a[3] or (a[3] <= b[3] and b[4] <= a[4]) or (b[3] <= a[3] and a[4] <= b[4])
            if a[3] <= b[3] <= a[4]:
                assert (a[2], b[2]) in reach


def test_travel_queries(spark):
    names = {c: i for i, c in enumerate("ABCDEF")}
    text = "A-car-C C-car-E E-car-D C-ferry-F F-ferry-D A-rail-B B-plane-E B-bus-D"
    g = G.Graph.of(spark, [(names[a], names[b], x) for a, x, b in (e.split("-") for e in text.split())]).stored()
    q = ["rail AND NOT bus", "rail AND bus", "ferry AND plane", "ONLY{car,rail}", "ONLY{rail}", "NONE{car}", "NONE{car,bus}"]
    assert list(dict(sorted(got(A.answer(g, asked(spark, [(i, 0, 3, p) for i, p in enumerate(q)]))).items())).values()) == [True, True, False, True, False, True, False]
    r = spark.createDataFrame([(1, 0, 3, "car+ ferry+"), (2, 0, 3, "ferry car"), (3, 0, 3, "(car|rail) (bus|car car)"), (4, 0, 0, "car*")], "qid long, src long, dst long, regex string")
    assert got(B.answer_regex(g, r)) == {1: True, 2: False, 3: True, 4: True}


def test_small_and_empty_graphs(spark):
    empty = G.Graph.of(spark, []).stored()
    q = asked(spark, [(1, 0, 1, "a"), (2, 3, 3, "NOT a"), (3, 0, 1, "FALSE")])
    assert got(A.answer(empty, q, None, ROUNDS)) == {1: False, 2: True, 3: False} == got(A.answer(empty, q, build_index(empty), ROUNDS))
    nulls = G.Graph.from_edges(spark.createDataFrame([(1, 2, "a"), (None, 2, "a"), (1, None, "b"), (1, 2, None), (1, 2, "a")], "src long, dst long, label string"))
    assert nulls.edges.count() == 1


def test_no_python_in_the_mask_loop(spark, example):
    g, ix = example
    run = A._Run(g, ix, A.SearchConfig())
    clauses = A._target_columns(A.compile_queries(asked(spark, [r[:4] for r in ASKED]), g.alphabet()), ix)
    from pathsieve.loop import cut

    frontier = cut(run.start(cut(clauses)))
    plan = run.expand(frontier)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan and "Cartesian" not in plan and "NestedLoop" not in plan


def test_searches_leave_only_their_answers(spark):
    from pathsieve.loop import scratch

    edges = spark.createDataFrame([(1, 2, "a"), (2, 3, "b"), (3, 1, "c"), (3, 4, "a")], "src long, dst long, label string")
    q = spark.createDataFrame([(0, 1, 4, "a AND b"), (1, 1, 4, "a AND c"), (2, 4, 1, "a")], "qid long, src long, dst long, pattern string")
    g = G.Graph.from_edges(edges).stored()
    with scratch(spark) as made:
        got = A.answer(g, q, None, A.SearchConfig(place="rounds"))
        assert {r.qid: r.answer for r in got.collect()} == {0: True, 1: True, 2: False}
        hops = A.pattern_distance(g, q)
        assert {r.qid: r.hops for r in hops.collect()} == {0: 3, 1: 6, 2: None}
        assert [(r.states, r.kept) for r in A.trace(g, q).collect()][0] == (3, 2)
        assert len(made.made) == 2


def test_sql_functions(spark):
    sql.register(spark)
    assert spark.sql("SELECT mask_contains(7, 5), mask_disjoint(4, 3), mask_minus(7, 2), mask_size(7)").first()[:] == (True, True, 5, 3)
    assert {tuple(r) for r in spark.sql("SELECT * FROM parse_clauses('a AND NOT b')").collect()} == {(0, "a", True), (0, "b", False)}


def test_closure_by_components(spark):
    """Closures over components, on arrays and in rounds, and pairs claimed by intervals, against brute force; loops and cycles included."""
    import random

    from pathsieve.operators import graph as operators
    from pathsieve.plans.index import claimed_pairs

    rng = random.Random(5)
    rows = sorted({(rng.randrange(-2, 14), rng.randrange(-2, 14), rng.choice("ab")) for _ in range(20)} | {(30, 31, "a"), (31, 30, "b"), (40, 40, "a"), (31, 41, "a")})
    g = operators.Graph.of(spark, rows)
    want = {(s, d) for s, d, _ in rows}
    while more := {(a, d) for a, b in want for c, d in want if b == c} - want:
        want |= more
    for most in (operators.SMALL_EDGES, 3):
        parts, reach = operators.closure_components(g, most=most)
        of, pairs = {r.vid: r.scc for r in parts.collect()}, {(r.a, r.b) for r in reach.collect()}
        assert {(s, d) for s in of for d in of if (of[s], of[d]) in pairs} == want
    assert sorted((r.src, r.dst) for r in operators.closure_pairs(g).collect()) == sorted(want)
    asked = spark.createDataFrame([(30, 31), (31, 41), (41, 30), (41, 31)], "src long, dst long")
    assert operators.unreached(g, asked).first()[0] == 2
    spans = [(v, 0, v % 2, rng.randrange(40), 0) for v in range(30)]
    spans = [(v, t, r, e, e + rng.randrange(20)) for v, t, r, e, _ in spans]
    got = sorted((r.src, r.dst) for r in claimed_pairs(spark.createDataFrame(spans, "vid long, tree int, root long, enter long, leave long")).collect())
    assert got == sorted((a[0], b[0]) for a in spans for b in spans if a[2] == b[2] and a[3] < b[3] <= a[4])


def test_nearest_vectors(spark, tmp_path):
    """Copies, zeros and missing vectors, in several blocks, against every pair."""
    import math
    import random

    from pathsieve.sources import graphs

    rng = random.Random(11)
    some = [[rng.uniform(-1, 1) for _ in range(4)] for _ in range(12)]
    vectors = [some[i % 12] for i in range(30)] + [[0.0] * 4] * 5 + [None] * 2
    rng.shuffle(vectors)
    rows = [(i, v, i % 3) for i, v in enumerate(vectors)]
    spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int").write.parquet(f"{tmp_path}/embeddings.parquet")

    def place(a, b):
        if a is None or b is None:
            return (1, 0.0)
        size = math.sqrt(sum(x * x for x in a) * sum(x * x for x in b))
        return (0, -sum(x * y for x, y in zip(a, b)) / size if size else -math.inf)

    want = {(i, j, str(x)) for i, v, _ in rows for _, j, x in sorted((place(v, w), j, x) for j, w, x in rows if j != i)[:3]}
    for block in (1000, 10):
        got = {(r.src, r.dst, r.label) for r in graphs.vec_near(spark, str(tmp_path), block=block).edges.collect()}
        assert got == want


def test_uniform_graph_of_a_table(spark):
    from pathsieve.sources import graphs

    rows = spark.range(2000).withColumnRenamed("id", "event_id")
    same = graphs.uniform_graph(spark, 500, 4, 8).edges.exceptAll(graphs.uniform_graph_of(rows, "event_id", 4, 8).edges)
    assert same.isEmpty() and not graphs.uniform_graph_of(rows, "event_id", 4, 8).edges.isEmpty()


def random_rows(rng, n, size, labels="abcd"):
    return sorted({(rng.randrange(n), rng.randrange(n), rng.choice(labels)) for _ in range(size)})


def test_search_from_both_ends(spark):
    """The traps and random graphs, with and without dominance; an end with nothing to go on from answers its query."""
    rng = random.Random(5)
    rows, queries, want = [], [], {}
    for i, (_, text, s, d, p, truth) in enumerate(TRAPS):
        rows += [(100 * i + int(a), 100 * i + int(b), x) for a, x, b in (e.split("-") for e in text.split())]
        queries.append((i, 100 * i + s, 100 * i + d, p))
        want[i] = truth
    for i in range(20):
        own, low = random_rows(rng, 9, 16), 2000 + 10 * i
        rows += [(low + a, low + b, x) for a, b, x in own]
        for text in ("ALL{a,b}", "ANY{c,d}", "NONE{a}", "ALL{a,b,c}", "(a OR c) AND NOT (b AND d)"):
            s, d, qid = rng.randrange(9), rng.randrange(9), len(queries)
            queries.append((qid, low + s, low + d, text))
            want[qid] = brute(own, s, d, P.parse_pattern(text))
    g, q = G.Graph.of(spark, rows).stored(), asked(spark, queries)
    for dominance in (False, True):
        assert got(A.answer(g, q, None, A.SearchConfig(place="rounds", both=True, dominance=dominance))) == want
    assert 30 < sum(want.values()) < len(want) - 30
    with pytest.raises(ValueError):
        A.answer(g, q, None, A.SearchConfig(both=True, empty_path=False))


def test_minimal_sets_on_arrays_equal_rounds(spark, monkeypatch):
    rng = random.Random(8)
    rows = random_rows(rng, 12, 30) + [(a, b, "a") for a in (20, 21, 22) for b in (0, 30, 31)] + [(30, 1, "b"), (31, 2, "b"), (30, 40, "c"), (30, 41, "c"), (7, 7, "d")]
    g = G.Graph.of(spark, rows).stored()
    few = spark.createDataFrame([(20,), (3,), (99,)], "vid long")
    with monkeypatch.context() as m:
        m.setattr(G, "SMALL_EDGES", 0)
        every, some = (set(map(tuple, B.minimal_closure(g, x).collect())) for x in (None, few))
    monkeypatch.setattr(G, "Layers", None)
    assert sorted(every) == sorted(map(tuple, B.minimal_closure(g).collect())) and len(every) > 200
    assert sorted(some) == sorted(map(tuple, B.minimal_closure(g, few).collect())) and {r[0] for r in some} == {3, 20}


def test_two_hop_cover_on_arrays(spark, monkeypatch):
    rng = random.Random(4)
    rows = random_rows(rng, 25, 70) + [(100, 0, "a"), (101, 0, "b"), (100, 102, "c"), (103, 104, "a")]
    g = G.Graph.of(spark, rows).stored()
    ends = [*range(25), 100, 101, 102, 103, 104]
    sets = [(i, rng.choice(ends), rng.choice(ends), rng.choice([["a"], ["a", "b"], ["b", "c", "d"], ["a", "c"]])) for i in range(300)]
    q = spark.createDataFrame(sets, "qid long, src long, dst long, allowed array<string>")
    truth = {i: brute([r for r in rows if r[2] in x], s, d, P.TRUE) for i, s, d, x in sets}
    inside = B._cover_on_arrays
    monkeypatch.setattr(B, "_cover_on_arrays", lambda *a: None)
    rounds = B.two_hop_build(g, batch=16)
    monkeypatch.setattr(B, "_cover_on_arrays", inside)
    monkeypatch.setattr(B, "_spread", None)
    cover = B.two_hop_build(g)
    assert got(B.two_hop_answer(g, cover, q)) == truth == got(B.two_hop_answer(g, B.two_hop_build(g, True, True), q)) and len(set(truth.values())) == 2
    assert cover.out.count() + cover.into.count() <= rounds.out.count() + rounds.into.count()
    with pytest.raises(MemoryError):
        B.two_hop_build(g, most_rows=10)


def reached(rows, ends, text, sources):
    """How many vertices each source reaches by an edge or more under a pattern, without those that reach none."""
    out, p = {}, P.parse_pattern(text)
    for src in sources:
        seen = {(b, frozenset([x])) for a, b, x in rows if a == src}
        stack = list(seen)
        while stack:
            v, have = stack.pop()
            new = {(b, have | {x}) for a, b, x in rows if a == v} - seen
            seen |= new
            stack += new
        n = len({v for v, have in seen if P.holds(p, have)})
        out |= {src: n} if n else {}
    return out


def test_reach_counts_by_components(spark, monkeypatch):
    rng = random.Random(6)
    rows = random_rows(rng, 30, 60) + [(7, 7, "a"), (50, 51, "b")]
    g = G.Graph.of(spark, rows).stored()
    sources = spark.createDataFrame([(i,) for i in [*range(20), 50, 99]], "vid long")
    assert dict(map(tuple, A.reach_counts(g, sources, "a OR b").collect())) == reached(rows, range(52), "a OR b", [*range(20), 50])
    monkeypatch.setattr(A, "answer_from", None)
    for text in ("a", "a AND NOT b", "ALL{a,b,c}", "NONE{c}"):
        want = reached(rows, range(52), text, [*range(20), 50])
        assert dict(map(tuple, A.reach_counts(g, sources, text).collect())) == want and len(want) > 3, text
    with monkeypatch.context() as m:
        m.setattr(A, "count_reached", lambda *a: None)
        assert dict(map(tuple, A.reach_counts(g, sources, "NONE{c}").collect())) == want


def test_counts_beyond_the_closures_bounds(spark, monkeypatch):
    """Counts make no pairs, so they stay on arrays where a closure's edges and pairs are beyond their bounds."""
    rng = random.Random(8)
    rows = {(rng.randrange(40), rng.randrange(40), "a") for _ in range(60)}
    monkeypatch.setattr(G, "SMALL_EDGES", 10)
    monkeypatch.setattr(G, "SMALL_PAIRS", 10)
    beyond = {v: {d for s, d, _ in rows if s == v} for v in range(40)}
    for _ in range(40):
        beyond = {v: x.union(*(beyond[d] for d in x)) for v, x in beyond.items()}
    told = G.count_reached(G.Graph.of(spark, sorted(rows)), (2, 1))
    ends = {v for s, d, _ in rows for v in (s, d)}
    assert told is not None and {r.vid: r.n for r in told.collect()} == {v: sum(d % 2 for d in beyond[v]) for v in ends}
    assert G.count_reached(G.Graph.of(spark, sorted(rows)), (2, 1), most=10) is None
