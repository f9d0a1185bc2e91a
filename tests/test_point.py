"""The point form against the batch form: index tables row by row, answers, and the work of each rule."""

import random

import pytest
from test_graphs import ASKED, EXAMPLE, HASH, ROWS, TRAPS, WAYS, asked, brute, edges_of, got

from pathsieve.functions import patterns as P
from pathsieve.operators import graph as G
from pathsieve.plans import point
from pathsieve.plans import search as A
from pathsieve.plans.index import IndexConfig, TwoAxisIndex, build_index

TEXTS = ["ALL{a,b}", "ANY{c,d}", "NONE{a}", "NONE{b,c}", "a AND NOT b", "(a OR c) AND NOT (b AND d)", "NOT (a OR b)", "ALL{a,b,c}", "TRUE", "FALSE", "a AND NOT a", "zz OR d"]


def random_edges(rng, graphs, most=6, edges=12):
    rows = []
    for i in range(graphs):
        n = rng.randint(2, most)
        rows += [(10 * i + a, 10 * i + b, x) for a, b, x in {(rng.randrange(n), rng.randrange(n), rng.choice("abcd")) for _ in range(rng.randint(1, edges))}]
    return rows


@pytest.mark.parametrize("cfg", [IndexConfig(trees=2), IndexConfig(k=3, vertex_bits=31, way_rule="overlap", include_self=True, n_hash=2), IndexConfig(mode="path", way_rule="label", way_count="sqrt"), IndexConfig(k=0, trees=0, way_rule="rank", way_count="linear", label_bits=31)])
def test_arrays_equal_tables(spark, cfg):
    g = G.Graph.of(spark, random_edges(random.Random(5), 12)).stored()
    want, p = build_index(g, cfg), point.build(g, cfg)
    ours, back = point.tables(spark, p), point.from_index(g, want)
    for name in TwoAxisIndex._TABLES:
        a, b = getattr(want, name), getattr(ours, name)
        assert sorted(map(tuple, a.select(sorted(a.columns)).collect())) == sorted(map(tuple, b.select(sorted(a.columns)).collect())), name
    for name in ("wide_v", "wide_l", "near_v", "near_l", "own", "out_v", "out_l", "into"):
        assert (getattr(p.index, name) == getattr(back.index, name)).all(), name


def test_golden_rows_and_answers(spark):
    g = G.Graph.of(spark, edges_of(EXAMPLE)).stored()
    p = point.build(g, IndexConfig(vertex_bits=5, k=1, vertex_hash={v: b - 1 for v, b in HASH.items()}, ways=WAYS))
    x, slots = p.index, {}
    for v, (first, last) in enumerate(zip(p.slot_at[:-1], p.slot_at[1:])):
        slots |= {(int(p.vids[v]), int(p.way[s])): s for s in range(first, last)}
    text = lambda m, n: "".join("1" if int(m) >> i & 1 else "0" for i in range(n))
    at = lambda m: "".join(str(i + 1) for i in range(5) if int(m) >> i & 1)
    for key, want in ROWS.items():
        s = slots[key]
        assert (at(x.wide_v[s, 0]), text(x.wide_l[s, 0], 5), at(x.near_v[0, s, 0]), text(x.near_l[0, s, 0], 5)) == want
    q, want = asked(spark, [r[:4] for r in ASKED]), {r[0]: r[4] for r in ASKED}
    assert got(point.answer(g, p, q)) == want == got(A.answer(g, q, p)) == got(A.answer(g, q, None, A.SearchConfig(place="tasks")))


def test_answers_of_random_graphs(spark, monkeypatch):
    """Every rule on and off, in small groups and steps, on cyclic graphs with loops, unknown vertices and labels."""
    rng = random.Random(21)
    rows = random_edges(rng, 25)
    g = G.Graph.of(spark, rows).stored()
    queries, want = [], {}
    for qid in range(400):
        i = rng.randrange(25)
        s, d, text = 10 * i + rng.randrange(6), 10 * i + rng.randrange(6), rng.choice(TEXTS)
        queries.append((qid, s, d, text))
        want[qid] = brute([r for r in rows if r[0] // 10 == i], s, d, P.parse_pattern(text, list("abcd")))
    q = asked(spark, queries)
    src, dst, texts = (list(c) for c in list(zip(*queries))[1:])
    import numpy as np

    answers = lambda p, rules: dict(enumerate(point._Walk(p, rules, True, 64).answers(np.array(src), np.array(dst), texts).tolist()))
    plain = point.load(g)
    assert answers(plain, ()) == want == got(point.answer(g, plain, q))
    for cfg in (IndexConfig(vertex_bits=9, k=2, n_hash=2), IndexConfig(vertex_bits=62, k=3, way_rule="overlap", include_self=True, trees=2), IndexConfig(label_bits=31, k=1), IndexConfig(mode="path")):
        p = point.build(g, cfg)
        for rules in (A.RULES, *((r,) for r in A.RULES)):
            assert answers(p, rules) == want, (cfg, rules)
    monkeypatch.setattr(point, "_VISITED", 600)
    monkeypatch.setattr(point, "_STEP", 3)
    assert answers(plain, ()) == want == answers(p, A.RULES)
    work = {r["measure"]: r["n"] for r in point.effort(g, p, q).collect()}
    bare = {r["measure"]: r["n"] for r in point.effort(g, plain, q).collect()}
    assert work["edges"] < bare["edges"] and all(work[r] > 0 for r in ("way_vertex", "way_required", "inbound", "certificate")) and all(bare[r] == 0 for r in A.RULES)


def test_traps(spark):
    rows, queries, want = [], [], {}
    for i, (_, text, s, d, p, truth) in enumerate(TRAPS):
        rows += [(100 * i + int(a), 100 * i + int(b), x) for a, x, b in (e.split("-") for e in text.split())]
        queries.append((i, 100 * i + s, 100 * i + d, p))
        want[i] = truth
    g = G.Graph.of(spark, rows).stored()
    q = asked(spark, queries)
    assert got(point.answer(g, point.build(g, IndexConfig(vertex_bits=7, k=3, way_count="one")), q)) == want
    without = {**want, 7: False}
    assert got(point.answer(g, point.build(g), q, empty_path=False)) == without == got(A.answer(g, q, None, A.SearchConfig(place="rounds", empty_path=False)))


def test_patterns_of_many_clauses_and_labels(spark):
    """A normal form beyond the bound is answered by its formula, in both forms; so are clauses that watch many labels."""
    names = [f"L{i}" for i in range(24)]
    g = G.Graph.of(spark, [(i, i + 1, x) for i, x in enumerate(names)] + [(5, 3, "L0")]).stored()
    many = " AND ".join(f"(L{2 * i} OR L{2 * i + 1})" for i in range(8))
    queries = [(1, 0, 16, many), (2, 0, 14, many), (3, 0, 24, f"ALL{{{','.join(names)}}}"), (4, 0, 23, f"ALL{{{','.join(names)}}}"), (5, 0, 4, "L3"), (6, 1, 6, "L0 AND L1")]
    want = {1: True, 2: False, 3: True, 4: False, 5: True, 6: True}
    q = asked(spark, queries)
    assert got(A.answer(g, q)) == want == got(point.answer(g, point.build(g), q))
    assert got(A.answer(g, q, None, A.SearchConfig(place="rounds"))) == want


def test_bounds(spark):
    g = G.Graph.of(spark, [(0, 1, "a"), (1, 2, "b")]).stored()
    with pytest.raises(point.TooLarge):
        point.load(g, most=1)
    empty = G.Graph.of(spark, []).stored()
    q = asked(spark, [(1, 0, 1, "a"), (2, 3, 3, "NOT a"), (3, 0, 1, "FALSE"), (4, None, None, "TRUE")])
    assert got(point.answer(empty, point.build(empty), q)) == {1: False, 2: True, 3: False, 4: False}


def test_index_beyond_the_bound(spark, monkeypatch):
    """A graph beyond the point form's bound is answered with the index that its query names, in the contracted graph or in rounds."""
    from pathsieve import entries

    small, used, build, rounds = "/root/testdata/sf0.001", [], point.build, entries.build_index
    monkeypatch.setattr(point, "build", lambda g, cfg=None, **more: (used.append(cfg), build(g, cfg, **more))[1])
    monkeypatch.setattr(entries, "build_index", lambda g, cfg=None: (used.append(cfg), rounds(g, cfg))[1])
    run = entries.queries()["same_answers_folded_labels"]
    want = got(run(spark, small))
    for most in (60, 5):
        monkeypatch.setattr(point, "MOST_EDGES", most)
        monkeypatch.setattr(point.load, "__defaults__", (most,))
        assert got(run(spark, small)) == want
    assert used and all(cfg.label_bits == 31 for cfg in used) and len(used) >= 3


def test_contracted_graphs(spark, monkeypatch):
    """Answers of contracted graphs equal brute force, with and without an index, for patterns with forbidden labels, null and unknown ends."""
    from pathsieve.plans import contract

    rng = random.Random(33)
    rows = random_edges(rng, 25) + [(1000 + i, 1000 + (i + 1) % 60, "a") for i in range(60)] + [(1000 + i, 1000 + (7 * i) % 60, "b") for i in range(60)]
    g = G.Graph.of(spark, rows).stored()
    queries, want = [(1000, None, 1001, "TRUE")], {1000: False}
    for qid in range(400):
        i, text = rng.randrange(27), rng.choice(TEXTS)
        s, d = (10 * i + rng.randrange(6) for _ in range(2)) if i < 25 else (1000 + rng.randrange(61) for _ in range(2))
        queries.append((qid, s, d, text))
        want[qid] = brute([r for r in rows if (r[0] // 10 == i if i < 25 else r[0] >= 1000)], s, d, P.parse_pattern(text, list("abcd")))
    most = len(set(rows)) - 70
    monkeypatch.setattr(point, "MOST_EDGES", most)
    for index in (True, False):
        found = contract.answer(g, g.vertices(), asked(spark, queries), index, IndexConfig(label_bits=31))
        assert got(found) == want
    chain = G.Graph.of(spark, [(i, i + 1, "a") for i in range(most + 9)]).stored()
    assert contract.answer(chain, chain.vertices(), asked(spark, queries)) is None
