import __spark_entry__ as entry


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_flagship(spark):
    rows = entry.entry(spark)
    assert rows.columns == ["qid", "answer"] and rows.count() == 20


def test_k_hop_of_every_customer(spark, tmp_path):
    """The neighbourhoods of all customers, whatever their ids, against brute force."""
    import random
    from datetime import datetime, timedelta

    rng = random.Random(3)
    labels = ["1-URGENT", "2-HIGH", "5-LOW"]
    rows = [(i, rng.randrange(1, 60), rng.choice("FO"), datetime(1995, 1, 1) + timedelta(days=i), rng.choice(labels)) for i in range(150)]
    spark.createDataFrame(rows, "o_orderkey long, o_custkey long, o_orderstatus string, o_orderdate timestamp_ntz, o_orderpriority string").write.parquet(f"{tmp_path}/orders.parquet")
    follows = {}
    for label in labels[:2]:
        line = [(r[1], r[2]) for r in rows if r[4] == label]
        for (a, status), (b, _) in zip(line, line[1:]):
            if status == "F" and a != b:
                follows.setdefault(a, set()).add(b)
    want = {}
    for src in follows:
        near = {src}
        for hops in (1, 2, 3):
            near = {b for a in near for b in follows.get(a, ())}
            for dst in near:
                want.setdefault((src, dst), hops)
    assert {(r.src, r.dst): r.hops for r in entry.queries()["k_hop_customer"](spark, str(tmp_path)).collect()} == want


def test_point_queries_beyond_the_bound_and_again(spark, monkeypatch):
    """A graph too large for arrays is answered in rounds, and each call reads its table anew."""
    from pathsieve import entries
    from pathsieve.plans import point

    small, read, table = "/root/testdata/sf0.001", [], entries.T.table
    monkeypatch.setattr(entries.T, "table", lambda s, d, name: (read.append(name), table(s, d, name))[1])
    run = entry.queries()["point_travel_style_part_chain"]
    want = sorted(map(tuple, run(spark, small).collect()))
    monkeypatch.setattr(point, "MOST_EDGES", 10)
    monkeypatch.setattr(point.load, "__defaults__", (10,))
    assert sorted(map(tuple, run(spark, small).collect())) == want and read == ["lineitem", "lineitem"]
