import pandas as pd
import pytest

from pathsieve.operators.graph import Graph
from pathsieve.plans.index import IndexConfig, outbound_masks
from pathsieve.plans.search import answer
from pathsieve.streaming import edges as E
from pathsieve.streaming.maintain import MaskMaintainer


def _run(stream, name, checkpoint, mode="append"):
    stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", str(checkpoint)).trigger(availableNow=True).start().awaitTermination()
    return stream.sparkSession.table(name)


@pytest.mark.parametrize("split", [1, 3, 7])
def test_chained_edges_equal_batch_in_any_split(spark, tmp_path, split):
    rows = pd.DataFrame({"ts": pd.date_range("2024-01-01", periods=40, freq="min"), "seq": range(40), "v": [(i * 7) % 11 for i in range(40)], "k": ["x" if i % 3 else "y" for i in range(40)]})
    for i in range(split):
        spark.createDataFrame(rows.iloc[i * 40 // split : (i + 1) * 40 // split]).coalesce(1).write.parquet(str(tmp_path / f"in/{i}"))
    stream = E.read_edges(spark, str(tmp_path / "in/*"), "ts timestamp, seq long, v long, k string")
    out = {tuple(r)[:3] for r in _run(E.chained_edges(stream, "k", "v", "ts", "seq"), f"chain{split}", tmp_path / "cp").where("src IS NOT NULL").collect()}
    want = set()
    for k, part in rows.groupby("k"):
        v = part.sort_values("ts").v.tolist()
        want |= {(a, b, k) for a, b in zip(v, v[1:])}
    assert out == want


def test_masks_follow_insertions_and_deletions(spark, tmp_path):
    rows = [(0, 1, "a"), (1, 2, "b"), (2, 3, "c"), (3, 1, "d"), (4, 0, "a"), (3, 5, "b")]
    cfg = IndexConfig(vertex_bits=31)
    q = spark.createDataFrame([(1, 0, 5, "b AND c"), (2, 4, 5, "NONE{a}"), (3, 1, 1, "d")], "qid long, src long, dst long, pattern string")
    m = MaskMaintainer(Graph.of(spark, rows[:2]), cfg, q)
    spark.createDataFrame(rows[2:], "src long, dst long, label string").repartition(3).write.parquet(str(tmp_path / "more"))
    m.start(E.read_edges(spark, str(tmp_path / "more"), "src long, dst long, label string"), str(tmp_path / "cp")).awaitTermination()
    whole = Graph.of(spark, rows).stored()
    assert {tuple(r) for r in m.out.collect()} == {tuple(r) for r in outbound_masks(whole, cfg).collect()}
    assert {tuple(r) for r in m.answers.collect()} == {tuple(r) for r in answer(whole, q).collect()} == {(1, True), (2, False), (3, True)}
    m.delete(spark.createDataFrame([(3, 5, "b")], "src long, dst long, label string"))
    assert {tuple(r) for r in m.answers.collect()} == {(1, False), (2, False), (3, True)}


def test_windows_and_repeats(spark, tmp_path):
    rows = pd.DataFrame({"ts": pd.to_datetime(["2024-01-01 00:10", "2024-01-01 00:20", "2024-01-02 01:00", "2024-01-05 00:00"]), "src": [1, 1, 2, 3], "dst": [2, 2, 3, 4], "label": ["a", "a", "b", "a"]})
    spark.createDataFrame(rows).coalesce(1).write.parquet(str(tmp_path / "in"))
    stream = lambda: E.read_edges(spark, str(tmp_path / "in"), "ts timestamp, src long, dst long, label string")
    assert _run(E.distinct_edges(stream(), "ts"), "distinct_edges", tmp_path / "a").count() == 3
    counts = {(str(r.start)[:10], r.label): r.n for r in _run(E.windowed_counts(stream(), "ts", "label"), "windowed", tmp_path / "b", "complete").collect()}
    assert counts == {("2024-01-01", "a"): 2, ("2024-01-02", "b"): 1, ("2024-01-05", "a"): 1}
    assert _run(E.session_counts(stream(), "ts", "src"), "sessions", tmp_path / "c").count() >= 1
