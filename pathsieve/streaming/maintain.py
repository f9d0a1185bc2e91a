"""Keeping masks and standing answers while edges arrive and go."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathsieve.loop import cut
from pathsieve.operators.graph import Graph
from pathsieve.plans.index import IndexConfig, extend_masks, outbound_masks, tree_intervals
from pathsieve.plans.search import answer


class MaskMaintainer:
    """Edges, outbound masks, intervals and standing queries of a growing graph.

    ``add`` is made for ``foreachBatch``. Insertions widen masks along reverse edges until nothing changes. Deletions leave masks
    as they are, which is sound, for masks may hold too much; intervals prove paths, so those are rebuilt at once, and masks when
    more than ``stale_share`` of the edges have gone. Under insertion true answers stay true, so only false ones are asked again.
    """

    def __init__(self, g: Graph, cfg: IndexConfig | None = None, queries: DataFrame | None = None, stale_share: float = 0.1) -> None:
        self.cfg, self.queries, self.stale_share = cfg or IndexConfig(), queries, stale_share
        self.graph = g.stored()
        self.out = cut(outbound_masks(self.graph, self.cfg), "out")
        self.deleted = 0
        self._interval: DataFrame | None = None
        self.answers = cut(answer(self.graph, queries), "answers") if queries is not None else None

    @property
    def interval(self) -> DataFrame:
        if self._interval is None:
            self._interval = tree_intervals(self.graph)
        return self._interval

    def _labels(self, edges: DataFrame) -> DataFrame:
        """The dictionary with labels that are new put last."""
        old = self.graph.labels
        top = old.agg(F.max("lid")).first()[0]
        top = -1 if top is None else top
        from pyspark.sql import Window

        new = edges.select("label").distinct().join(old, "label", "left_anti")
        return cut(old.unionByName(new.select("label", (F.row_number().over(Window.orderBy("label")) + top).cast("int").alias("lid"))), "alphabet")

    def add(self, batch: DataFrame, batch_id: int = 0) -> None:
        """Take in a batch of edges; repeats change nothing."""
        new = cut(batch.select("src", "dst", "label").na.drop().distinct().join(self.graph.edges, ["src", "dst", "label"], "left_anti"), "added")
        if new.isEmpty():
            return
        labels = self._labels(new)
        self.graph = Graph(cut(self.graph.edges.unionByName(new), "graph"), labels)
        self.out = cut(extend_masks(self.out, self.graph, new, self.cfg), "out")
        self._interval = None
        if self.queries is not None:
            asked = self.queries.join(self.answers.where("NOT answer"), "qid", "left_semi")
            again = answer(self.graph, asked)
            self.answers = cut(self.answers.where("answer").unionByName(again), "answers")

    def delete(self, edges: DataFrame) -> None:
        """Take edges out."""
        gone = cut(self.graph.edges.join(edges.select("src", "dst", "label"), ["src", "dst", "label"], "left_semi"), "gone")
        self.deleted += gone.count()
        self.graph = Graph(cut(self.graph.edges.join(gone, ["src", "dst", "label"], "left_anti"), "graph"), self.graph.labels)
        self._interval = None
        if self.deleted > self.stale_share * max(1, self.graph.edges.count()):
            self.out, self.deleted = cut(outbound_masks(self.graph, self.cfg), "out"), 0
        if self.queries is not None:
            asked = self.queries.join(self.answers.where("answer"), "qid", "left_semi")
            self.answers = cut(self.answers.where("NOT answer").unionByName(answer(self.graph, asked)), "answers")

    def start(self, stream: DataFrame, checkpoint: str):
        """Run over all that is there of a stream of edges; returns the query."""
        return stream.writeStream.foreachBatch(self.add).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
