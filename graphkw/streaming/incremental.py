"""Continuous top-k under edge and posting insertions.

Insertions only lower distances, so the labels of all earlier graphs stay valid
upper bounds and an insertion is one more incremental step: the labels at the new
edges' targets are pending again. Deletions break this; they need a new search.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphkw.operators import waves
from graphkw.operators.bounds import top_answers
from graphkw.schema import Graph, KeywordQuery, merge_edges, query_frame
from graphkw.storage import Snapshot


@dataclass
class Continuous:
    """Edges, postings and labels so far of one standing query."""

    query: KeywordQuery
    edges: Snapshot
    postings: Snapshot
    labels: Snapshot
    rounds: int = 0

    @classmethod
    def start(cls, graph: Graph, query: KeywordQuery) -> Continuous:
        q = query_frame(graph.edges.sparkSession, [query])
        labels = waves.origins(graph.postings, q).withColumn("done", F.lit(None).cast("long"))
        out = cls(query, Snapshot(graph.edges), Snapshot(graph.postings), Snapshot(labels))
        out._settle()
        return out

    def _settle(self) -> None:
        spark = self.edges.spark
        cap = spark.createDataFrame([(self.query.qid, self.query.tau)], "qid int, cap long")
        while True:
            front = waves.pending(self.labels.df).select(*waves.KEY, "p")
            if front.isEmpty():
                return
            after = Snapshot(waves.merge(self.labels.df, front, waves.relax(front, self.edges.df, cap)))
            self.labels.drop()
            self.labels = after
            self.rounds += 1

    def insert(self, edges: DataFrame, postings: DataFrame | None = None) -> None:
        """One incremental step."""
        fresh = merge_edges(edges)
        touched = fresh.select(F.col("dst").alias("vid")).distinct()
        labels = self.labels.df
        again = labels.join(touched, "vid", "left_semi").select(*waves.KEY, "p", F.lit(None).cast("long").alias("done"))
        labels = labels.join(touched, "vid", "left_anti").unionByName(again)
        if postings is not None:
            q = query_frame(self.edges.spark, [self.query])
            labels = waves.merge(labels, labels.limit(0), waves.origins(postings, q))
            old = self.postings
            self.postings = Snapshot(old.df.unionByName(postings.select("kw", "vid")).distinct())
            old.drop()
        old_labels, self.labels = self.labels, Snapshot(labels)
        old_labels.drop()
        old_edges, self.edges = self.edges, Snapshot(merge_edges(self.edges.df.unionByName(fresh)))
        old_edges.drop()
        self._settle()

    def answers(self) -> DataFrame:
        q = query_frame(self.edges.spark, [self.query])
        return top_answers(waves.matches(self.labels.df, q).filter("complete"), {self.query.qid: self.query.k})
