"""Baselines: exhaustive, sequential and all pairs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphkw.operators.reach import spread
from graphkw.plans.search import Result, search
from graphkw.reference import sequential
from graphkw.schema import Graph, KeywordQuery


def exhaustive(graph: Graph, query: KeywordQuery) -> Result:
    """No bound at all: every vertex within tau of every keyword is found, and all complete ones are candidates to verify."""
    return search(graph, query, "exhaustive")


def sequential_answers(graph: Graph, query: KeywordQuery) -> DataFrame:
    """The one-machine baseline, in a single task by design: it reads the whole graph there."""
    edges = graph.edges.select(F.lit("e").alias("t"), F.lit("").alias("kw"), F.col("src").alias("a"), F.col("dst").alias("b"), "w")
    held = graph.postings.filter(F.col("kw").isin(*query.keywords)).select(F.lit("p").alias("t"), "kw", F.col("vid").alias("a"), F.lit(0).cast("long").alias("b"), F.lit(0).cast("long").alias("w"))

    def run(batches):
        import pandas as pd

        rows = [r for b in batches for r in b.itertuples(index=False)]
        found, _ = sequential([(r.a, r.b, r.w) for r in rows if r.t == "e"], [(r.kw, r.a) for r in rows if r.t == "p"], query)
        yield pd.DataFrame([(query.qid, i + 1, r, s) for i, (r, s) in enumerate(found)], columns=["qid", "rank", "root", "score"])

    return edges.unionByName(held).coalesce(1).mapInPandas(run, "qid int, rank int, root long, score long")


def all_pairs(graph: Graph, cap: int) -> DataFrame:
    """(src, dst, d) of all pairs within ``cap``: quadratic, for small graphs and as an oracle only."""
    ends = graph.edges.select(F.col("dst").alias("key"), F.col("dst").alias("vid")).distinct()
    return spread(graph.edges, ends, cap).select(F.col("vid").alias("src"), F.col("key").alias("dst"), "d")
