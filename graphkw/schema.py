"""Tables of the engine and the small classes that describe graphs and queries."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Vertex ids are tag * TAG + key.
TAG = 10**12
EDGES = "src long, dst long, w long"
POSTINGS = "kw string, vid long"
QUERY = "qid int, kid int, kw string, tau long, k int, n int"
LABELS = "qid int, kid int, vid long, d long, leaf long"
FAR = (1 << 19) - 1


@dataclass(frozen=True)
class Graph:
    """vertices (vid, kind), edges (src, dst, w; one row per pair) and postings (kw, vid)."""

    vertices: DataFrame
    edges: DataFrame
    postings: DataFrame
    frags: DataFrame | None = None

    def undirected(self) -> Graph:
        return replace(self, edges=merge_edges(self.edges.unionByName(self.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w"))))


@dataclass(frozen=True)
class KeywordQuery:
    """Keywords (a set), distance threshold and number of answers."""

    keywords: tuple[str, ...]
    tau: int = 3
    k: int = 10
    qid: int = 0

    def __post_init__(self):
        words = dict.fromkeys(w.strip().lower() for w in self.keywords)
        words.pop("", None)
        if not words or self.tau < 0 or self.k < 1:
            raise ValueError("a query needs keywords, tau >= 0 and k >= 1")
        if self.tau >= FAR:
            raise ValueError(f"tau must be below {FAR}")
        object.__setattr__(self, "keywords", tuple(words))


def merge_edges(edges: DataFrame) -> DataFrame:
    """Parallel edges become their lightest, loops go, weights below 1 are an error."""
    w = F.when(F.col("w") > 0, F.col("w")).otherwise(F.raise_error(F.lit("an edge weight is not positive")).cast("long"))
    return edges.filter("src <> dst").groupBy("src", "dst").agg(F.min(w).alias("w"))


def query_frame(spark: SparkSession, queries: Iterable[KeywordQuery]) -> DataFrame:
    """One row per query and keyword; as small as what was asked."""
    rows = [(q.qid, i, w, q.tau, q.k, len(q.keywords)) for q in queries for i, w in enumerate(q.keywords)]
    return spark.createDataFrame(rows, QUERY)
