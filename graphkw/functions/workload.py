"""Seeded keyword queries that SQL can draw as well."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from graphkw.schema import Graph, KeywordQuery

SEED = "rks"


def draw_keywords(graph: Graph, count: int, size: int, seed: str = SEED) -> DataFrame:
    """(qid, kid, kw): for each query the first ``size`` keywords by the md5 of seed, query and keyword.

    A row per keyword holds the numbers of all queries; every partition keeps its ``size`` best of each query
    (the filter by a literal rank), so no more than that is moved.
    """
    pool = graph.postings.select("kw").distinct()
    drawn = pool.select(F.explode(F.sequence(F.lit(0), F.lit(count - 1))).alias("qid"), "kw")
    order = Window.partitionBy("qid").orderBy(F.md5(F.concat(F.lit(seed), F.col("qid").cast("string"), F.lit("|"), F.col("kw"))), "kw")
    return drawn.withColumn("kid", F.row_number().over(order)).filter(F.col("kid") <= size).select("qid", (F.col("kid") - 1).cast("int").alias("kid"), "kw")


def generate(graph: Graph, count: int, size: int, tau: int, k: int, seed: str = SEED) -> list[KeywordQuery]:
    """The drawn queries; as many rows as asked reach the driver."""
    words: dict[int, list[tuple[int, str]]] = {}
    for r in draw_keywords(graph, count, size, seed).collect():
        words.setdefault(r["qid"], []).append((r["kid"], r["kw"]))
    return [KeywordQuery(tuple(w for _, w in sorted(words[q])), tau, k, q) for q in sorted(words)]
