"""Connected components by alternating large and small stars.

Each half-step is a minimum per node (combined before it is moved) joined back to
the edges. The edges of a hub, two longs a row, meet in one task of that join unless
the session lets adaptive execution split it; they are streamed, never held. Every
round is written to the shared folder, which cuts the lineage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import Stage


def _star(edges: DataFrame, large: bool) -> DataFrame:
    """Links the larger (or the smaller) neighbours of each node to its least neighbour. Edges: a > b."""
    both = edges.select(F.col("a").alias("u"), F.col("b").alias("v"))
    if large:
        both = both.unionByName(edges.select(F.col("b").alias("u"), F.col("a").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    joined = both.join(least, "u")
    if large:
        out = joined.filter("v > u").select(F.col("v").alias("a"), F.col("m").alias("b"))
    else:
        out = joined.select(F.explode(F.array("u", "v")).alias("a"), F.col("m").alias("b"))
    return out.filter("a <> b").distinct()


def components(edges: DataFrame, label: str) -> DataFrame:
    """(node, root) for every node of ``edges`` (two columns of longs) but the roots; root: its component's least node."""
    a, b = edges.columns
    held = Stage(edges.select(F.greatest(a, b).alias("a"), F.least(a, b).alias("b")).filter("a <> b").distinct(), label)
    before = None
    while True:
        n, s = held.df.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if not n or (n, s) == before:
            return held.df.select(F.col("a").alias("node"), F.col("b").alias("root"))
        before = n, s
        after = Stage(_star(_star(held.df, True), False), label)
        held.drop()
        held = after
