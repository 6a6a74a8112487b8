"""Distances from (or to) sets of seeds, many sets at once, and keyed closures."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphkw.storage import Bucketed, Snapshot


def spread(edges: DataFrame, seeds: DataFrame, cap: int, backwards: bool = True) -> DataFrame:
    """(key, vid, d <= cap): least distance of each vertex to (forwards: from) a seed of the key, as label-correcting rounds.

    Seeds may bring a ``d`` that they start with. The edges are written once, dealt by the end that rounds join on.
    """
    near, far = ("dst", "src") if backwards else ("src", "dst")
    steps = Bucketed(edges.filter(F.col("w") <= cap).select(F.col(near).alias("at"), F.col(far).alias("to"), "w"), "at")
    start = F.col("d") if "d" in seeds.columns else F.lit(0)
    fresh = (F.sum(F.col("fresh").cast("long")).alias("fresh"),)
    first = seeds.select("key", "vid", start.cast("long").alias("d")).filter(F.col("d") <= cap).groupBy("key", "vid").agg(F.min("d").alias("d"))
    held = Snapshot(first.withColumn("fresh", F.lit(True)), fresh)
    while held.seen["fresh"]:
        front = held.df.filter("fresh")
        found = front.join(steps.df, F.col("vid") == F.col("at")).select("key", F.col("to").alias("vid"), (F.col("d") + F.col("w")).alias("d")).filter(F.col("d") <= cap)
        old = held.df.select("key", "vid", "d", F.col("d").alias("was"))
        merged = old.unionByName(found.withColumn("was", F.lit(None).cast("long"))).groupBy("key", "vid").agg(F.min("d").alias("d"), F.min("was").alias("was"))
        after = Snapshot(merged.select("key", "vid", "d", (F.col("was").isNull() | (F.col("d") < F.col("was"))).alias("fresh")), fresh)
        held.drop()
        held = after
    steps.drop()
    return held.df.select("key", "vid", "d")
