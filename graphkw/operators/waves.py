"""Waves of labels along incoming edges, and of demands along outgoing ones.

A label row (qid, kid, vid, p) says that vertex vid reaches a holder of keyword kid
at the distance packed in p. ``done`` is the p at which the vertex was last
expanded; a label is pending while its p is less. All merges are minima (or maxima
of budgets), so a replayed round changes nothing.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphkw.functions.packing import distance, leaf, pack

KEY = ["qid", "kid", "vid"]


def origins(postings: DataFrame, query: DataFrame) -> DataFrame:
    """Holders of each keyword, as labels of distance 0."""
    return postings.join(F.broadcast(query.select("qid", "kid", "kw")), "kw").select("qid", "kid", "vid", pack(F.lit(0), F.col("vid")).alias("p")).distinct()


def pending(labels: DataFrame) -> DataFrame:
    return labels.filter(F.col("done").isNull() | (F.col("p") < F.col("done")))


def relax(frontier: DataFrame, edges: DataFrame, limits: DataFrame) -> DataFrame:
    """New labels of the sources of the frontier's incoming edges, within each query's limit."""
    reached = frontier.join(edges, frontier["vid"] == edges["dst"]).select("qid", "kid", F.col("src").alias("vid"), (distance(F.col("p")) + F.col("w")).alias("d"), leaf(F.col("p")).alias("leaf"))
    return reached.join(F.broadcast(limits), "qid").filter("d <= cap").select(*KEY, pack(F.col("d"), F.col("leaf")).alias("p"))


def merge(labels: DataFrame, expanded: DataFrame, found: DataFrame) -> DataFrame:
    """Least label per key; rows of ``expanded`` count as expanded at their present p."""
    marks = expanded.select(*KEY, "p", F.col("p").alias("done"))
    fresh = found.select(*KEY, "p", F.lit(None).cast("long").alias("done"))
    rows = labels.select(*KEY, "p", "done").unionByName(marks).unionByName(fresh)
    return rows.groupBy(*KEY).agg(F.min("p").alias("p"), F.min("done").alias("done"))


def walk_demands(frontier: DataFrame, edges: DataFrame) -> DataFrame:
    """What the targets of outgoing edges may still cost."""
    return frontier.join(edges, frontier["vid"] == edges["src"]).select("qid", "kid", F.col("dst").alias("vid"), (F.col("budget") - F.col("w")).alias("budget")).filter("budget >= 0")


def merge_demands(demands: DataFrame, expanded: DataFrame, found: DataFrame) -> DataFrame:
    """Largest budget per key; ``done`` is the budget served last."""
    marks = expanded.select(*KEY, "budget", F.col("budget").alias("done"))
    fresh = found.select(*KEY, "budget", F.lit(None).cast("long").alias("done"))
    rows = demands.select(*KEY, "budget", "done").unionByName(marks).unionByName(fresh)
    return rows.groupBy(*KEY).agg(F.max("budget").alias("budget"), F.max("done").alias("done"))


def matches(labels: DataFrame, query: DataFrame) -> DataFrame:
    """Per query and vertex: keywords reached, score so far, and whether all are reached."""
    sizes = query.select("qid", "n").distinct()
    found = labels.groupBy("qid", "vid").agg(F.count("*").alias("found"), F.sum(distance(F.col("p"))).alias("score"))
    return found.join(F.broadcast(sizes), "qid").withColumn("complete", F.col("found") == F.col("n"))


#: In-edges of one vertex that a task may meet; vertices with more are split by their edges' sources.
HUB = 1_000_000


def hubs(edges: DataFrame, most: int = HUB) -> DataFrame:
    """(vid, parts) of the vertices with more than ``most`` edges into them."""
    return edges.groupBy(F.col("dst").alias("vid")).agg(F.count("*").alias("n")).filter(F.col("n") > most).select("vid", F.ceil(F.col("n") / most).cast("int").alias("parts"))


def split_edges(edges: DataFrame, hub: DataFrame) -> DataFrame:
    """The edges with ``part``: 0, or for edges into hubs one of the hub's parts."""
    return edges.join(hub, edges["dst"] == hub["vid"], "left").select("src", "dst", "w", F.coalesce(F.pmod(F.xxhash64("src"), F.col("parts")), F.lit(0)).cast("int").alias("part"))


def relax_split(frontier: DataFrame, edges: DataFrame, hub: DataFrame, limits: DataFrame) -> DataFrame:
    """``relax`` over ``split_edges``: a hub's frontier row goes to all its parts."""
    dealt = frontier.join(hub, "vid", "left").withColumn("part", F.explode(F.sequence(F.lit(0), F.coalesce("parts", F.lit(1)) - 1)))
    reached = dealt.join(edges, (dealt["vid"] == edges["dst"]) & (dealt["part"] == edges["part"]))
    reached = reached.select("qid", "kid", F.col("src").alias("vid"), (distance(F.col("p")) + F.col("w")).alias("d"), leaf(F.col("p")).alias("leaf"))
    return reached.join(F.broadcast(limits), "qid").filter("d <= cap").select(*KEY, pack(F.col("d"), F.col("leaf")).alias("p"))


def visited_sets(labels: DataFrame, query: DataFrame) -> DataFrame:
    """Sizes of the union, the intersection and the difference of the keywords' visited sets."""
    m = matches(labels, query)
    return m.groupBy("qid").agg(F.count("*").alias("n_union"), F.sum(F.col("complete").cast("long")).alias("n_all"), F.sum((~F.col("complete")).cast("long")).alias("n_some"))
