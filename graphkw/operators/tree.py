"""Match trees of answers, other result forms, filters and explanations."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphkw.functions.packing import distance, leaf
from graphkw.schema import Graph


def match_tree(graph: Graph, answers: DataFrame, labels: DataFrame, query: DataFrame, longest: int) -> DataFrame:
    """(qid, root, kw, pos, src, dst, w): the edges from each root to its nearest leaf of each keyword.

    From a vertex the next one is the least that is as much nearer to the keyword as the edge weighs and
    leads to the same leaf. Paths have at most ``longest`` edges; rows: answers times keywords times length.
    """
    lab = labels.select("qid", "kid", "vid", distance(F.col("p")).alias("d"), leaf(F.col("p")).alias("leaf"))
    roots = answers.select(F.col("qid").alias("q0"), "root")
    at = roots.join(lab, (F.col("q0") == F.col("qid")) & (F.col("root") == F.col("vid"))).select("qid", "kid", "root", "vid", "d", "leaf")
    nxt = lab.select(F.col("qid").alias("q2"), F.col("kid").alias("k2"), F.col("vid").alias("v2"), F.col("d").alias("d2"), F.col("leaf").alias("l2"))
    parts = []
    for pos in range(longest):
        step = at.filter("d > 0").join(graph.edges.select("src", "dst", "w"), F.col("vid") == F.col("src"))
        step = step.join(nxt, (F.col("qid") == F.col("q2")) & (F.col("kid") == F.col("k2")) & (F.col("dst") == F.col("v2")) & (F.col("d") - F.col("w") == F.col("d2")) & (F.col("leaf") == F.col("l2")))
        best = step.groupBy("qid", "kid", "root", "vid", "leaf").agg(F.min(F.struct("dst", "w", "d2")).alias("e")).select("qid", "kid", "root", "vid", "leaf", "e.*")
        parts.append(best.select("qid", "kid", "root", F.lit(pos).cast("int").alias("pos"), F.col("vid").alias("src"), "dst", "w"))
        at = best.select("qid", "kid", "root", F.col("dst").alias("vid"), F.col("d2").alias("d"), "leaf")
    rows = parts[0]
    for p in parts[1:]:
        rows = rows.unionByName(p)
    return rows.join(F.broadcast(query.select("qid", "kid", "kw")), ["qid", "kid"]).select("qid", "root", "kw", "pos", "src", "dst", "w")


def steiner_weight(tree: DataFrame, k_answers: DataFrame) -> DataFrame:
    """The tree's edges counted once: an approximation of the least connecting tree (one leaf per keyword)."""
    once = tree.select("qid", "root", "src", "dst", "w").distinct().groupBy("qid", "root").agg(F.sum("w").alias("weight"))
    return k_answers.join(once, ["qid", "root"], "left").select("qid", "root", "score", F.coalesce("weight", F.lit(0)).alias("weight"))


def explain_match(tree: DataFrame, graph: Graph) -> DataFrame:
    """(qid, root, kw, path): each path as text."""
    path = F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("pos", "dst"))), lambda x: x["dst"].cast("string")), " > ")
    return tree.groupBy("qid", "root", "kw").agg(F.concat(F.col("root").cast("string"), F.lit(" > "), path).alias("path"))


def with_root_kind(complete: DataFrame, graph: Graph, kind: str) -> DataFrame:
    """Complete matches whose root is of one kind."""
    return complete.join(graph.vertices.filter(F.col("kind") == kind).select("vid"), "vid", "left_semi")


def expand_prefix(graph: Graph, prefix: str, name: str) -> DataFrame:
    """Postings in which ``name`` stands for all keywords with a prefix (an OR within one slot)."""
    return graph.postings.unionByName(graph.postings.filter(F.col("kw").startswith(prefix)).select(F.lit(name).alias("kw"), "vid").distinct())
