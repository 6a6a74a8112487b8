"""Fragments of a graph: partitioners, border sets and their measures."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from graphkw.schema import TAG, Graph
from graphkw.storage import Snapshot


def hash_frag(v: Column, m: int) -> Column:
    """Kind and key both count, so that neighbours of equal keys do not fall together."""
    return F.pmod(7 * F.floor(v / F.lit(TAG)).cast("long") + F.pmod(v, F.lit(TAG)), F.lit(m)).cast("int")


def _neighbours(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("src").alias("vid"), F.col("dst").alias("near")).unionByName(edges.select(F.col("dst").alias("vid"), F.col("src").alias("near")))


def _vertices(graph: Graph) -> DataFrame:
    ends = _neighbours(graph.edges).select("vid")
    return ends.unionByName(graph.postings.select("vid")).unionByName(graph.vertices.select("vid")).distinct()


def _preferred(near: DataFrame, frags: DataFrame, vertices: DataFrame, m: int, size: float) -> DataFrame:
    """For each of ``vertices`` the fragment with most neighbours less a penalty for its load (m rows)."""
    load = frags.groupBy("frag").agg(F.count("*").alias("load"))
    votes = near.join(vertices, "vid", "left_semi").join(frags.select(F.col("vid").alias("near"), "frag"), "near").groupBy("vid", "frag").agg(F.count("*").alias("votes"))
    scored = votes.join(F.broadcast(load), "frag", "left").select("vid", F.struct((F.col("votes") * (1 - F.coalesce("load", F.lit(0)) / F.lit(size))).alias("s"), (-F.col("frag")).alias("f")).alias("x"))
    return scored.groupBy("vid").agg(F.max("x").alias("x")).filter("x.s > 0").select("vid", (-F.col("x.f")).cast("int").alias("frag"))


def partition(graph: Graph, m: int = 8, how: str = "hash", rounds: int = 4) -> Graph:
    """The graph with a table (vid, frag). Edge-cut: each vertex is owned once."""
    v = _vertices(graph)
    if how == "hash":
        frags = v.select("vid", hash_frag(F.col("vid"), m).alias("frag"))
    elif how == "range":
        bounds = v.approxQuantile("vid", [i / m for i in range(1, m)], 0.01)
        frags = v.select("vid", sum(((F.col("vid") > b).cast("int") for b in bounds), F.lit(0)).alias("frag"))
    elif how == "by_kind":
        frags = v.select("vid", F.pmod(F.floor(F.col("vid") / F.lit(TAG)).cast("int"), F.lit(m)).alias("frag"))
    elif how in ("balanced_lp", "greedy_stream"):
        near, n = _neighbours(graph.edges), v.count()
        size = 1.1 * n / m + 1
        if how == "balanced_lp":
            held = Snapshot(v.select("vid", hash_frag(F.col("vid"), m).alias("frag")))
            for r in range(rounds):
                turn = v.filter(F.pmod(F.xxhash64("vid", F.lit(r)), F.lit(2)) == 0)
                want = _preferred(near, held.df, turn, m, 2 * size).withColumnRenamed("frag", "to")
                moved = held.df.join(want, "vid", "left")
                # Fragments above their size let in only the room they have: the first by hash.
                load = held.df.groupBy("frag").agg(F.count("*").alias("load")).select(F.col("frag").alias("to"), "load")
                room = F.greatest(F.lit(0.0), F.lit(size) - F.coalesce("load", F.lit(0)))
                share = moved.filter("to <> frag").groupBy("to").agg(F.count("*").alias("wish")).join(load, "to", "left").select("to", (room / F.col("wish")).alias("share"))
                ok = F.pmod(F.xxhash64("vid", F.lit(r), F.lit("in")), F.lit(1000)) < F.coalesce("share", F.lit(0.0)) * 1000
                after = Snapshot(moved.join(F.broadcast(share), "to", "left").select("vid", F.when(ok & F.col("to").isNotNull(), F.col("to")).otherwise(F.col("frag")).alias("frag")))
                held.drop()
                held = after
        else:
            held = Snapshot(v.filter(F.pmod(F.xxhash64("vid"), F.lit(2 * rounds)) == 0).select("vid", hash_frag(F.col("vid"), m).alias("frag")))
            for r in range(1, 2 * rounds):
                turn = v.filter(F.pmod(F.xxhash64("vid"), F.lit(2 * rounds)) == r)
                want = turn.join(_preferred(near, held.df, turn, m, size), "vid", "left").select("vid", F.coalesce("frag", hash_frag(F.col("vid"), m)).alias("frag"))
                after = Snapshot(held.df.unionByName(want))
                held.drop()
                held = after
        frags = held.df
    else:
        raise ValueError(f"no such partitioner: {how}")
    return replace(graph, frags=frags)


def hold(graph: Graph, m: int, how: str = "hash") -> Graph:
    """The graph with its fragments, its edges, postings and fragments each written once: whoever reads them goes back to no source."""
    graph = replace(graph, edges=Snapshot(graph.edges).df, postings=Snapshot(graph.postings).df)
    graph = graph if graph.frags is not None else partition(graph, m, how)
    return replace(graph, frags=Snapshot(graph.frags).df)


def framed_edges(graph: Graph) -> DataFrame:
    """Edges with the fragments of both ends."""
    side = lambda c: graph.frags.select(F.col("vid").alias(c), F.col("frag").alias(f"{c}_frag"))
    return graph.edges.join(side("src"), "src").join(side("dst"), "dst").select("src", "dst", "w", "src_frag", "dst_frag")


def borders(graph: Graph) -> tuple[DataFrame, DataFrame]:
    """Owned vertices that other fragments point to, and foreign vertices that a fragment points to: (frag, vid) each."""
    cross = framed_edges(graph).filter("src_frag <> dst_frag")
    return cross.select(F.col("dst_frag").alias("frag"), F.col("dst").alias("vid")).distinct(), cross.select(F.col("src_frag").alias("frag"), F.col("dst").alias("vid")).distinct()


def measures(graph: Graph) -> DataFrame:
    """Edge-cut and size of each fragment."""
    cut = framed_edges(graph).groupBy(F.col("src_frag").alias("frag")).agg(F.count("*").alias("n_edges"), F.sum((F.col("src_frag") != F.col("dst_frag")).cast("long")).alias("n_cross"))
    return graph.frags.groupBy("frag").agg(F.count("*").alias("n_vertices")).join(cut, "frag", "left").select("frag", "n_vertices", F.coalesce("n_edges", F.lit(0)).alias("n_edges"), F.coalesce("n_cross", F.lit(0)).alias("n_cross"))
