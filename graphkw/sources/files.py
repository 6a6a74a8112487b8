"""Graphs from and to files: edge lists, triples, partitioned and bucketed stores."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphkw.operators.partition import framed_edges, hash_frag, partition
from graphkw.schema import EDGES, POSTINGS, Graph, merge_edges
from graphkw.storage import shared_dir


def load_edge_list(spark: SparkSession, path: str, kind: str = "csv", postings: str | None = None, separator: str = ",") -> Graph:
    """Edges (src, dst, w) from CSV/TSV, JSON lines or Parquet, and postings (kw, vid) in the same format."""

    def read(at: str, schema: str) -> DataFrame:
        reader = spark.read.schema(schema)
        return reader.option("sep", separator).csv(at) if kind == "csv" else reader.json(at) if kind == "json" else reader.parquet(at)

    edges = merge_edges(read(path, EDGES))
    named = read(postings, POSTINGS).select(F.lower(F.trim("kw")).alias("kw"), "vid").filter("kw <> ''").distinct() if postings else spark.createDataFrame([], POSTINGS)
    vertices = edges.select(F.col("src").alias("vid")).unionByName(edges.select(F.col("dst").alias("vid"))).distinct().withColumn("kind", F.lit("node"))
    return Graph(vertices, edges, named)


def load_triples(spark: SparkSession, path: str) -> Graph:
    """N-Triples-like lines ``<subject> <predicate> <object> .``; literals become keywords, ids are 43-bit hashes."""
    part = lambda i: F.regexp_extract("value", r'^\s*<([^>]*)>\s+<([^>]*)>\s+(?:<([^>]*)>|"([^"]*)").*$', i)
    number = lambda c: F.shiftrightunsigned(F.xxhash64(c), 21)
    rows = spark.read.text(path).select(part(1).alias("s"), part(3).alias("o"), part(4).alias("text")).filter("s <> ''")
    edges = merge_edges(rows.filter("o <> ''").select(number("s").alias("src"), number("o").alias("dst"), F.lit(1).cast("long").alias("w")))
    postings = rows.filter("text <> ''").select(F.explode(F.split(F.lower("text"), r"\s+")).alias("kw"), number("s").alias("vid")).filter("kw <> ''").distinct()
    vertices = rows.select(number("s").alias("vid")).unionByName(rows.filter("o <> ''").select(number("o").alias("vid"))).distinct().withColumn("kind", F.lit("resource"))
    return Graph(vertices, edges, postings)


def save_graph(graph: Graph, path: str, m: int = 8) -> None:
    """Edges by the fragment of their target, so that a wave reads only fragments it touches; postings sorted by keyword."""
    g = graph if graph.frags is not None else partition(graph, m)
    framed_edges(g).write.mode("overwrite").partitionBy("dst_frag").parquet(f"{path}/edges")
    g.postings.repartitionByRange("kw").sortWithinPartitions("kw", "vid").write.mode("overwrite").parquet(f"{path}/postings")
    g.vertices.write.mode("overwrite").parquet(f"{path}/vertices")
    g.frags.write.mode("overwrite").parquet(f"{path}/frags")


def load_graph(spark: SparkSession, path: str) -> Graph:
    read = lambda name: spark.read.parquet(f"{path}/{name}")
    return Graph(read("vertices"), read("edges").select("src", "dst", "w"), read("postings"), read("frags"))


def partitioned_round_trip(graph: Graph) -> DataFrame:
    spark = graph.edges.sparkSession
    path = f"{shared_dir(spark)}/store-{uuid.uuid4().hex}"
    save_graph(graph, path, 4)
    return load_graph(spark, path).edges


def bucketed_round_trip(graph: Graph) -> DataFrame:
    """Edges bucketed and sorted by target, as a table of the session's catalog."""
    spark = graph.edges.sparkSession
    name = f"edges_{uuid.uuid4().hex}"
    graph.edges.write.bucketBy(8, "dst").sortBy("dst").option("path", f"{shared_dir(spark)}/{name}").saveAsTable(name)
    return spark.table(name)


def text_round_trip(graph: Graph) -> DataFrame:
    """Half of the edges by CSV and half by JSON lines, written and loaded again."""
    spark = graph.edges.sparkSession
    path = f"{shared_dir(spark)}/lists-{uuid.uuid4().hex}"
    half = F.pmod(F.col("src"), F.lit(2)) == 0
    graph.edges.filter(half).write.csv(f"{path}/csv")
    graph.edges.filter(~half).write.json(f"{path}/json")
    return load_edge_list(spark, f"{path}/csv").edges.unionByName(load_edge_list(spark, f"{path}/json", "json").edges)


__all__ = ["bucketed_round_trip", "hash_frag", "load_edge_list", "load_graph", "load_triples", "partitioned_round_trip", "save_graph", "text_round_trip"]
