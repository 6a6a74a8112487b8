"""Graphs built from the given tables. Each builder has its SQL twin in ``tables_sql``."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from graphkw.schema import TAG, Graph, merge_edges

REGION, NATION, CUSTOMER, SUPPLIER, PART, ORDER, PAGE, TARGET, HOST, USER, EVENT, DOCUMENT, VECTOR, TURN, CONVERSATION, SOURCE = range(1, 17)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def vid(tag: int, key: str | Column) -> Column:
    return F.lit(tag * TAG) + (F.col(key) if isinstance(key, str) else key).cast("long")


def edge(df: DataFrame, src: Column, dst: Column, w: Column | int = 1) -> DataFrame:
    return df.select(src.alias("src"), dst.alias("dst"), (F.lit(w) if isinstance(w, int) else w).cast("long").alias("w")).filter("src IS NOT NULL AND dst IS NOT NULL")


def words(df: DataFrame, text: Column, at: Column) -> DataFrame:
    """Postings of every non-empty word of ``text``."""
    return df.select(F.explode(F.split(F.lower(text), " ")).alias("kw"), at.alias("vid")).filter("kw <> '' AND vid IS NOT NULL").distinct()


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def name_number(text: Column) -> Column:
    """A stable number below 10**11 for a string key, the same in SQL."""
    return F.conv(F.substring(F.md5(text), 1, 9), 16, 10).cast("long")


def trade(spark: SparkSession, sf_dir: str) -> Graph:
    """Orders point to customers and parts, these to nations and suppliers, nations to regions."""
    t = {n: table(spark, sf_dir, n) for n in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem")}
    line = t["lineitem"]
    per_order = F.least(F.lit(1) + F.floor(F.col("l_quantity").cast("long") / 10), F.lit(1 << 18))
    per_part = F.lit(1) + F.floor(F.round(F.col("l_discount") * 100).cast("long") / 2)
    edges = _union(
        [
            edge(t["orders"], vid(ORDER, "o_orderkey"), vid(CUSTOMER, "o_custkey")),
            edge(t["customer"], vid(CUSTOMER, "c_custkey"), vid(NATION, "c_nationkey")),
            edge(t["supplier"], vid(SUPPLIER, "s_suppkey"), vid(NATION, "s_nationkey")),
            edge(t["nation"], vid(NATION, "n_nationkey"), vid(REGION, "n_regionkey")),
            edge(line, vid(ORDER, "l_orderkey"), vid(PART, "l_partkey"), per_order),
            edge(line, vid(PART, "l_partkey"), vid(SUPPLIER, "l_suppkey"), per_part),
        ]
    )
    postings = _union(
        [
            words(t["region"], F.col("r_name"), vid(REGION, "r_regionkey")),
            words(t["nation"], F.col("n_name"), vid(NATION, "n_nationkey")),
            words(t["customer"], F.col("c_mktsegment"), vid(CUSTOMER, "c_custkey")),
            words(t["part"], F.concat_ws(" ", "p_name", "p_brand", "p_type"), vid(PART, "p_partkey")),
            t["orders"].select(F.explode(F.array(F.lower("o_orderpriority"), F.concat(F.lit("status_"), F.lower("o_orderstatus")))).alias("kw"), vid(ORDER, "o_orderkey").alias("vid")).filter("kw IS NOT NULL"),
        ]
    ).distinct()
    kinds = [("region", REGION, "r_regionkey"), ("nation", NATION, "n_nationkey"), ("customer", CUSTOMER, "c_custkey"), ("supplier", SUPPLIER, "s_suppkey"), ("part", PART, "p_partkey"), ("orders", ORDER, "o_orderkey")]
    vertices = _union([t[n].select(vid(tag, key).alias("vid"), F.lit(n).alias("kind")) for n, tag, key in kinds])
    return Graph(vertices, merge_edges(edges), postings)


def trade_unit(spark: SparkSession, sf_dir: str) -> Graph:
    g = trade(spark, sf_dir)
    return Graph(g.vertices, g.edges.withColumn("w", F.lit(1).cast("long")), g.postings)


def trade_reversible(spark: SparkSession, sf_dir: str) -> Graph:
    """Every edge also backwards, one heavier: cycles and hubs."""
    g = trade(spark, sf_dir)
    back = g.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), (F.col("w") + 1).alias("w"))
    return Graph(g.vertices, merge_edges(g.edges.unionByName(back)), g.postings)


def web(spark: SparkSession, sf_dir: str) -> Graph:
    """Pages, the targets of their links, and hosts; a target points to the pages whose title holds its word."""
    pages = table(spark, sf_dir, "pages").select("page_id", F.regexp_extract("url", "://([^/]+)", 1).alias("host"), F.regexp_extract("html", "<title>([^<]*)</title>", 1).alias("title"), F.regexp_extract("html", 'lang="([^"]*)"', 1).alias("lang"), F.regexp_extract_all("html", F.lit('href="/([^"]*)"'), 1).alias("targets"))
    links = pages.select("page_id", F.explode("targets").alias("target")).filter("target <> ''").distinct()
    titles = words(pages, F.col("title"), F.col("page_id")).select("kw", F.col("vid").alias("page_id"))
    target = vid(TARGET, name_number(F.col("target")))
    named = links.select("target").distinct().withColumn("kw", F.lower("target"))
    back = named.join(titles, "kw")
    page, host = vid(PAGE, "page_id"), vid(HOST, name_number(F.col("host")))
    edges = _union([edge(links, page, target), edge(back, target, page), edge(pages, page, host), edge(pages, host, page)])
    postings = _union([titles.select("kw", page.alias("vid")), pages.select(F.lower("lang").alias("kw"), page.alias("vid")).filter("kw <> ''"), pages.select(F.lower("host").alias("kw"), host.alias("vid")).filter("kw <> ''")]).distinct()
    vertices = _union([pages.select(page.alias("vid"), F.lit("page").alias("kind")), links.select(target.alias("vid"), F.lit("target").alias("kind")).distinct(), pages.select(host.alias("vid"), F.lit("host").alias("kind")).distinct()])
    return Graph(vertices, merge_edges(edges), postings)


def copurchase(spark: SparkSession, sf_dir: str) -> Graph:
    """Customers who bought one part in one month, nearer the more parts they share."""
    orders, line = table(spark, sf_dir, "orders"), table(spark, sf_dir, "lineitem")
    month = F.date_format("o_orderdate", "yyyyMM")
    bought = orders.join(line, orders["o_orderkey"] == line["l_orderkey"]).select("o_custkey", "l_partkey", month.alias("month")).distinct()
    other = bought.select(F.col("o_custkey").alias("to"), "l_partkey", "month")
    shared = bought.join(other, ["l_partkey", "month"]).filter("o_custkey <> to").groupBy("o_custkey", "to").agg(F.count_distinct("l_partkey").alias("n"))
    edges = edge(shared, vid(CUSTOMER, "o_custkey"), vid(CUSTOMER, "to"), F.lit(5) - F.least(F.lit(4), F.col("n")))
    customer, nation = table(spark, sf_dir, "customer"), table(spark, sf_dir, "nation")
    at = vid(CUSTOMER, "c_custkey")
    named = customer.join(F.broadcast(nation), customer["c_nationkey"] == nation["n_nationkey"])
    postings = _union([words(customer, F.col("c_mktsegment"), at), words(named, F.col("n_name"), at), orders.select(F.lower("o_orderpriority").alias("kw"), vid(CUSTOMER, "o_custkey").alias("vid")).filter("kw IS NOT NULL")]).distinct()
    return Graph(customer.select(at.alias("vid"), F.lit("customer").alias("kind")), merge_edges(edges), postings)


def journeys(spark: SparkSession, sf_dir: str) -> Graph:
    """Each event points to its user and to the user's next event, farther the longer the pause."""
    events = table(spark, sf_dir, "events")
    following = Window.partitionBy("user_id").orderBy("ts", "event_id")
    steps = events.select("event_id", "user_id", F.lead("event_id").over(following).alias("next"), (F.unix_micros(F.lead("ts").over(following).cast("timestamp")) - F.unix_micros(F.col("ts").cast("timestamp"))).alias("pause"))
    at = vid(EVENT, "event_id")
    edges = _union([edge(steps.filter("next IS NOT NULL"), at, vid(EVENT, "next"), F.lit(1) + F.least(F.lit(4), F.floor(F.col("pause") / (6 * 3600 * 10**6)))), edge(events, at, vid(USER, "user_id"))])
    number = F.regexp_extract("props", '"k": *([0-9]+)', 1)
    postings = _union(
        [
            events.select(F.lower("event_type").alias("kw"), at.alias("vid")),
            events.filter(number != "").select(F.concat(F.lit("k_"), number).alias("kw"), at.alias("vid")),
            events.select(F.concat(F.lit("band_"), F.floor(F.col("value") / 10).cast("string")).alias("kw"), at.alias("vid")),
        ]
    ).filter("kw IS NOT NULL").distinct()
    vertices = events.select(at.alias("vid"), F.lit("event").alias("kind")).unionByName(events.select(vid(USER, "user_id").alias("vid"), F.lit("user").alias("kind")).distinct())
    return Graph(vertices, merge_edges(edges), postings)


def _nearest(neighbours: int):
    def run(left, right):
        """The pairs of two blocks that may be among the nearest; ties with the last one stay."""
        if left.empty or right.empty:
            return pd.DataFrame({"vec_id": [], "to": [], "c": []})
        x, y = left["vec_id"].to_numpy(), right["vec_id"].to_numpy()
        c = np.round(np.stack(left["e"].to_numpy()) @ np.stack(right["e"].to_numpy()).T, 12)
        c[x[:, None] == y[None, :]] = -np.inf
        k = min(neighbours, c.shape[1])
        i, j = np.nonzero((c >= np.partition(c, -k, axis=1)[:, -k, None]) & (c > -np.inf))
        return pd.DataFrame({"vec_id": x[i], "to": y[j], "c": c[i, j]})

    return run


def vectors(spark: SparkSession, sf_dir: str, neighbours: int = 5, block: int = 2000) -> Graph:
    """Each vector points to its nearest by cosine (rounded to 12 digits; of equal ones the least id).

    Every block of vectors meets every block in one matrix product, so the answer is exact and no task holds
    more than two blocks. Weights grow with one minus the cosine.
    """
    v = table(spark, sf_dir, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("e"), F.lower(F.concat(F.lit("label_"), F.col("label").cast("string"))).alias("kw"))
    norm = lambda e: F.sqrt(F.aggregate(e, F.lit(0.0), lambda a, x: a + x * x))
    v = v.withColumn("e", F.transform("e", lambda x: x / norm(F.col("e"))))
    blocks = max(1, -(-v.count() // block))
    dealt = v.filter("vec_id IS NOT NULL AND e IS NOT NULL").select("vec_id", "e", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).alias("own"))
    other = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("other")
    met = dealt.select("own", other, "vec_id", "e")
    left = met.select(F.col("own").alias("i"), F.col("other").cast("long").alias("j"), "vec_id", "e")
    right = met.select(F.col("other").cast("long").alias("i"), F.col("own").alias("j"), "vec_id", "e")
    scored = left.groupBy("i", "j").cogroup(right.groupBy("i", "j")).applyInPandas(_nearest(neighbours), "vec_id long, to long, c double")
    rank = F.row_number().over(Window.partitionBy("vec_id").orderBy(F.desc("c"), "to"))
    near = scored.withColumn("r", rank).filter(F.col("r") <= neighbours)
    edges = edge(near, vid(VECTOR, "vec_id"), vid(VECTOR, "to"), F.lit(1) + F.greatest(F.lit(0), F.floor(10 * (1 - F.col("c")))))
    return Graph(v.select(vid(VECTOR, "vec_id").alias("vid"), F.lit("vector").alias("kind")), merge_edges(edges), v.select("kw", vid(VECTOR, "vec_id").alias("vid")))


def texts(spark: SparkSession, sf_dir: str, line_chars: int = 40) -> Graph:
    """Documents point to their source and, over a vertex for each, to long lines they share."""
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    at = vid(DOCUMENT, "doc_id")
    lines = docs.select("doc_id", F.explode(F.split("text", "\n")).alias("line")).filter(F.length("line") >= line_chars).select("doc_id", name_number(F.col("line")).alias("line")).distinct()
    shared = lines.join(lines.groupBy("line").agg(F.count("*").alias("n")).filter("n > 1").select("line"), "line")
    source = vid(SOURCE, name_number(F.col("source")))
    line = vid(TARGET, "line")
    edges = _union([edge(docs, at, source), edge(shared, at, line), edge(shared, line, at)])
    tags = labels.select(F.explode(F.array(F.concat(F.lit("quality_"), F.col("quality").cast("string")), F.concat(F.lit("toxic_"), F.col("toxic").cast("string")))).alias("kw"), vid(DOCUMENT, "doc_id").alias("vid"))
    postings = _union([docs.select(F.lower("lang").alias("kw"), at.alias("vid")), docs.select(F.lower("source").alias("kw"), source.alias("vid")), tags]).filter("kw IS NOT NULL").distinct()
    vertices = _union([docs.select(at.alias("vid"), F.lit("document").alias("kind")), docs.select(source.alias("vid"), F.lit("source").alias("kind")).distinct(), shared.select(line.alias("vid"), F.lit("line").alias("kind")).distinct()])
    return Graph(vertices, merge_edges(edges), postings)


def dialogues(spark: SparkSession, sf_dir: str) -> Graph:
    """Turns point to the next turn and to their conversation."""
    turns = table(spark, sf_dir, "conversations")
    at = vid(TURN, F.col("conv_id") * 100 + F.col("turn"))
    following = Window.partitionBy("conv_id").orderBy("turn")
    steps = turns.withColumn("next", F.lead("turn").over(following))
    edges = _union([edge(steps.filter("next IS NOT NULL"), at, vid(TURN, F.col("conv_id") * 100 + F.col("next"))), edge(turns, at, vid(CONVERSATION, "conv_id"))])
    tokens = turns.select(F.explode(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), 0)).alias("kw"), at.alias("vid")).filter(F.length("kw") >= 4)
    postings = tokens.unionByName(turns.select(F.lower("role").alias("kw"), at.alias("vid")).filter("kw IS NOT NULL")).distinct()
    vertices = turns.select(at.alias("vid"), F.lit("turn").alias("kind")).unionByName(turns.select(vid(CONVERSATION, "conv_id").alias("vid"), F.lit("conversation").alias("kind")).distinct())
    return Graph(vertices, merge_edges(edges), postings)


def synthetic(spark: SparkSession, n_vertices: int, n_edges: int, labels: int = 50, seed: int = 7, max_weight: int = 3) -> Graph:
    """A seeded random graph with one label per vertex."""
    draw = lambda salt, n: F.pmod(F.xxhash64(F.lit(seed), F.lit(salt), F.col("id")), F.lit(n))
    edges = spark.range(n_edges).select(draw(1, n_vertices).alias("src"), draw(2, n_vertices).alias("dst"), (1 + draw(3, max_weight)).alias("w"))
    vertices = spark.range(n_vertices).select(F.col("id").alias("vid"), F.lit("node").alias("kind"))
    postings = spark.range(n_vertices).select(F.concat(F.lit("l"), draw(4, labels).cast("string")).alias("kw"), F.col("id").alias("vid"))
    return Graph(vertices, merge_edges(edges), postings)


BUILDERS: dict[str, Callable[[SparkSession, str], Graph]] = {
    "g1": trade,
    "g1u": trade_unit,
    "g1r": trade_reversible,
    "g2": web,
    "g3": copurchase,
    "g4": journeys,
    "g5": vectors,
    "g6": texts,
    "g6c": dialogues,
}


def build_graph(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    return BUILDERS[name](spark, sf_dir)
