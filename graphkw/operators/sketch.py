"""PageRank order, all-distances sketches, exact landmarks and the bounds they give."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from graphkw.operators.reach import spread
from graphkw.schema import FAR, Graph
from graphkw.storage import Snapshot


def pagerank(graph: Graph, damping: float = 0.85, iterations: int = 20) -> DataFrame:
    """(vid, pr); vertices without outgoing edges share their rank evenly."""
    edges = graph.edges.select("src", "dst")
    vertices = edges.select(F.col("src").alias("vid")).unionByName(edges.select(F.col("dst").alias("vid"))).distinct()
    degree = edges.groupBy("src").agg(F.count("*").alias("degree"))
    base = Snapshot(vertices.join(degree, vertices["vid"] == degree["src"], "left").select("vid", "degree")).df
    n = base.count()
    held = Snapshot(base.select("vid", "degree", F.lit(1.0 / max(1, n)).alias("pr")))
    for _ in range(iterations):
        now = held.df
        loose = now.filter("degree IS NULL").agg(F.coalesce(F.sum("pr"), F.lit(0.0)).alias("loose"))
        given = now.join(edges, F.col("vid") == F.col("src")).groupBy("dst").agg(F.sum(F.col("pr") / F.col("degree")).alias("got"))
        after = base.join(given, F.col("vid") == F.col("dst"), "left").crossJoin(F.broadcast(loose))
        fresh = Snapshot(after.select("vid", "degree", ((1 - damping) / n + damping * (F.coalesce("got", F.lit(0.0)) + F.col("loose") / n)).alias("pr")))
        held.drop()
        held = fresh
    return held.df.select("vid", "pr")


def ranks(pr: DataFrame) -> DataFrame:
    """(vid, crank): a sortable rank, the best first; ties by vid."""
    return pr.select("vid", F.struct((-F.round("pr", 9)).alias("p"), F.col("vid").alias("v")).alias("crank"))


def build_sketch(graph: Graph, pr: DataFrame, radius: int, out: bool = True, kappa: int = 1) -> DataFrame:
    """(vid, centre, d): for each vertex the centres that no nearer centre of better rank hides (``kappa`` may).

    ``out``: distances from the vertex to the centre; else from the centre to the vertex. An entry that is hidden
    at a vertex is hidden at all vertices beyond, so rounds only pass on what survives.
    """
    far, near = ("src", "dst") if out else ("dst", "src")
    steps = graph.edges.select(F.col(near).alias("at"), F.col(far).alias("to"), "w")
    order = ranks(pr)
    held = Snapshot(order.select("vid", F.col("vid").alias("centre"), F.lit(0).cast("long").alias("d"), "crank", F.lit(True).alias("fresh")))
    before = Window.partitionBy("vid").orderBy("d", "crank").rowsBetween(Window.unboundedPreceding, -1)
    while not held.df.filter("fresh").isEmpty():
        front = held.df.filter("fresh")
        found = front.join(steps, front["vid"] == steps["at"]).select(F.col("to").alias("vid"), "centre", (F.col("d") + F.col("w")).alias("d"), "crank").filter(F.col("d") <= radius)
        old = held.df.select("vid", "centre", "d", "crank", F.col("d").alias("was"))
        merged = old.unionByName(found.withColumn("was", F.lit(None).cast("long"))).groupBy("vid", "centre", "crank").agg(F.min("d").alias("d"), F.min("was").alias("was"))
        if kappa == 1:
            hidden = F.min("crank").over(before) < F.col("crank")
        else:
            hidden = F.size(F.filter(F.collect_list("crank").over(before), lambda c: c < F.col("crank"))) >= kappa
        kept = merged.withColumn("hidden", F.coalesce(hidden, F.lit(False))).filter("NOT hidden")
        after = Snapshot(kept.select("vid", "centre", "d", "crank", (F.col("was").isNull() | (F.col("d") < F.col("was"))).alias("fresh")))
        held.drop()
        held = after
    return held.df.select("vid", "centre", "d")


def top_centres(pr: DataFrame, count: int) -> DataFrame:
    return pr.orderBy(F.desc(F.round("pr", 9)), "vid").limit(count).select(F.col("vid").alias("key"), "vid")


def landmark_side(graph: Graph, centres: DataFrame, radius: int, out: bool = True) -> DataFrame:
    """(vid, centre, d): exact distances to each centre, or from each centre; farther than ``radius`` is unknown."""
    return spread(graph.edges, centres, radius, backwards=out).select("vid", F.col("key").alias("centre"), "d")


def landmarks(graph: Graph, centres: DataFrame, radius: int) -> tuple[DataFrame, DataFrame]:
    """Exact distances to each centre and from each centre."""
    return landmark_side(graph, centres, radius), landmark_side(graph, centres, radius, out=False)


def keyword_sketch(sketch: DataFrame, postings: DataFrame) -> DataFrame:
    """The holders' entries merged: (kw, centre, d_min, d_max, holders)."""
    return sketch.join(postings, "vid").groupBy("kw", "centre").agg(F.min("d").alias("d_min"), F.max("d").alias("d_max"), F.count("*").alias("holders"))


def upper_bound(out: DataFrame, kw_in: DataFrame) -> DataFrame:
    """(vid, kw, ub): over common centres the least way by one; always a real path's length."""
    return out.join(kw_in, "centre").groupBy("vid", "kw").agg(F.min(F.col("d") + F.col("d_min")).alias("ub"))


def lower_bound_out(out: DataFrame, kw_out: DataFrame, postings: DataFrame) -> DataFrame:
    """First form: distance to a centre less that of the farthest holder; only centres that every holder reaches."""
    total = postings.groupBy("kw").agg(F.count("*").alias("total"))
    usable = kw_out.join(total, "kw").filter("holders = total").select("kw", "centre", "d_max")
    return out.join(usable, "centre").groupBy("vid", "kw").agg(F.max(F.col("d") - F.col("d_max")).alias("lb"))


def lower_bound_in(inward: DataFrame, kw_in: DataFrame) -> DataFrame:
    """Second form: distance from a centre to the keyword less that to the vertex; both must be exact."""
    return inward.join(kw_in, "centre").groupBy("vid", "kw").agg(F.max(F.col("d_min") - F.col("d")).alias("lb"))


def lower_bound_as_printed(out: DataFrame, kw_out: DataFrame, least: bool = True) -> DataFrame:
    """The published form, with the nearest holder: not a bound in general; kept to measure how often it fails."""
    d = F.col("d") - F.col("d_min")
    return out.join(kw_out, "centre").groupBy("vid", "kw").agg((F.min(d) if least else F.max(d)).alias("lb"))


@dataclass
class Index:
    """Landmark distances and keyword sketches, used to seed and to prune."""

    out: DataFrame
    inward: DataFrame
    kw_out: DataFrame
    kw_in: DataFrame
    postings: DataFrame
    form: str = "both"

    @classmethod
    def build(cls, graph: Graph, count: int = 16, radius: int = 12, form: str = "both", iterations: int = 10) -> Index:
        out, inward = landmarks(graph, top_centres(pagerank(graph, iterations=iterations), count), radius)
        keep = lambda df: Snapshot(df).df
        return cls(out, inward, keep(keyword_sketch(out, graph.postings)), keep(keyword_sketch(inward, graph.postings)), graph.postings, form)

    def save(self, path: str) -> None:
        for name in ("out", "inward", "kw_out", "kw_in", "postings"):
            getattr(self, name).write.mode("overwrite").parquet(f"{path}/{name}")

    @classmethod
    def load(cls, spark, path: str, form: str = "both") -> Index:
        return cls(*(spark.read.parquet(f"{path}/{n}") for n in ("out", "inward", "kw_out", "kw_in", "postings")), form)

    def _asked(self, table: DataFrame, query: DataFrame) -> DataFrame:
        return table.join(F.broadcast(query.select("kw").distinct()), "kw", "left_semi")

    def lower_bounds(self, query: DataFrame) -> DataFrame:
        parts = []
        if self.form in ("lb1", "both"):
            parts.append(lower_bound_out(self.out, self._asked(self.kw_out, query), self._asked(self.postings, query)))
        if self.form in ("lb2", "both"):
            parts.append(lower_bound_in(self.inward, self._asked(self.kw_in, query)))
        if self.form == "as_printed":
            parts.append(lower_bound_as_printed(self.out, self._asked(self.kw_out, query)))
        rows = parts[0]
        for p in parts[1:]:
            rows = rows.unionByName(p)
        return rows.groupBy("vid", "kw").agg(F.max("lb").alias("lb"))

    def raise_bounds(self, grid: DataFrame, query: DataFrame) -> DataFrame:
        """``grid`` (qid, vid, kid, d, lb, ...) with lb raised for labels that aren't final."""
        bounds = self.lower_bounds(query).join(F.broadcast(query.select("qid", "kid", "kw")), "kw").select("qid", "kid", "vid", F.col("lb").alias("known"))
        raised = F.when(F.col("d").isNull() | (F.col("d") > F.col("m")), F.greatest("lb", F.coalesce("known", F.lit(0)))).otherwise(F.col("lb"))
        return grid.join(bounds, ["qid", "kid", "vid"], "left").withColumn("lb", raised).drop("known")

    def seed_bounds(self, graph: Graph, query: DataFrame, queries: dict) -> dict[int, float]:
        """Scores of k distinct roots by upper bounds, each within tau: S before the search begins."""
        ub = upper_bound(self.out, self._asked(self.kw_in, query)).join(F.broadcast(query), "kw").filter("ub <= tau")
        scored = ub.groupBy("qid", "vid", "k", "n").agg(F.count("*").alias("found"), F.sum("ub").alias("score")).filter("found = n")
        rank = F.row_number().over(Window.partitionBy("qid").orderBy("score", "vid"))
        rows = scored.withColumn("r", rank).filter("r <= k").groupBy("qid").agg(F.count("*").alias("n"), F.max("score").alias("s")).collect()
        return {r["qid"]: r["s"] if r["n"] == queries[r["qid"]].k else math.inf for r in rows}


__all__ = ["FAR", "Index", "build_sketch", "keyword_sketch", "landmark_side", "landmarks", "lower_bound_as_printed", "lower_bound_in", "lower_bound_out", "pagerank", "ranks", "top_centres", "upper_bound"]
