"""Exact top-k search as iterated relational joins, many queries at once.

Backward: labels spread along incoming edges in global distance steps. ``m`` is the
least pending distance of a keyword over the whole graph; labels up to it are final,
and a vertex without any label scores above the sum of all m. The wave of a query
ends when that sum exceeds the k-th best score S, or nothing is pending.

Forward: what remains are vertices with some labels whose optimistic score is at
most S. For each keyword they lack, or hold only provisionally, a demand with the
budget that S leaves walks along outgoing edges, largest budget first merged, and
ends at vertices whose label is final. Labels then flow back along demanded
vertices only, to a fixpoint. Only the k best rows and a row per keyword ever reach
the driver.
"""

from __future__ import annotations

import math
from collections.abc import Iterable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphkw.functions.packing import distance, leaf
from graphkw.operators import waves
from graphkw.operators.bounds import top_answers
from graphkw.schema import FAR, Graph, KeywordQuery, query_frame
from graphkw.storage import Bucketed, Snapshot

#: name: (stops the wave by the bound, uses sketch bounds). One global bound is known to all tasks after each round, so
#: bound exchange and preemption, which are about fragments that don't wait, exist in the fragment program only.
VARIANTS = {"exhaustive": (False, False), "backward_only": (False, False), "two_phase": (True, False), "sketch": (True, True)}
#: Least pending distances are taken while a round is written if there are no more of them than this, else by one more aggregate.
WATCHED = 64


@dataclass
class Result:
    """Answers (qid, rank, root, score), the labels behind them and what each round did."""

    answers: DataFrame
    labels: DataFrame
    query: DataFrame
    trace: list[dict] = field(default_factory=list)

    def wide(self, n: int) -> DataFrame:
        """qid, rank, root, score and the distance to each of the first ``n`` keywords."""
        d = self.labels.groupBy("qid", F.col("vid").alias("root")).pivot("kid", list(range(n))).agg(F.min(distance(F.col("p"))))
        d = d.select("qid", "root", *(F.col(str(i)).alias(f"d{i + 1}") for i in range(n)))
        return self.answers.join(d, ["qid", "root"]).select("qid", "rank", "root", "score", *(f"d{i + 1}" for i in range(n)))

    def maps(self) -> DataFrame:
        """Each answer with a map of keyword to nearest leaf and distance."""
        pair = F.struct("kw", F.struct(leaf(F.col("p")).alias("leaf"), distance(F.col("p")).alias("dist")))
        parts = self.labels.join(F.broadcast(self.query.select("qid", "kid", "kw")), ["qid", "kid"]).groupBy("qid", F.col("vid").alias("root")).agg(F.map_from_entries(F.sort_array(F.collect_list(pair))).alias("dists"))
        return self.answers.join(parts, ["qid", "root"]).select("qid", "rank", "root", "score", "dists")


class Search:
    """State of one batch of queries."""

    def __init__(self, graph: Graph, queries: Iterable[KeywordQuery], variant: str = "two_phase", delta: int = 1, index=None, limits: dict[int, float] | None = None):
        if variant not in VARIANTS:
            raise ValueError(f"no such variant: {variant}")
        self.queries = {q.qid: q for q in queries}
        self.graph, self.delta, self.index = graph, delta, index
        self.stops, self.bounds_known = VARIANTS[variant]
        self.variant = variant
        self.spark: SparkSession = graph.edges.sparkSession
        self.query = query_frame(self.spark, self.queries.values())
        self.score = dict.fromkeys(self.queries, math.inf) | (limits or {})
        self.trace: list[dict] = []
        self.held: Snapshot | None = None
        self.ks = {q.qid: q.k for q in self.queries.values()}
        self.tables: list = []
        self._edges: dict[str, DataFrame] = {}
        self._hubs: DataFrame | None = None

    # -- the graph, read once ---------------------------------------------------------

    def _held_edges(self, key: str) -> DataFrame:
        """The edges that can matter, dealt by ``key``: every round joins this table, none reads the sources again."""
        if key not in self._edges:
            longest = max(q.tau for q in self.queries.values())
            made = self._edges["dst"].select("src", "dst", "w") if self._edges else self.graph.edges.filter(F.col("w") <= longest)
            if key == "dst":
                plain = Bucketed(made, "dst")
                self.tables.append(plain)
                hub = Snapshot(waves.hubs(plain.df), [F.count("*").alias("n")])
                self.tables.append(hub)
                if hub.seen["n"]:
                    self._hubs = hub.df
                    split = Bucketed(waves.split_edges(plain.df, hub.df), "dst")
                    self.tables.append(split)
                    self._edges[key] = split.df
                else:
                    self._edges[key] = plain.df
            else:
                self.tables.append(Bucketed(made, key))
                self._edges[key] = self.tables[-1].df
        return self._edges[key]

    def _relax(self, front: DataFrame, bounded: bool) -> DataFrame:
        edges = self._held_edges("dst")
        if self._hubs is None:
            return waves.relax(front, edges, self._limits(bounded))
        return waves.relax_split(front, edges, self._hubs, self._limits(bounded))

    def close(self) -> None:
        """Deletes what the search has written, but for the labels that its answers read."""
        for t in self.tables:
            t.drop()
        self.tables, self._edges, self._hubs = [], {}, None

    # -- small tables -----------------------------------------------------------------

    def _limits(self, bounded: bool = True) -> DataFrame:
        rows = [(q.qid, int(min(q.tau, self.score[q.qid] if bounded else FAR))) for q in self.queries.values()]
        return self.spark.createDataFrame(rows, "qid int, cap long")

    def _watch(self) -> list:
        pairs = [(q.qid, kid) for q in self.queries.values() for kid in range(len(q.keywords))]
        if len(pairs) > WATCHED:
            return []
        open_ = F.col("done").isNull() | (F.col("p") < F.col("done"))
        return [F.min(F.when((F.col("qid") == qid) & (F.col("kid") == kid) & open_, distance(F.col("p")))).alias(f"m_{qid}_{kid}") for qid, kid in pairs]

    def _keep(self, df: DataFrame) -> DataFrame:
        old, self.held = self.held, Snapshot(df, self._watch())
        if old:
            old.drop()
        return self.held.df

    def _refresh(self, labels: DataFrame) -> None:
        """The k-th best score of each query so far (k rows per query reach the driver)."""
        complete = waves.matches(labels, self.query).filter("complete")
        for r in top_answers(complete, self.ks).groupBy("qid").agg(F.count("*").alias("n"), F.max("score").alias("s")).collect():
            if r["n"] == self.queries[r["qid"]].k:
                self.score[r["qid"]] = min(self.score[r["qid"]], r["s"])

    def _minima(self, labels: DataFrame) -> dict[int, dict[int, float]]:
        m = {q.qid: dict.fromkeys(range(len(q.keywords)), math.inf) for q in self.queries.values()}
        seen = self.held.seen
        if not seen:
            seen = {f"m_{r['qid']}_{r['kid']}": r["d"] for r in waves.pending(labels).groupBy("qid", "kid").agg(F.min(distance(F.col("p"))).alias("d")).collect()}
        for name, d in seen.items():
            if d is not None:
                qid, kid = name[2:].rsplit("_", 1)
                m[int(qid)][int(kid)] = d
        return m

    # -- phases -----------------------------------------------------------------------

    def backward(self) -> tuple[DataFrame, dict[int, dict[int, float]]]:
        bounded = self.variant != "exhaustive"
        labels = self._keep(waves.origins(self.graph.postings, self.query).withColumn("done", F.lit(None).cast("long")))
        live = set(self.queries)
        while True:
            m = self._minima(labels)
            if bounded:
                self._refresh(labels)
            for qid in sorted(live):
                least = min(m[qid].values())
                if least > self.queries[qid].tau or self.stops and sum(m[qid].values()) > self.score[qid] or bounded and least > self.score[qid]:
                    live.discard(qid)
            if not live:
                return labels, m
            ends = self.spark.createDataFrame([(q, int(min(m[q].values())) + self.delta) for q in sorted(live)], "qid int, upto long")
            front = waves.pending(labels).join(F.broadcast(ends), "qid").filter(distance(F.col("p")) < F.col("upto")).select(*waves.KEY, "p")
            labels = self._keep(waves.merge(labels, front, self._relax(front, bounded)))
            self.trace.append({"phase": "backward", "live": len(live), "bounds": dict(self.score), "minima": m})

    def _demands(self, labels: DataFrame, m: dict[int, dict[int, float]]) -> DataFrame:
        """First demands: of every vertex with a label that may still be among the answers."""
        rows = [(q.qid, kid, q.tau, int(min(FAR, self.score[q.qid])), int(min(FAR, m[q.qid][kid]))) for q in self.queries.values() for kid in range(len(q.keywords))]
        asked = self.spark.createDataFrame(rows, "qid int, kid int, tau long, s long, m long")
        roots = labels.select("qid", "vid").distinct()
        grid = roots.join(F.broadcast(asked), "qid").join(labels.select(*waves.KEY, distance(F.col("p")).alias("d")), waves.KEY, "left")
        grid = grid.withColumn("lb", F.least(F.coalesce("d", F.lit(FAR)), "m"))
        if self.bounds_known and self.index is not None:
            grid = self.index.raise_bounds(grid, self.query)
        total = grid.groupBy("qid", "vid").agg(F.sum("lb").alias("total"))
        open_ = grid.join(total, ["qid", "vid"]).filter("total <= s AND lb <= tau AND (d IS NULL OR d > m)")
        budget = F.least("tau", F.coalesce("d", F.lit(FAR)), F.col("s") - (F.col("total") - F.col("lb")))
        return open_.select(*waves.KEY, budget.alias("budget")).filter("budget >= 0")

    def forward(self, labels: DataFrame, m: dict[int, dict[int, float]]) -> DataFrame:
        finals = self.spark.createDataFrame([(q, kid, int(min(FAR, d))) for q, by in m.items() for kid, d in by.items()], "qid int, kid int, m long")
        unserved = F.col("done").isNull() | (F.col("budget") > F.col("done"))
        watch = [F.count_if(unserved).alias("open"), F.count("*").alias("n")]
        demands = Snapshot(self._demands(labels, m).withColumn("done", F.lit(None).cast("long")), watch)
        final = labels.join(F.broadcast(finals), ["qid", "kid"]).filter(distance(F.col("p")) <= F.col("m")).select(*waves.KEY)
        n_roots = demands.seen["n"]
        while demands.seen["open"]:
            open_ = demands.df.filter(unserved)
            front = open_.join(final, waves.KEY, "left_anti").select(*waves.KEY, "budget")
            after = Snapshot(waves.merge_demands(demands.df, open_, waves.walk_demands(front, self._held_edges("src"))), watch)
            demands.drop()
            demands = after
            self.trace.append({"phase": "demand", "bounds": dict(self.score)})
        if not n_roots:
            return labels
        # Labels flow back over demanded vertices only.
        asked = demands.df.select(*waves.KEY)
        pending = F.col("done").isNull() | (F.col("p") < F.col("done"))
        watch = [F.count_if(pending).alias("open")]
        sources = labels.join(asked, waves.KEY, "left_semi").select(*waves.KEY, "p", F.lit(None).cast("long").alias("done"))
        back = Snapshot(sources, watch)
        while back.seen["open"]:
            front = waves.pending(back.df).select(*waves.KEY, "p")
            found = self._relax(front, False).join(asked, waves.KEY, "left_semi")
            after = Snapshot(waves.merge(back.df, front, found), watch)
            back.drop()
            back = after
            self.trace.append({"phase": "answer", "bounds": dict(self.score)})
        known = labels.join(asked, waves.KEY, "left_anti").select(*waves.KEY, "p")
        out = self._keep(known.unionByName(back.df.select(*waves.KEY, "p")).withColumn("done", F.lit(None).cast("long")))
        back.drop()
        demands.drop()
        return out

    def run(self) -> Result:
        if self.bounds_known and self.index is not None:
            self.score |= {q: min(s, self.score[q]) for q, s in self.index.seed_bounds(self.graph, self.query, self.queries).items()}
        labels, m = self.backward()
        if self.stops:
            labels = self.forward(labels, m)
        self.close()
        complete = waves.matches(labels, self.query).filter("complete")
        return Result(top_answers(complete, self.ks), labels, self.query, self.trace)


def search(graph: Graph, query: KeywordQuery, variant: str = "two_phase", **options) -> Result:
    return Search(graph, [query], variant, **options).run()


def search_batch(graph: Graph, queries: Iterable[KeywordQuery], variant: str = "two_phase", **options) -> Result:
    return Search(graph, queries, variant, **options).run()


def keyword_distances(graph: Graph, query: KeywordQuery) -> DataFrame:
    """(kw, vid, d) within tau, without any bound."""
    wave = Search(graph, [query], "exhaustive")
    labels, _ = wave.backward()
    wave.close()
    q = query_frame(graph.edges.sparkSession, [query])
    return labels.join(F.broadcast(q.select("qid", "kid", "kw")), ["qid", "kid"]).select("kw", "vid", distance(F.col("p")).alias("d"))
