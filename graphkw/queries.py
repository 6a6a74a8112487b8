"""Registered queries of the search engine and the SQL that checks them."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphkw.functions.packing import distance
from graphkw.functions.workload import draw_keywords, generate
from graphkw.operators import bounds, partition, sketch, tree, waves
from graphkw.operators.reach import spread
from graphkw.plans.baseline import all_pairs, sequential_answers
from graphkw.plans.experiments import trajectory
from graphkw.plans.program import run_program
from graphkw.plans.search import Search, keyword_distances, search, search_batch
from graphkw.schema import Graph, KeywordQuery, query_frame
from graphkw.sources.tables import build_graph
from graphkw.sources.tables_sql import EDGES, POSTINGS, graph_ctes
from graphkw.storage import Snapshot

Q2, Q4 = ("household", "widget"), ("household", "brand#17", "nation_3", "promo")
Q6 = ("asia", "brand#17", "gizmo", "1-urgent", "furniture", "europe")
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def _add(name: str, run: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    QUERIES[name] = run
    if sql:
        SQL[name] = sql


# -- SQL forms ---------------------------------------------------------------------------


def _list(keywords) -> str:
    return ", ".join(f"({i}, '{w}')" for i, w in enumerate(keywords))


def _walk(graph: str, keywords, tau: int, edges: str = "edges", directed: bool = True) -> str:
    """CTEs q, edges, postings and dist(kid, vid, d): least distances within tau."""
    ctes = graph_ctes(graph).replace("edges AS (", "edges0 AS MATERIALIZED (", 1).replace("postings AS (", "postings AS MATERIALIZED (", 1)
    both = "SELECT * FROM edges0" if directed else "SELECT src, dst, min(w) AS w FROM (SELECT * FROM edges0 UNION ALL SELECT dst, src, w FROM edges0) GROUP BY src, dst"
    return f"""WITH RECURSIVE q(kid, kw) AS (VALUES {_list(keywords)}), {ctes}, edges AS MATERIALIZED ({both}),
walk(kid, vid, d) AS (
  SELECT q.kid, p.vid, CAST(0 AS BIGINT) FROM postings p JOIN q ON p.kw = q.kw
  UNION SELECT w.kid, e.src, w.d + e.w FROM walk w JOIN {edges} e ON e.dst = w.vid WHERE w.d + e.w <= {tau}),
dist AS (SELECT kid, vid, min(d) AS d FROM walk GROUP BY kid, vid),
complete AS (SELECT vid AS root, CAST(sum(d) AS BIGINT) AS score FROM dist GROUP BY vid HAVING count(*) = {len(keywords)})"""


def topk_sql(graph: str, keywords, tau: int, k: int, directed: bool = True, roots: str = "complete", qid: int = 0) -> str:
    wide = ", ".join(f"max(CASE WHEN kid = {i} THEN d END) AS d{i + 1}" for i in range(len(keywords)))
    return f"""{_walk(graph, keywords, tau, directed=directed)},
best AS (SELECT root, score, row_number() OVER (ORDER BY score, root) AS rank FROM {roots}),
wide AS (SELECT vid, {wide} FROM dist GROUP BY vid)
SELECT CAST({qid} AS INTEGER) AS qid, CAST(rank AS INTEGER) AS rank, root, score, {", ".join(f"d{i + 1}" for i in range(len(keywords)))}
FROM best JOIN wide ON vid = root WHERE rank <= {k}"""


# -- graphs --------------------------------------------------------------------------------

for _g in ("g1", "g1u", "g1r", "g2", "g3", "g4", "g6", "g6c"):
    _add(f"{_g}_edges", lambda s, d, g=_g: build_graph(s, d, g).edges, f"SELECT * FROM ({EDGES[_g]})")
    _add(f"{_g}_postings", lambda s, d, g=_g: build_graph(s, d, g).postings, f"SELECT * FROM ({POSTINGS[_g]})")
_add("g5_edges", lambda s, d: build_graph(s, d, "g5").edges)
_add(
    "g1_vertices",
    lambda s, d: build_graph(s, d, "g1").vertices,
    "SELECT CAST(tag * 1000000000000 + key AS BIGINT) AS vid, kind FROM (SELECT 1 AS tag, r_regionkey AS key, 'region' AS kind FROM region UNION ALL SELECT 2, n_nationkey, 'nation' FROM nation UNION ALL SELECT 3, c_custkey, 'customer' FROM customer"
    " UNION ALL SELECT 4, s_suppkey, 'supplier' FROM supplier UNION ALL SELECT 5, p_partkey, 'part' FROM part UNION ALL SELECT 6, o_orderkey, 'orders' FROM orders)",
)
_add(
    "g1_degree",
    lambda s, d: build_graph(s, d, "g1").edges.groupBy(F.col("dst").alias("vid")).agg(F.count("*").alias("n_in"), F.sum("w").alias("w_in")),
    f"WITH {graph_ctes('g1')} SELECT dst AS vid, count(*) AS n_in, CAST(sum(w) AS BIGINT) AS w_in FROM edges GROUP BY dst",
)
_add("g1_kw_freq", lambda s, d: build_graph(s, d, "g1").postings.groupBy("kw").agg(F.count("*").alias("holders")), f"WITH {graph_ctes('g1')} SELECT kw, count(*) AS holders FROM postings GROUP BY kw")

# -- search --------------------------------------------------------------------------------


def _topk(graph: str, keywords, tau: int = 3, k: int = 10, variant: str = "two_phase", directed: bool = True):
    def run(s: SparkSession, d: str) -> DataFrame:
        g = build_graph(s, d, graph)
        g = g if directed else g.undirected()
        options = {"index": sketch.Index.build(g, 4, 2 * tau, iterations=3)} if variant == "sketch" else {}
        return search(g, KeywordQuery(keywords, tau, k), variant, **options).wide(len(keywords))

    return run, topk_sql(graph, keywords, tau, k, directed)


for _n, _words in ((2, Q2), (3, Q4[:3]), (4, Q4), (5, Q6[:5]), (6, Q6)):
    _add(f"kw_topk_q{_n}", *_topk("g1", _words, 6 if _n > 4 else 3))
for _t in (3, 4, 5, 6):
    _add(f"kw_topk_tau{_t}", *_topk("g1u", Q4, _t))
for _k in (5, 10, 15, 20, 25, 30):
    _add(f"kw_topk_k{_k}", *_topk("g1", Q2, 3, _k))
for _v in ("two_phase", "sketch", "exhaustive", "backward_only"):
    _add(f"kw_topk_{_v}", *_topk("g1", Q4, 3, 10, _v))
_add("kw_topk_weighted", *_topk("g1r", Q4, 6))
_add("kw_topk_copurchase", *_topk("g3", ("household", "nation_3", "1-urgent"), 6))
_add("kw_topk_web", *_topk("g2", ("de", "en"), 3))
_add("kw_topk_conversation", *_topk("g6c", ("user", "assistant"), 3))
_add("kw_topk_journeys", *_topk("g4", ("purchase", "error"), 6))
_add("kw_topk_texts", *_topk("g6", ("quality_0", "quality_1", "src1"), 3))
_add("kw_undirected", *_topk("g1", ("asia", "widget"), 3, directed=False))


def _program(variant: str):
    def run(s: SparkSession, d: str) -> DataFrame:
        g, q = partition.hold(build_graph(s, d, "g1"), 4), KeywordQuery(Q4, 3, 10)
        index = sketch.Index.build(g, 4, 6, iterations=3) if variant not in ("exhaustive", "two_phase") else None
        return run_program(g, q, variant, m=4, index=index).frame(s)

    return run, f"SELECT qid, rank, root, score FROM ({topk_sql('g1', Q4, 3, 10)})"


for _v in ("exhaustive", "two_phase", "sketch", "exchange", "preemptive", "single_task"):
    _add(f"frag_topk_{_v}", *_program(_v))
_add("kw_topk_sequential", lambda s, d: sequential_answers(build_graph(s, d, "g1"), KeywordQuery(Q4, 3, 10)), f"SELECT qid, rank, root, score FROM ({topk_sql('g1', Q4, 3, 10)})")
_add(
    "kw_all_pairs",
    lambda s, d: all_pairs(build_graph(s, d, "g6c"), 6),
    f"WITH RECURSIVE {graph_ctes('g6c')}, w(dst, src, d) AS (SELECT DISTINCT dst, dst, CAST(0 AS BIGINT) FROM edges UNION SELECT w.dst, e.src, w.d + e.w FROM w JOIN edges e ON e.dst = w.src WHERE w.d + e.w <= 6) SELECT src, dst, min(d) AS d FROM w GROUP BY src, dst",
)
_add("kw_origins", lambda s, d: build_graph(s, d, "g1").postings.filter(F.col("kw").isin(*Q4)), f"WITH {graph_ctes('g1')} SELECT kw, vid FROM postings WHERE kw IN {Q4}")
_add("kw_distances", lambda s, d: keyword_distances(build_graph(s, d, "g1"), KeywordQuery(Q4, 3)), f"{_walk('g1', Q4, 3)} SELECT kw, vid, d FROM dist JOIN q USING (kid)")


def _labels(s: SparkSession, d: str, graph: str = "g1", keywords=Q4, tau: int = 3) -> tuple[DataFrame, DataFrame]:
    wave = Search(build_graph(s, d, graph), [KeywordQuery(keywords, tau)], "exhaustive")
    labels, _ = wave.backward()
    wave.close()
    return labels, query_frame(s, [KeywordQuery(keywords, tau)])


def _split(complete: bool):
    def run(s: SparkSession, d: str) -> DataFrame:
        m = waves.matches(*_labels(s, d))
        return m.filter(F.col("complete") == complete).select("vid", "found", "score")

    sql = f"{_walk('g1', Q4, 3)} SELECT vid, count(*) AS found, CAST(sum(d) AS BIGINT) AS score FROM dist GROUP BY vid HAVING count(*) {'=' if complete else '<'} 4"
    return run, sql


_add("kw_complete_matches", *_split(True))
_add("kw_partial_matches", *_split(False))
_add(
    "kw_visited_sets",
    lambda s, d: waves.visited_sets(*_labels(s, d)),
    f"{_walk('g1', Q4, 3)}, m AS (SELECT vid, count(*) AS c FROM dist GROUP BY vid) SELECT CAST(0 AS INTEGER) AS qid, count(*) AS n_union, count(*) FILTER (c = 4) AS n_all, count(*) FILTER (c < 4) AS n_some FROM m",
)


def _root_filter(s: SparkSession, d: str) -> DataFrame:
    g, q = build_graph(s, d, "g1r"), KeywordQuery(Q2, 3, 10)
    labels, query = _labels(s, d, "g1r", Q2)
    complete = tree.with_root_kind(waves.matches(labels, query).filter("complete"), g, "customer")
    return bounds.top_answers(complete, {q.qid: q.k})


_add(
    "kw_root_filter",
    _root_filter,
    f"{_walk('g1r', Q2, 3)} SELECT CAST(0 AS INTEGER) AS qid, CAST(row_number() OVER (ORDER BY score, root) AS INTEGER) AS rank, root, score FROM complete WHERE root // 1000000000000 = 3 ORDER BY rank LIMIT 10",
)


def _prefix(s: SparkSession, d: str) -> DataFrame:
    g = build_graph(s, d, "g1")
    g = type(g)(g.vertices, g.edges, tree.expand_prefix(g, "brand#1", "brands"))
    return search(g, KeywordQuery(("household", "brands"), 3)).wide(2)


_add(
    "kw_prefix_expand",
    _prefix,
    topk_sql("g1", ("household", "brands"), 3, 10).replace("postings AS MATERIALIZED (", "postings AS MATERIALIZED (SELECT DISTINCT 'brands' AS kw, vid FROM (" + POSTINGS["g1"] + ") WHERE starts_with(kw, 'brand#1') UNION ALL ", 1),
)


def _tree(s: SparkSession, d: str) -> DataFrame:
    g = build_graph(s, d, "g1")
    r = search(g, KeywordQuery(Q4, 3, 10))
    return tree.match_tree(g, r.answers, r.labels, r.query, 3)


def _steiner(s: SparkSession, d: str) -> DataFrame:
    g = build_graph(s, d, "g1")
    r = search(g, KeywordQuery(Q4, 3, 10))
    return tree.steiner_weight(tree.match_tree(g, r.answers, r.labels, r.query, 3), r.answers)


_TREE = f"""{_walk('g1', Q4, 3)},
lw(kid, vid, leaf, d) AS (
  SELECT q.kid, p.vid, p.vid, CAST(0 AS BIGINT) FROM postings p JOIN q ON p.kw = q.kw
  UNION SELECT w.kid, e.src, w.leaf, w.d + e.w FROM lw w JOIN edges e ON e.dst = w.vid WHERE w.d + e.w <= 3),
near AS (SELECT kid, vid, d, min(leaf) AS leaf FROM lw JOIN dist USING (kid, vid, d) GROUP BY kid, vid, d),
best AS (SELECT root, score FROM complete ORDER BY score, root LIMIT 10),
step AS (SELECT a.kid, a.vid, a.leaf, min({{'dst': b.vid, 'w': e.w}}) AS e FROM near a JOIN edges e ON e.src = a.vid JOIN near b ON b.kid = a.kid AND b.vid = e.dst AND b.d = a.d - e.w AND b.leaf = a.leaf WHERE a.d > 0 GROUP BY a.kid, a.vid, a.leaf),
path(kid, root, pos, src, dst, w) AS (
  SELECT s.kid, b.root, 0, s.vid, s.e.dst, s.e.w FROM best b JOIN step s ON s.vid = b.root
  UNION ALL SELECT s.kid, p.root, p.pos + 1, s.vid, s.e.dst, s.e.w FROM path p JOIN step s ON s.kid = p.kid AND s.vid = p.dst)"""
_add("kw_match_tree", _tree, f"{_TREE} SELECT CAST(0 AS INTEGER) AS qid, root, kw, CAST(pos AS INTEGER) AS pos, src, dst, w FROM path JOIN q USING (kid)")
_add(
    "kw_steiner_approx",
    _steiner,
    f"{_TREE}, once AS (SELECT root, CAST(sum(w) AS BIGINT) AS weight FROM (SELECT DISTINCT root, src, dst, w FROM path) GROUP BY root) SELECT CAST(0 AS INTEGER) AS qid, root, score, coalesce(weight, 0) AS weight FROM best LEFT JOIN once USING (root)",
)
_add("query_workload_gen", lambda s, d: draw_keywords(build_graph(s, d, "g1"), 20, 4), f"WITH {graph_ctes('g1')}, p AS (SELECT DISTINCT kw FROM postings) SELECT CAST(qid AS INTEGER) AS qid, CAST(n - 1 AS INTEGER) AS kid, kw FROM (SELECT qid, kw, row_number() OVER (PARTITION BY qid ORDER BY md5('rks' || qid || '|' || kw), kw) AS n FROM p, range(20) t(qid)) WHERE n <= 4")


def _batch(s: SparkSession, d: str) -> DataFrame:
    g = build_graph(s, d, "g1u")
    return search_batch(g, generate(g, 10, 3, 3, 5)).answers


_add(
    "kw_batch",
    _batch,
    f"""WITH RECURSIVE {graph_ctes('g1u').replace('edges AS (', 'edges AS MATERIALIZED (', 1).replace('postings AS (', 'postings AS MATERIALIZED (', 1)}, p AS (SELECT DISTINCT kw FROM postings),
q AS MATERIALIZED (SELECT qid, n - 1 AS kid, kw FROM (SELECT qid, kw, row_number() OVER (PARTITION BY qid ORDER BY md5('rks' || qid || '|' || kw), kw) AS n FROM p, range(10) t(qid)) WHERE n <= 3),
walk(qid, kid, vid, d) AS (SELECT qid, kid, vid, CAST(0 AS BIGINT) FROM postings JOIN q USING (kw) UNION SELECT qid, kid, src, d + e.w FROM walk JOIN edges e ON dst = vid WHERE d + e.w <= 3),
dist AS (SELECT qid, kid, vid, min(d) AS d FROM walk GROUP BY ALL),
done AS (SELECT qid, vid AS root, CAST(sum(d) AS BIGINT) AS score FROM dist GROUP BY qid, vid HAVING count(*) = 3)
SELECT CAST(qid AS INTEGER) AS qid, CAST(rank AS INTEGER) AS rank, root, score FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY score, root) AS rank FROM done) WHERE rank <= 5""",
)

# -- fragments -----------------------------------------------------------------------------

_FRAG = "(7 * ({0} // 1000000000000) + {0} % 1000000000000) % 4"
_FRAMED = f"{graph_ctes('g1').replace('edges AS (', 'edges AS MATERIALIZED (', 1)}, framed AS (SELECT *, CAST({_FRAG.format('src')} AS INTEGER) AS src_frag, CAST({_FRAG.format('dst')} AS INTEGER) AS dst_frag FROM edges)"


def _framed(s: SparkSession, d: str):
    return partition.partition(build_graph(s, d, "g1"), 4)


_add("frag_hash", lambda s, d: _framed(s, d).frags, f"WITH {_FRAMED}, v AS (SELECT src AS vid FROM edges UNION SELECT dst FROM edges UNION SELECT vid FROM postings) SELECT vid, CAST({_FRAG.format('vid')} AS INTEGER) AS frag FROM v")
_add("frag_border_in", lambda s, d: partition.borders(_framed(s, d))[0], f"WITH {_FRAMED} SELECT DISTINCT dst_frag AS frag, dst AS vid FROM framed WHERE src_frag <> dst_frag")
_add("frag_border_out", lambda s, d: partition.borders(_framed(s, d))[1], f"WITH {_FRAMED} SELECT DISTINCT src_frag AS frag, dst AS vid FROM framed WHERE src_frag <> dst_frag")
_add(
    "frag_edge_cut",
    lambda s, d: partition.framed_edges(_framed(s, d)).groupBy("src_frag", "dst_frag").agg(F.count("*").alias("n")),
    f"WITH {_FRAMED} SELECT src_frag, dst_frag, count(*) AS n FROM framed GROUP BY ALL",
)
for _how in ("balanced_lp", "greedy_stream", "range"):
    _add(f"frag_measures_{_how}", lambda s, d, h=_how: partition.measures(partition.partition(build_graph(s, d, "g2"), 4, h)))
_add(
    "frag_measures_by_kind",
    lambda s, d: partition.measures(partition.partition(build_graph(s, d, "g2"), 4, "by_kind")),
    f"WITH {graph_ctes('g2').replace('edges AS (', 'edges AS MATERIALIZED (', 1)}, v AS (SELECT src AS vid FROM edges UNION SELECT dst FROM edges UNION SELECT vid FROM postings),"
    " cut AS (SELECT src // 1000000000000 % 4 AS frag, count(*) AS n_edges, count(*) FILTER (src // 1000000000000 % 4 <> dst // 1000000000000 % 4) AS n_cross FROM edges GROUP BY 1),"
    " own AS (SELECT vid // 1000000000000 % 4 AS frag, count(*) AS n_vertices FROM v GROUP BY 1)"
    " SELECT CAST(frag AS INTEGER) AS frag, n_vertices, coalesce(n_edges, 0) AS n_edges, coalesce(n_cross, 0) AS n_cross FROM own LEFT JOIN cut USING (frag)",
)


def _local(s: SparkSession, d: str, keywords=Q2, tau: int = 6) -> tuple[DataFrame, DataFrame]:
    """Labels by edges inside fragments only, and the edges with fragments."""
    g = _framed(s, d)
    framed = Snapshot(partition.framed_edges(g)).df
    ids = {w: i for i, w in enumerate(keywords)}
    kid = F.create_map(*(x for w, i in ids.items() for x in (F.lit(w), F.lit(i).cast("long"))))
    seeds = g.postings.filter(F.col("kw").isin(*keywords)).select(kid[F.col("kw")].alias("key"), "vid")
    return spread(framed.filter("src_frag = dst_frag").select("src", "dst", "w"), seeds, tau), framed


_LOCAL = f"""{_walk('g1', Q2, 6, edges="(SELECT * FROM edges WHERE " + _FRAG.format("src") + " = " + _FRAG.format("dst") + ")")},
lists AS (SELECT CAST({_FRAG.format('root')} AS INTEGER) AS frag, root, score, row_number() OVER (PARTITION BY {_FRAG.format('root')} ORDER BY score, root) AS rank FROM complete)"""


def _local_lists(s: SparkSession, d: str) -> DataFrame:
    labels, _ = _local(s, d)
    complete = labels.groupBy("vid").agg(F.count("*").alias("n"), F.sum("d").alias("score")).filter("n = 2")
    from pyspark.sql.window import Window

    frag = partition.hash_frag(F.col("vid"), 4)
    rank = F.row_number().over(Window.partitionBy("frag").orderBy("score", "root"))
    return complete.select(frag.alias("frag"), F.col("vid").alias("root"), "score").withColumn("rank", rank).filter("rank <= 10").select("frag", F.col("rank").cast("int").alias("rank"), "root", "score")


_add("frag_local_topk", _local_lists, f"{_LOCAL} SELECT frag, CAST(rank AS INTEGER) AS rank, root, score FROM lists WHERE rank <= 10")
_add("frag_assemble", lambda s, d: _local_lists(s, d).orderBy("score", "root").limit(10).select("root", "score"), f"{_LOCAL} SELECT root, score FROM lists WHERE rank <= 10 ORDER BY score, root LIMIT 10")
_add(
    "frag_bounds_min",
    lambda s, d: _local_lists(s, d).groupBy("frag").agg(F.when(F.count("*") == 10, F.max("score")).alias("s_local")),
    f"{_LOCAL} SELECT frag, CASE WHEN count(*) = 10 THEN max(score) END AS s_local FROM lists WHERE rank <= 10 GROUP BY frag",
)
_add("frag_bounds_union", lambda s, d: _local_lists(s, d).orderBy("score", "root").limit(10).agg(F.max("score").alias("s_union")), f"{_LOCAL} SELECT max(score) AS s_union FROM (SELECT score FROM lists WHERE rank <= 10 ORDER BY score, root LIMIT 10)")


def _messages(local: tuple[DataFrame, DataFrame]) -> DataFrame:
    labels, framed = local
    cross = framed.filter("src_frag <> dst_frag").select(F.col("dst").alias("vid"), F.col("dst_frag").alias("from_frag"), F.col("src_frag").alias("to_frag")).distinct()
    return labels.join(cross, "vid").select("from_frag", "to_frag", "vid", F.col("key").cast("int").alias("kid"), "d")


_MESSAGES = f"{_LOCAL}, framed AS (SELECT *, CAST({_FRAG.format('src')} AS INTEGER) AS src_frag, CAST({_FRAG.format('dst')} AS INTEGER) AS dst_frag FROM edges), msg AS (SELECT DISTINCT dst_frag AS from_frag, src_frag AS to_frag, vid, kid, d FROM dist JOIN framed ON dst = vid WHERE src_frag <> dst_frag)"
_add("backward_messages_step1", lambda s, d: _messages(_local(s, d)), f"{_MESSAGES} SELECT * FROM msg")
_add(
    "budgets_step1",
    lambda s, d: _messages(_local(s, d)).select("to_frag", "vid", "kid", F.least(F.lit(6), F.lit(9) - F.col("d")).alias("budget")),
    f"{_MESSAGES} SELECT to_frag, vid, kid, least(6, 9 - d) AS budget FROM msg",
)
_add(
    "staleness_step1",
    lambda s, d: _messages(_local(s, d)).groupBy(F.col("to_frag").alias("frag")).agg(F.sum(F.least(F.lit(6), F.lit(9) - F.col("d"))).alias("sum_budget"), F.count("*").alias("size")),
    f"{_MESSAGES} SELECT to_frag AS frag, CAST(sum(least(6, 9 - d)) AS BIGINT) AS sum_budget, count(*) AS size FROM msg GROUP BY to_frag",
)


def _demands(local: tuple[DataFrame, DataFrame]) -> DataFrame:
    labels, framed = local
    partial = labels.groupBy("vid").agg(F.count("*").alias("n"), F.min("d").alias("d"), F.min("key").alias("key")).filter("n < 2")
    seeds = partial.select((1 - F.col("key")).alias("key"), "vid", "d")
    inside, cross = framed.filter("src_frag = dst_frag"), framed.filter("src_frag <> dst_frag")
    # Budgets fall along paths, so the furthest demands are shortest distances from seeds that start at their own distance.
    out = spread(inside.select("src", "dst", "w"), seeds, 6, backwards=False).select("key", "vid", (F.lit(6) - F.col("d")).alias("budget"))
    sent = out.join(cross, out["vid"] == cross["src"]).select(F.col("src_frag").alias("from_frag"), F.col("dst_frag").alias("to_frag"), F.col("dst").alias("vid"), F.col("key").cast("int").alias("kid"), (F.col("budget") - F.col("w")).alias("budget")).filter("budget >= 0")
    return sent.groupBy("from_frag", "to_frag", "vid", "kid").agg(F.max("budget").alias("budget"))


_DEMANDS = f"""{_MESSAGES},
seed AS (SELECT 1 - min(kid) AS kid, vid, 6 - min(d) AS b FROM dist GROUP BY vid HAVING count(*) < 2),
dem(kid, vid, b) AS (SELECT kid, vid, b FROM seed WHERE b >= 0 UNION SELECT kid, dst, b - w FROM dem JOIN framed ON src = vid WHERE src_frag = dst_frag AND b - w >= 0),
sent AS (SELECT src_frag AS from_frag, dst_frag AS to_frag, dst AS vid, kid, max(b - w) AS budget FROM dem JOIN framed ON src = vid WHERE src_frag <> dst_frag AND b - w >= 0 GROUP BY ALL)"""
_add("forward_demand_step1", lambda s, d: _demands(_local(s, d)), f"{_DEMANDS} SELECT from_frag, to_frag, vid, kid, budget FROM sent")


def _selector(s: SparkSession, d: str) -> DataFrame:
    local = _local(s, d)
    back = _messages(local).groupBy(F.col("to_frag").alias("frag")).agg(F.sum(F.least(F.lit(6), F.lit(9) - F.col("d"))).alias("sb"), F.count("*").alias("nb"))
    ahead = _demands(local).groupBy(F.col("to_frag").alias("frag")).agg(F.sum(F.least(F.lit(6), F.col("budget"))).alias("sf"), F.count("*").alias("nf"))
    stale = F.col("sb").isNotNull() & (F.col("sf").isNull() | (F.col("sb") * F.col("nf") < F.col("sf") * F.col("nb")))
    return back.join(ahead, "frag", "full").select("frag", F.when(stale, "b").otherwise("f").alias("task"))


_add(
    "selector_step1",
    _selector,
    f"{_DEMANDS}, b AS (SELECT to_frag AS frag, sum(least(6, 9 - d)) AS sb, count(*) AS nb FROM msg GROUP BY 1), f AS (SELECT to_frag AS frag, sum(least(6, budget)) AS sf, count(*) AS nf FROM sent GROUP BY 1)"
    " SELECT frag, CASE WHEN sb IS NOT NULL AND (sf IS NULL OR sb * nf < sf * nb) THEN 'b' ELSE 'f' END AS task FROM b FULL JOIN f USING (frag)",
)

# -- sketches ------------------------------------------------------------------------------


def _centres(g) -> DataFrame:
    """The 8 vertices with most incoming edges."""
    return g.edges.groupBy("dst").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "dst").limit(8).select(F.col("dst").alias("key"), F.col("dst").alias("vid"))


_CENTRES = f"""WITH RECURSIVE {graph_ctes('g1r').replace('edges AS (', 'edges AS MATERIALIZED (', 1).replace('postings AS (', 'postings AS MATERIALIZED (', 1)},
centres AS MATERIALIZED (SELECT dst AS centre FROM edges GROUP BY dst ORDER BY count(*) DESC, dst LIMIT 8),
wo(centre, vid, d) AS (SELECT centre, centre, CAST(0 AS BIGINT) FROM centres UNION SELECT centre, src, d + w FROM wo JOIN edges ON dst = vid WHERE d + w <= 6),
wi(centre, vid, d) AS (SELECT centre, centre, CAST(0 AS BIGINT) FROM centres UNION SELECT centre, dst, d + w FROM wi JOIN edges ON src = vid WHERE d + w <= 6),
lo AS MATERIALIZED (SELECT vid, centre, min(d) AS d FROM wo GROUP BY ALL), li AS MATERIALIZED (SELECT vid, centre, min(d) AS d FROM wi GROUP BY ALL),
ko AS (SELECT kw, centre, min(d) AS d_min, max(d) AS d_max, count(*) AS holders FROM lo JOIN postings USING (vid) GROUP BY ALL),
ki AS (SELECT kw, centre, min(d) AS d_min, max(d) AS d_max, count(*) AS holders FROM li JOIN postings USING (vid) GROUP BY ALL),
total AS (SELECT kw, count(*) AS total FROM postings GROUP BY kw)"""


def _marks(s: SparkSession, d: str):
    g = build_graph(s, d, "g1r")
    return g, *sketch.landmarks(g, _centres(g), 6)


def _side(s: SparkSession, d: str, out: bool):
    g = build_graph(s, d, "g1r")
    return g, sketch.landmark_side(g, _centres(g), 6, out)


def _sketched(part: str):
    def run(s: SparkSession, d: str) -> DataFrame:
        if part == "upper":
            g, out, inward = _marks(s, d)
            return sketch.upper_bound(out, sketch.keyword_sketch(inward, g.postings)).filter(F.col("kw").isin(*Q4))
        g, side = _side(s, d, part != "lb2")
        if part == "lb1":
            return sketch.lower_bound_out(side, sketch.keyword_sketch(side, g.postings), g.postings).filter(F.col("kw").isin(*Q6))
        if part == "lb2":
            return sketch.lower_bound_in(side, sketch.keyword_sketch(side, g.postings)).filter(F.col("kw").isin(*Q4))
        return sketch.keyword_sketch(side, g.postings)

    return run


_add("landmark_out", lambda s, d: _side(s, d, True)[1], f"{_CENTRES} SELECT vid, centre, d FROM lo")
_add("landmark_in", lambda s, d: _side(s, d, False)[1], f"{_CENTRES} SELECT vid, centre, d FROM li")
_add("kw_sketch_merge", _sketched("merge"), f"{_CENTRES} SELECT kw, centre, d_min, d_max, holders FROM ko")
_add("sketch_upper", _sketched("upper"), f"{_CENTRES} SELECT vid, kw, min(d + d_min) AS ub FROM lo JOIN ki USING (centre) WHERE kw IN {Q4} GROUP BY ALL")
_add("sketch_lower_lb1", _sketched("lb1"), f"{_CENTRES} SELECT vid, kw, max(d - d_max) AS lb FROM lo JOIN ko USING (centre) JOIN total USING (kw) WHERE holders = total AND kw IN {Q6} GROUP BY ALL")
_add("sketch_lower_lb2", _sketched("lb2"), f"{_CENTRES} SELECT vid, kw, max(d_min - d) AS lb FROM li JOIN ki USING (centre) WHERE kw IN {Q4} GROUP BY ALL")


def _violations(s: SparkSession, d: str, graph: Graph | None = None, keywords=Q4) -> DataFrame:
    """How often each lower bound exceeds the true distance to the keywords."""
    g = graph or build_graph(s, d, "g1r")
    # Three searches walk these edges; the bounds of other keywords meet no distance.
    g = replace(g, edges=Snapshot(g.edges).df, postings=Snapshot(g.postings.filter(F.col("kw").isin(*keywords))).df)
    out, inward = sketch.landmarks(g, _centres(g), 6)
    wave = Search(g, [KeywordQuery(keywords, 6)], "exhaustive")
    labels, _ = wave.backward()
    wave.close()
    query = query_frame(s, [KeywordQuery(keywords, 6)])
    true = labels.join(F.broadcast(query.select("qid", "kid", "kw")), ["qid", "kid"]).select("kw", "vid", distance(F.col("p")).alias("d"))
    ko, ki = sketch.keyword_sketch(out, g.postings), sketch.keyword_sketch(inward, g.postings)
    forms = {"lb1": sketch.lower_bound_out(out, ko, g.postings), "lb2": sketch.lower_bound_in(inward, ki), "as_printed": sketch.lower_bound_as_printed(out, ko)}
    rows = None
    for name, lb in forms.items():
        part = true.join(lb, ["kw", "vid"]).agg(F.count("*").alias("n"), F.sum((F.col("lb") > F.col("d")).cast("long")).alias("n_wrong")).withColumn("form", F.lit(name))
        rows = part if rows is None else rows.unionByName(part)
    return rows.select("form", "n", F.coalesce("n_wrong", F.lit(0)).alias("n_wrong"))


_TRUE = ", wk(kw, vid, d) AS (SELECT kw, vid, CAST(0 AS BIGINT) FROM postings WHERE kw IN " + str(Q4) + " UNION SELECT kw, src, d + w FROM wk JOIN edges ON dst = vid WHERE d + w <= 6), t AS (SELECT kw, vid, min(d) AS d FROM wk GROUP BY ALL)"
_add(
    "lb_violation_rate",
    _violations,
    f"{_CENTRES}{_TRUE}, b AS (SELECT 'lb1' AS form, vid, kw, max(d - d_max) AS lb FROM lo JOIN ko USING (centre) JOIN total USING (kw) WHERE holders = total GROUP BY ALL UNION ALL SELECT 'lb2', vid, kw, max(d_min - d) FROM li JOIN ki USING (centre) GROUP BY ALL UNION ALL SELECT 'as_printed', vid, kw, min(d - d_min) FROM lo JOIN ko USING (centre) GROUP BY ALL)"
    " SELECT form, count(t.d) AS n, count(*) FILTER (lb > t.d) AS n_wrong FROM (SELECT unnest(['lb1', 'lb2', 'as_printed']) AS form) LEFT JOIN (b JOIN t USING (kw, vid)) USING (form) GROUP BY form",
)
_PR = f"WITH {graph_ctes('g1').replace('edges AS (', 'edges AS MATERIALIZED (', 1)}, deg AS (SELECT src, count(*) AS g FROM edges GROUP BY src), v AS MATERIALIZED (SELECT vid, g FROM (SELECT src AS vid FROM edges UNION SELECT dst FROM edges) LEFT JOIN deg ON src = vid), n AS (SELECT count(*) AS n FROM v), p0 AS (SELECT vid, g, 1.0::DOUBLE / n AS pr FROM v, n)" + "".join(
    f", p{i} AS MATERIALIZED (SELECT v.vid, v.g, 0.15 / n + 0.85 * (coalesce(got, 0) + (SELECT coalesce(sum(pr), 0) FROM p{i - 1} WHERE g IS NULL) / n) AS pr FROM v CROSS JOIN n LEFT JOIN (SELECT dst, sum(pr / g) AS got FROM p{i - 1} JOIN edges ON src = vid GROUP BY dst) ON dst = v.vid)" for i in range(1, 6)
)
_add("pagerank_5", lambda s, d: sketch.pagerank(build_graph(s, d, "g1"), iterations=5).select("vid", F.round(F.col("pr") * 10**7).cast("long").alias("pr7")), f"{_PR} SELECT vid, CAST(round(pr * 10000000) AS BIGINT) AS pr7 FROM p5")
_add("all_distances_sketch", lambda s, d: sketch.build_sketch(g := build_graph(s, d, "g2"), sketch.pagerank(g, iterations=5), 3))


def _costs(s: SparkSession, d: str) -> DataFrame:
    """Supersteps, messages, bytes, expansions and exchanges of each variant on one query."""
    g, q = partition.hold(build_graph(s, d, "g1r"), 4), KeywordQuery(Q4, 3, 10)
    index = sketch.Index.build(g, 4, 6, iterations=3)
    rows = []
    for v in ("two_phase", "sketch", "exchange", "preemptive"):
        r = run_program(g, q, v, 4, index=index)
        rows.append((v, len(r.steps), r.messages, r.message_bytes, r.pops, r.visited, r.notified, r.pushed))
    return s.createDataFrame(rows, "variant string, supersteps int, messages long, bytes long, pops long, visited long, notified long, pushed long")


def _share(s: SparkSession, d: str) -> DataFrame:
    """Bytes, expansions and forward roots beside the exhaustive baseline's, and the share of its bytes."""
    g, q = partition.hold(build_graph(s, d, "g1"), 4), KeywordQuery(Q4, 3, 10)
    runs = {v: run_program(g, q, v, 4) for v in ("exhaustive", "two_phase")}
    base = runs["exhaustive"].message_bytes
    rows = [(v, r.message_bytes, r.pops, r.forward_roots, r.message_bytes / base if base else None) for v, r in runs.items()]
    return s.createDataFrame(rows, "variant string, bytes long, pops long, forward_roots long, share double")


_add("cost_messages_by_variant", _costs)
_add("cost_share_of_exhaustive", _share)
_add("exp_trajectory", lambda s, d: trajectory(s, build_graph(s, d, "g1r"), KeywordQuery(Q4, 3, 10), "single_task", 2))
_add(
    "cost_visited_by_step",
    lambda s, d: _labels(s, d)[0].groupBy(distance(F.col("p")).alias("d")).agg(F.count_distinct("vid").alias("visited"), F.count("*").alias("labels")),
    f"{_walk('g1', Q4, 3)} SELECT d, count(DISTINCT vid) AS visited, count(*) AS labels FROM dist GROUP BY d",
)

SQL_INCREMENTAL = f"SELECT qid, rank, root, score FROM ({topk_sql('g4', ('purchase', 'error'), 4, 10)})"
