"""Relational building blocks around the search, each with its SQL twin."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from graphkw.sources.tables import build_graph, table
from graphkw.sources.tables_sql import graph_ctes

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}
_G1 = f"WITH {graph_ctes('g1')}"


def _add(name: str, run: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    QUERIES[name] = run
    if sql:
        SQL[name] = sql


def _on(name: str, run: Callable[[DataFrame], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    return lambda s, d: run(table(s, d, name))


def _g1(run) -> Callable[[SparkSession, str], DataFrame]:
    return lambda s, d: run(build_graph(s, d, "g1"))


# -- scan, filter, projection --------------------------------------------------------------

_add("op_scan_prune", _on("customer", lambda t: t.filter("c_mktsegment = 'HOUSEHOLD'").select("c_custkey", "c_acctbal")), "SELECT c_custkey, c_acctbal FROM customer WHERE c_mktsegment = 'HOUSEHOLD'")
_FILTER = "(p_size BETWEEN 5 AND 20 OR p_brand IN ('Brand#1', 'Brand#2')) AND NOT p_type = 'SMALL' AND p_name LIKE '%widget%' AND p_retailprice IS NOT NULL"
_add("op_filter_compound", _on("part", lambda t: t.filter(_FILTER).select("p_partkey", "p_name", "p_size")), f"SELECT p_partkey, p_name, p_size FROM part WHERE {_FILTER}")
_add(
    "op_project_case",
    _on("lineitem", lambda t: t.select("l_orderkey", "l_linenumber", "l_quantity", F.when(F.col("l_quantity") < 10, "low").when(F.col("l_quantity") < 30, "mid").otherwise("high").alias("band"))),
    "SELECT l_orderkey, l_linenumber, l_quantity, CASE WHEN l_quantity < 10 THEN 'low' WHEN l_quantity < 30 THEN 'mid' ELSE 'high' END AS band FROM lineitem",
)

# -- joins -------------------------------------------------------------------------------------


def _join(left: str, right: str, on: str, columns: list[str], how: str = "inner", hint: str = ""):
    def run(s: SparkSession, d: str) -> DataFrame:
        r = table(s, d, right).alias(right)
        return table(s, d, left).alias(left).join(r.hint(hint) if hint else r, F.expr(on), how).select(*columns)

    kind = {"inner": "JOIN", "left": "LEFT JOIN", "full": "FULL JOIN", "left_semi": "SEMI JOIN", "left_anti": "ANTI JOIN"}[how]
    return run, f"SELECT {', '.join(columns)} FROM {left} {kind} {right} ON {on}"


_add("op_join_inner_broadcast", *_join("customer", "nation", "c_nationkey = n_nationkey", ["c_custkey", "n_name"], hint="broadcast"))
_add("op_join_sortmerge", *_join("lineitem", "orders", "l_orderkey = o_orderkey", ["l_orderkey", "l_linenumber", "o_custkey"], hint="merge"))
_add("op_join_shuffle_hash", *_join("lineitem", "part", "l_partkey = p_partkey", ["l_orderkey", "p_brand"], hint="shuffle_hash"))
_add("op_join_left_outer", *_join("documents", "labels", "documents.doc_id = labels.doc_id", ["documents.doc_id", "quality"], "left"))
_add("op_join_full_outer", *_join("customer", "orders", "c_custkey = o_custkey AND o_orderstatus = 'P'", ["c_custkey", "o_orderkey"], "full"))
_add("op_join_semi", *_join("customer", "orders", "c_custkey = o_custkey", ["c_custkey"], "left_semi"))
_add("op_join_anti", *_join("customer", "orders", "c_custkey = o_custkey", ["c_custkey"], "left_anti"))


def _bands(s: SparkSession, d: str) -> DataFrame:
    """Parts within two of each other's price: equal or neighbouring bands of width two, then the exact test."""
    p = table(s, d, "part").select(F.col("p_partkey").alias("a"), F.col("p_retailprice").alias("x"), F.floor(F.col("p_retailprice") / 2).alias("band"))
    q = p.select(F.col("a").alias("b"), F.col("x").alias("y"), F.explode(F.array(F.col("band") - 1, F.col("band"), F.col("band") + 1)).alias("band"))
    return p.join(q, "band").filter("a < b AND abs(x - y) <= 2").select("a", "b")


_add("op_join_theta_range", _bands, "SELECT p.p_partkey AS a, q.p_partkey AS b FROM part p JOIN part q ON p.p_partkey < q.p_partkey AND abs(p.p_retailprice - q.p_retailprice) <= 2")
_add("op_join_cross_small", lambda s, d: table(s, d, "region").select(F.col("r_name").alias("a")).crossJoin(F.broadcast(table(s, d, "region").select(F.col("r_name").alias("b")))), "SELECT a.r_name AS a, b.r_name AS b FROM region a, region b")


def _by_user():
    return Window.partitionBy("user_id").orderBy("ts", "event_id")


_add(
    "op_join_asof",
    _on("events", lambda t: t.select("event_id", F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(_by_user().rowsBetween(Window.unboundedPreceding, -1)).alias("prior"))),
    "SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS prior FROM events",
)
_add(
    "op_join_self_two_hop",
    _g1(lambda g: g.edges.alias("a").join(g.edges.alias("b"), F.expr("a.dst = b.src")).groupBy("a.src", "b.dst").agg(F.min(F.expr("a.w + b.w")).alias("w"))),
    f"{_G1} SELECT a.src, b.dst, min(a.w + b.w) AS w FROM edges a JOIN edges b ON a.dst = b.src GROUP BY a.src, b.dst",
)

# -- aggregation -----------------------------------------------------------------------------------

_add("op_agg_hash", _g1(lambda g: g.edges.groupBy("dst").agg(F.min("w").alias("w"), F.count("*").alias("n"))), f"{_G1} SELECT dst, min(w) AS w, count(*) AS n FROM edges GROUP BY dst")
_add("op_agg_sort_struct", _g1(lambda g: g.edges.groupBy("src").agg(F.min(F.struct("w", "dst")).alias("m")).select("src", "m.w", "m.dst")), f"{_G1} SELECT src, w, dst FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY w, dst) AS r FROM edges) WHERE r = 1")
_add("op_struct_min", _g1(lambda g: g.edges.groupBy("dst").agg(F.min_by("src", F.struct("w", "src")).alias("nearest"))), f"{_G1} SELECT dst, src AS nearest FROM (SELECT *, row_number() OVER (PARTITION BY dst ORDER BY w, src) AS r FROM edges) WHERE r = 1")
_add("op_agg_distinct", _g1(lambda g: g.postings.agg(F.count_distinct("kw").alias("keywords"), F.count_distinct("vid").alias("vertices"))), f"{_G1} SELECT count(DISTINCT kw) AS keywords, count(DISTINCT vid) AS vertices FROM postings")
_add("op_agg_approx_distinct", _g1(lambda g: g.postings.agg(F.approx_count_distinct("vid").alias("vertices"))))
_add("op_agg_having", _g1(lambda g: g.postings.groupBy("vid").agg(F.count("*").alias("n")).filter("n >= 4")), f"{_G1} SELECT vid, count(*) AS n FROM postings GROUP BY vid HAVING count(*) >= 4")
_add("op_agg_collect", _g1(lambda g: g.postings.groupBy("vid").agg(F.array_join(F.sort_array(F.collect_set("kw")), ",").alias("kws"))), f"{_G1} SELECT vid, string_agg(kw, ',' ORDER BY kw) AS kws FROM postings GROUP BY vid")
_add(
    "op_agg_filter",
    _on("lineitem", lambda t: t.groupBy("l_returnflag").agg(F.sum(F.when(F.col("l_linestatus") == "O", 1).otherwise(0)).alias("n_open"), F.sum(F.when(F.col("l_quantity") > 25, F.col("l_quantity").cast("long")).otherwise(0)).alias("q"))),
    "SELECT l_returnflag, CAST(count(*) FILTER (l_linestatus = 'O') AS BIGINT) AS n_open, CAST(coalesce(sum(CAST(l_quantity AS BIGINT)) FILTER (l_quantity > 25), 0) AS BIGINT) AS q FROM lineitem GROUP BY l_returnflag",
)
_CUBE = "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY {}(o_orderstatus, o_orderpriority)"
_add("op_rollup", _on("orders", lambda t: t.rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))), _CUBE.format("ROLLUP "))
_add("op_cube", _on("orders", lambda t: t.cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))), _CUBE.format("CUBE "))
_SETS = "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM {} GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority))"
_add("op_grouping_sets", _on("orders", lambda t: t.sparkSession.sql(_SETS.format("{t}"), t=t)), _SETS.format("orders"))
_add(
    "op_pivot",
    _on("orders", lambda t: t.groupBy("o_custkey").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).select("o_custkey", *(F.coalesce(c, F.lit(0)).alias(c.lower()) for c in "FOP"))),
    "SELECT o_custkey, count(*) FILTER (o_orderstatus = 'F') AS f, count(*) FILTER (o_orderstatus = 'O') AS o, count(*) FILTER (o_orderstatus = 'P') AS p FROM orders GROUP BY o_custkey HAVING count(*) > 0",
)
_add(
    "op_unpivot",
    _on("part", lambda t: t.select("p_partkey", F.col("p_size").cast("long").alias("size"), F.floor("p_retailprice").alias("price")).unpivot("p_partkey", ["size", "price"], "name", "value")),
    "SELECT p_partkey, 'size' AS name, CAST(p_size AS BIGINT) AS value FROM part UNION ALL SELECT p_partkey, 'price', CAST(floor(p_retailprice) AS BIGINT) FROM part",
)

# -- windows, order, limits --------------------------------------------------------------------------



def _nation():
    return Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"))


_add(
    "op_window_rank",
    _on("customer", lambda t: t.select("c_custkey", F.row_number().over(_nation().orderBy(F.desc("c_acctbal"), "c_custkey")).alias("n"), F.rank().over(_nation()).alias("r"), F.dense_rank().over(_nation()).alias("dr"))),
    "SELECT c_custkey, CAST(row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS INTEGER) AS n, CAST(rank() OVER w AS INTEGER) AS r, CAST(dense_rank() OVER w AS INTEGER) AS dr FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal DESC)",
)
_add("op_window_frame_rows", _on("events", lambda t: t.select("event_id", F.count("*").over(_by_user().rowsBetween(-3, 0)).alias("n"), F.max("event_id").over(_by_user().rowsBetween(-3, -1)).alias("m"))), "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW) AS n, max(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND 1 PRECEDING) AS m FROM events")


def _hour():
    return Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-3600 * 10**6, 0)


_add("op_window_frame_range", _on("events", lambda t: t.select("event_id", F.count("*").over(_hour()).alias("n"))), "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS n FROM events")
_add("op_window_lag_lead", _on("events", lambda t: t.select("event_id", F.lag("event_id").over(_by_user()).alias("before"), F.lead("event_id").over(_by_user()).alias("after"))), "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")


def _brand():
    return Window.partitionBy("p_brand").orderBy("p_retailprice", "p_partkey")


_add(
    "op_window_ntile_pct",
    _on("part", lambda t: t.select("p_partkey", F.ntile(4).over(_brand()).alias("tile"), F.round(F.percent_rank().over(_brand()) * 10**6).cast("long").alias("pct"), F.round(F.cume_dist().over(_brand()) * 10**6).cast("long").alias("cum"))),
    "SELECT p_partkey, CAST(ntile(4) OVER w AS INTEGER) AS tile, CAST(round(percent_rank() OVER w * 1000000) AS BIGINT) AS pct, CAST(round(cume_dist() OVER w * 1000000) AS BIGINT) AS cum FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_retailprice, p_partkey)",
)
_add("op_topk_global", _g1(lambda g: g.edges.groupBy("dst").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "dst").limit(10)), f"{_G1} SELECT dst, count(*) AS n FROM edges GROUP BY dst ORDER BY n DESC, dst LIMIT 10")
_add("op_sort_nulls", lambda s, d: _join("documents", "labels", "documents.doc_id = labels.doc_id", ["documents.doc_id", "quality"], "left")[0](s, d).orderBy(F.asc_nulls_last("quality"), F.desc("doc_id")).limit(20), "SELECT documents.doc_id, quality FROM documents LEFT JOIN labels ON documents.doc_id = labels.doc_id ORDER BY quality ASC NULLS LAST, documents.doc_id DESC LIMIT 20")
_add("op_limit_offset", _on("part", lambda t: t.select("p_partkey", "p_retailprice").orderBy(F.desc("p_retailprice"), "p_partkey").offset(10).limit(10)), "SELECT p_partkey, p_retailprice FROM part ORDER BY p_retailprice DESC, p_partkey LIMIT 10 OFFSET 10")

# -- sets ---------------------------------------------------------------------------------------------

_HOLD = lambda g, kw: g.postings.filter(F.col("kw") == kw).select("vid")
_H = lambda kw: f"SELECT vid FROM postings WHERE kw = '{kw}'"
_add("op_union_by_name", lambda s, d: table(s, d, "nation").select(F.col("n_name").alias("name"), F.col("n_regionkey").alias("up")).unionByName(table(s, d, "region").select(F.col("r_name").alias("name")), allowMissingColumns=True), "SELECT n_name AS name, n_regionkey AS up FROM nation UNION ALL SELECT r_name, NULL FROM region")
_add("op_union_distinct", _g1(lambda g: _HOLD(g, "widget").union(_HOLD(g, "brand#17")).distinct()), f"{_G1} {_H('widget')} UNION {_H('brand#17')}")
_add("op_intersect", _g1(lambda g: _HOLD(g, "widget").intersect(_HOLD(g, "brand#17"))), f"{_G1} {_H('widget')} INTERSECT {_H('brand#17')}")
_add("op_except", _g1(lambda g: _HOLD(g, "widget").subtract(_HOLD(g, "brand#17"))), f"{_G1} {_H('widget')} EXCEPT {_H('brand#17')}")
_add("op_except_all", _on("orders", lambda t: t.select("o_custkey").exceptAll(t.filter("o_orderstatus = 'F'").select("o_custkey"))), "SELECT o_custkey FROM orders EXCEPT ALL SELECT o_custkey FROM orders WHERE o_orderstatus = 'F'")

# -- scalar functions -------------------------------------------------------------------------------

_add("op_string_tokens", _on("part", lambda t: t.select("p_partkey", F.explode(F.split(F.lower(F.trim("p_name")), " ")).alias("token"))), "SELECT p_partkey, unnest(string_split(lower(trim(p_name)), ' ')) AS token FROM part")
_add("op_string_regex", _on("pages", lambda t: t.select("page_id", F.regexp_extract("html", "<title>([^<]*)</title>", 1).alias("title"), F.size(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).cast("long").alias("links"))), "SELECT page_id, regexp_extract(html, '<title>([^<]*)</title>', 1) AS title, CAST(len(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS BIGINT) AS links FROM pages")
_add("op_url_parts", _on("pages", lambda t: t.select("page_id", F.regexp_extract("url", "^[a-z]+://([^/?#]+)", 1).alias("host"), F.coalesce(F.parse_url("url", F.lit("QUERY")), F.lit("")).alias("query"))), r"SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, regexp_extract(url, '\?([^#]*)', 1) AS query FROM pages")
_add("op_hash_md5", _g1(lambda g: g.postings.select("kw").distinct().select("kw", F.md5(F.concat_ws("|", F.lit("s"), "kw")).alias("h"))), f"{_G1} SELECT kw, md5('s|' || kw) AS h FROM (SELECT DISTINCT kw FROM postings)")
_add("op_date_trunc", _on("orders", lambda t: t.groupBy(F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("month"), F.year("o_orderdate").cast("long").alias("y")).agg(F.count("*").alias("n"), F.max(F.datediff("o_orderdate", F.lit("1998-01-01").cast("date"))).cast("long").alias("days"))), "SELECT strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month, CAST(year(o_orderdate) AS BIGINT) AS y, count(*) AS n, CAST(max(date_diff('day', DATE '1998-01-01', CAST(o_orderdate AS DATE))) AS BIGINT) AS days FROM orders GROUP BY 1, 2")
_add("op_math_buckets", _on("lineitem", lambda t: t.select("l_orderkey", "l_linenumber", F.expr("cast(l_quantity as bigint) div 10").alias("b"), F.least(F.lit(3), F.greatest(F.lit(1), F.pmod(F.col("l_orderkey"), F.lit(7)))).cast("long").alias("c"))), "SELECT l_orderkey, l_linenumber, CAST(l_quantity AS BIGINT) // 10 AS b, CAST(least(3, greatest(1, l_orderkey % 7)) AS BIGINT) AS c FROM lineitem")
_add("op_array_hof", _on("embeddings", lambda t: t.select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("n_pos"), F.exists("embedding", lambda x: x > 0.3).alias("any_big"), F.aggregate(F.transform("embedding", lambda x: F.floor(x.cast("double") * 100).cast("long")), F.lit(0).cast("long"), lambda a, x: a + x).alias("total"))), "SELECT vec_id, CAST(len(list_filter(embedding, lambda x: x > 0)) AS BIGINT) AS n_pos, len(list_filter(embedding, lambda x: CAST(x AS DOUBLE) > 0.3)) > 0 AS any_big, CAST(list_sum(list_transform(embedding, lambda x: CAST(floor(CAST(x AS DOUBLE) * 100) AS BIGINT))) AS BIGINT) AS total FROM embeddings")
_DOT = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def _cosine(s: SparkSession, d: str) -> DataFrame:
    t = table(s, d, "embeddings")
    one = t.filter("vec_id = 0").select(F.col("embedding").alias("q"))
    c = _DOT("embedding", "q") / F.sqrt(_DOT("embedding", "embedding") * _DOT("q", "q"))
    return t.crossJoin(F.broadcast(one)).select("vec_id", F.round(c * 10000).cast("long").alias("c4"))


_D = lambda a, b: f"list_sum(list_transform(range(1, 65), lambda i: CAST({a}[i] AS DOUBLE) * CAST({b}[i] AS DOUBLE)))"
_add("op_array_cosine", _cosine, f"SELECT e.vec_id, CAST(round(10000 * {_D('e.embedding', 'q.embedding')} / sqrt({_D('e.embedding', 'e.embedding')} * {_D('q.embedding', 'q.embedding')})) AS BIGINT) AS c4 FROM embeddings e, (SELECT * FROM embeddings WHERE vec_id = 0) q")
_add("op_map_match", _on("orders", lambda t: t.groupBy("o_custkey").agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("o_orderkey", "o_totalprice")))).alias("m")).select("o_custkey", F.size("m").cast("long").alias("n"), F.array_min(F.map_keys("m")).alias("least"), F.element_at("m", F.array_min(F.map_keys("m"))).alias("price"))), "SELECT o_custkey, count(*) AS n, min(o_orderkey) AS least, arg_min(o_totalprice, o_orderkey) AS price FROM orders GROUP BY o_custkey")
_add("op_json_parse", _on("events", lambda t: t.select("event_id", F.from_json("props", "k long")["k"].alias("k"), F.get_json_object("props", "$.k").alias("ks"))), "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, json_extract_string(props, '$.k') AS ks FROM events")
_add("op_json_write", _on("nation", lambda t: t.select(F.to_json(F.struct(F.col("n_nationkey").alias("k"), F.col("n_name").alias("n"))).alias("j"))), """SELECT '{"k":' || n_nationkey || ',"n":"' || n_name || '"}' AS j FROM nation""")
_add("op_sample_hash", _on("lineitem", lambda t: t.filter(F.pmod(F.col("l_orderkey") * 31 + F.col("l_linenumber"), F.lit(10)) < 3).select("l_orderkey", "l_linenumber")), "SELECT l_orderkey, l_linenumber FROM lineitem WHERE (l_orderkey * 31 + l_linenumber) % 10 < 3")
_add("op_histogram", _g1(lambda g: g.edges.groupBy("dst").agg(F.count("*").alias("degree")).groupBy("degree").agg(F.count("*").alias("n"))), f"{_G1} SELECT degree, count(*) AS n FROM (SELECT dst, count(*) AS degree FROM edges GROUP BY dst) GROUP BY degree")


def _explode_outer(s: SparkSession, d: str) -> DataFrame:
    g = build_graph(s, d, "g1")
    held = g.postings.groupBy("vid").agg(F.sort_array(F.collect_set("kw")).alias("kws"))
    return g.vertices.filter("kind IN ('supplier', 'region')").join(held, "vid", "left").select("vid", F.explode_outer("kws").alias("kw"))


_add("op_explode_outer", _explode_outer, f"{_G1}, v AS (SELECT CAST(4000000000000 + s_suppkey AS BIGINT) AS vid FROM supplier UNION ALL SELECT CAST(1000000000000 + r_regionkey AS BIGINT) FROM region) SELECT v.vid, kw FROM v LEFT JOIN postings USING (vid)")

# -- user functions --------------------------------------------------------------------------------


def _mean_weight(pdf):
    return pdf.groupby("src", as_index=False).agg(n=("dst", "count"), w=("w", "sum"))


_add("op_udf_pandas_grouped", _g1(lambda g: g.edges.withColumn("frag", F.pmod("src", F.lit(4))).groupBy("frag").applyInPandas(_mean_weight, "src long, n long, w long")), f"{_G1} SELECT src, count(*) AS n, CAST(sum(w) AS BIGINT) AS w FROM edges GROUP BY src")


def _reach(left, right):
    got = left.merge(right, left_on="dst", right_on="vid")
    return got.groupby(["kw", "src"], as_index=False).agg(d=("w", "min"))[["kw", "src", "d"]]


def _cogroup(s: SparkSession, d: str) -> DataFrame:
    g = build_graph(s, d, "g1")
    left = g.edges.withColumn("part", F.pmod("dst", F.lit(8)))
    right = g.postings.filter(F.col("kw").isin("widget", "household")).withColumn("part", F.pmod("vid", F.lit(8)))
    one = left.groupBy("part").cogroup(right.groupBy("part")).applyInPandas(_reach, "kw string, src long, d long")
    return one.groupBy("kw", "src").agg(F.min("d").alias("d"))


_add("op_udf_pandas_cogroup", _cogroup, f"{_G1} SELECT kw, src, min(w) AS d FROM edges JOIN postings ON dst = vid WHERE kw IN ('widget', 'household') GROUP BY kw, src")


def _udtf(s: SparkSession, d: str) -> DataFrame:
    class Steps:
        def eval(self, n: int):
            for k in range(n):
                yield k, n - k

    s.udtf.register("path_steps", F.udtf(Steps, returnType="pos: int, left: int"))
    table(s, d, "region").createOrReplaceTempView("_udtf_region")
    return s.sql("SELECT r_regionkey, pos, left FROM _udtf_region, LATERAL path_steps(CAST(r_regionkey AS INT))")


_add("op_udtf_tree", _udtf, 'SELECT r_regionkey, CAST(pos AS INTEGER) AS pos, CAST(r_regionkey - pos AS INTEGER) AS "left" FROM region, range(10) t(pos) WHERE pos < r_regionkey')
_add("op_udaf_topk", _on("orders", lambda t: t.groupBy("o_custkey").agg(F.slice(F.sort_array(F.collect_list(F.struct((-F.col("o_totalprice")).alias("p"), "o_orderkey"))), 1, 3).alias("x")).select("o_custkey", F.array_join(F.transform("x", lambda e: e["o_orderkey"].cast("string")), ",").alias("top"))), "SELECT o_custkey, string_agg(CAST(o_orderkey AS VARCHAR), ',' ORDER BY r) AS top FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 3 GROUP BY o_custkey")


def _recursive(s: SparkSession, d: str) -> DataFrame:
    build_graph(s, d, "g1").edges.createOrReplaceTempView("_all_edges")
    return s.sql("WITH RECURSIVE w(vid, d) AS (SELECT 1000000000002L, 0L UNION ALL SELECT e.src, w.d + e.w FROM w JOIN _all_edges e ON e.dst = w.vid WHERE w.d + e.w <= 2) SELECT vid, min(d) AS d FROM w GROUP BY vid")


_add("op_recursive_cte", _recursive, f"WITH RECURSIVE {graph_ctes('g1')}, w(vid, d) AS (SELECT CAST(1000000000002 AS BIGINT), CAST(0 AS BIGINT) UNION ALL SELECT e.src, w.d + e.w FROM w JOIN edges e ON e.dst = w.vid WHERE w.d + e.w <= 2) SELECT vid, min(d) AS d FROM w GROUP BY vid")

# -- sources, sinks, streams ------------------------------------------------------------------------

from graphkw.sources.files import bucketed_round_trip, partitioned_round_trip, text_round_trip  # noqa: E402
from graphkw.queries import SQL_INCREMENTAL  # noqa: E402
from graphkw.streaming import events as st  # noqa: E402

_EDGES_SQL = f"{_G1} SELECT src, dst, w FROM edges"
_add("op_sink_partitioned", lambda s, d: partitioned_round_trip(build_graph(s, d, "g1")), _EDGES_SQL)
_add("op_sink_bucketed", lambda s, d: bucketed_round_trip(build_graph(s, d, "g1")), _EDGES_SQL)
_add("op_source_csv_json", lambda s, d: text_round_trip(build_graph(s, d, "g1")), _EDGES_SQL)
_TUMBLE = "SELECT CAST(epoch_us(time_bucket(INTERVAL '{0}', ts, TIMESTAMP '1970-01-01')) // 1000000 AS BIGINT) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2"
_add("st_tumbling", st.tumbling, _TUMBLE.format("1 hour"))
_add("st_sliding", st.sliding, "SELECT CAST(b * 1800 AS BIGINT) AS start, event_type, count(*) AS n FROM (SELECT event_type, unnest([epoch_us(ts) // 1800000000, epoch_us(ts) // 1800000000 - 1]) AS b FROM events) GROUP BY 1, 2")
_add(
    "st_session",
    st.session,
    "SELECT user_id, CAST(min(t) // 1000000 AS BIGINT) AS start, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY t) AS k FROM (SELECT user_id, epoch_us(ts) AS t, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) < 1800000000 THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, k",
)
_add("st_watermark_late", st.watermark_late)
_add("st_dedup", st.dedup, "SELECT event_id, event_type FROM events")
_add("st_stateful_last", st.stateful_last, "SELECT user_id, arg_max(event_id, (ts, event_id)) AS last_event, count(*) AS n FROM events GROUP BY user_id")
_add("st_incremental_search", st.incremental_search, SQL_INCREMENTAL)
