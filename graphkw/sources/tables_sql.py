"""The graph builders again as SQL, for checks: CTEs named edges(src, dst, w) and postings(kw, vid)."""

from __future__ import annotations


def _number(text: str) -> str:
    return f"CAST('0x' || substr(md5({text}), 1, 9) AS BIGINT)"


def _words(table: str, text: str, at: str) -> str:
    return f"SELECT DISTINCT kw, vid FROM (SELECT unnest(string_split(lower({text}), ' ')) AS kw, {at} AS vid FROM {table}) WHERE kw <> '' AND vid IS NOT NULL"


def _v(tag: int, key: str) -> str:
    return f"CAST({tag}000000000000 + {key} AS BIGINT)"


_TRADE_EDGES = f"""
  SELECT src, dst, min(w) AS w FROM (
    SELECT {_v(6, "o_orderkey")} AS src, {_v(3, "o_custkey")} AS dst, CAST(1 AS BIGINT) AS w FROM orders
    UNION ALL SELECT {_v(3, "c_custkey")}, {_v(2, "c_nationkey")}, 1 FROM customer
    UNION ALL SELECT {_v(4, "s_suppkey")}, {_v(2, "s_nationkey")}, 1 FROM supplier
    UNION ALL SELECT {_v(2, "n_nationkey")}, {_v(1, "n_regionkey")}, 1 FROM nation
    UNION ALL SELECT {_v(6, "l_orderkey")}, {_v(5, "l_partkey")}, 1 + CAST(l_quantity AS BIGINT) // 10 FROM lineitem
    UNION ALL SELECT {_v(5, "l_partkey")}, {_v(4, "l_suppkey")}, 1 + CAST(round(l_discount * 100) AS BIGINT) // 2 FROM lineitem)
  WHERE src IS NOT NULL AND dst IS NOT NULL GROUP BY src, dst"""
_TRADE_POSTINGS = f"""
  SELECT DISTINCT kw, vid FROM (
    {_words("region", "r_name", _v(1, "r_regionkey"))}
    UNION ALL {_words("nation", "n_name", _v(2, "n_nationkey"))}
    UNION ALL {_words("customer", "c_mktsegment", _v(3, "c_custkey"))}
    UNION ALL {_words("part", "p_name || ' ' || p_brand || ' ' || p_type", _v(5, "p_partkey"))}
    UNION ALL SELECT lower(o_orderpriority), {_v(6, "o_orderkey")} FROM orders
    UNION ALL SELECT 'status_' || lower(o_orderstatus), {_v(6, "o_orderkey")} FROM orders)"""

_PAGES = """SELECT page_id, regexp_extract(url, '://([^/]+)', 1) AS host, regexp_extract(html, '<title>([^<]*)</title>', 1) AS title,
    regexp_extract(html, 'lang="([^"]*)"', 1) AS lang, regexp_extract_all(html, 'href="/([^"]*)"', 1) AS targets FROM pages"""
_LINKS = f"SELECT DISTINCT page_id, target FROM (SELECT page_id, unnest(targets) AS target FROM ({_PAGES})) WHERE target <> ''"
_TITLES = f"SELECT DISTINCT kw, page_id FROM (SELECT page_id, unnest(string_split(lower(title), ' ')) AS kw FROM ({_PAGES})) WHERE kw <> ''"
_WEB_EDGES = f"""
  SELECT src, dst, min(w) AS w FROM (
    SELECT {_v(7, "page_id")} AS src, {_v(8, _number("target"))} AS dst, CAST(1 AS BIGINT) AS w FROM ({_LINKS})
    UNION ALL SELECT {_v(8, _number("target"))}, {_v(7, "page_id")}, 1 FROM (SELECT DISTINCT target FROM ({_LINKS})) t JOIN ({_TITLES}) ON lower(target) = kw
    UNION ALL SELECT {_v(7, "page_id")}, {_v(9, _number("host"))}, 1 FROM ({_PAGES})
    UNION ALL SELECT {_v(9, _number("host"))}, {_v(7, "page_id")}, 1 FROM ({_PAGES}))
  GROUP BY src, dst"""
_WEB_POSTINGS = f"""
  SELECT DISTINCT kw, vid FROM (
    SELECT kw, {_v(7, "page_id")} AS vid FROM ({_TITLES})
    UNION ALL SELECT lower(lang), {_v(7, "page_id")} FROM ({_PAGES})
    UNION ALL SELECT lower(host), {_v(9, _number("host"))} FROM ({_PAGES})) WHERE kw <> ''"""

_BOUGHT = "SELECT DISTINCT o_custkey, l_partkey, strftime(o_orderdate, '%Y%m') AS month FROM orders JOIN lineitem ON o_orderkey = l_orderkey"
_COPURCHASE_EDGES = f"""
  SELECT {_v(3, "a.o_custkey")} AS src, {_v(3, "b.o_custkey")} AS dst, 5 - least(4, count(DISTINCT a.l_partkey)) AS w
  FROM ({_BOUGHT}) a JOIN ({_BOUGHT}) b ON a.l_partkey = b.l_partkey AND a.month = b.month AND a.o_custkey <> b.o_custkey GROUP BY 1, 2"""
_COPURCHASE_POSTINGS = f"""
  SELECT DISTINCT kw, vid FROM (
    {_words("customer", "c_mktsegment", _v(3, "c_custkey"))}
    UNION ALL {_words("customer JOIN nation ON c_nationkey = n_nationkey", "n_name", _v(3, "c_custkey"))}
    UNION ALL SELECT lower(o_orderpriority), {_v(3, "o_custkey")} FROM orders) WHERE kw IS NOT NULL"""

_JOURNEY_EDGES = f"""
  SELECT src, dst, min(w) AS w FROM (
    SELECT {_v(11, "event_id")} AS src, {_v(11, "nxt")} AS dst, 1 + least(4, pause // 21600000000) AS w
    FROM (SELECT event_id, lead(event_id) OVER o AS nxt, epoch_us(lead(ts) OVER o) - epoch_us(ts) AS pause FROM events WINDOW o AS (PARTITION BY user_id ORDER BY ts, event_id)) WHERE nxt IS NOT NULL
    UNION ALL SELECT {_v(11, "event_id")}, {_v(10, "user_id")}, 1 FROM events) GROUP BY src, dst"""
_JOURNEY_POSTINGS = f"""
  SELECT DISTINCT kw, vid FROM (
    SELECT lower(event_type) AS kw, {_v(11, "event_id")} AS vid FROM events
    UNION ALL SELECT 'k_' || regexp_extract(props, '"k": *([0-9]+)', 1), {_v(11, "event_id")} FROM events WHERE regexp_extract(props, '"k": *([0-9]+)', 1) <> ''
    UNION ALL SELECT 'band_' || CAST(CAST(floor(value / 10) AS BIGINT) AS VARCHAR), {_v(11, "event_id")} FROM events) WHERE kw IS NOT NULL"""

_LINES = f"SELECT DISTINCT doc_id, {_number('line')} AS line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) >= 40"
_SHARED = f"SELECT doc_id, line FROM ({_LINES}) WHERE line IN (SELECT line FROM ({_LINES}) GROUP BY line HAVING count(*) > 1)"
_TEXT_EDGES = f"""
  SELECT src, dst, min(w) AS w FROM (
    SELECT {_v(12, "doc_id")} AS src, {_v(16, _number("source"))} AS dst, CAST(1 AS BIGINT) AS w FROM documents
    UNION ALL SELECT {_v(12, "doc_id")}, {_v(8, "line")}, 1 FROM ({_SHARED})
    UNION ALL SELECT {_v(8, "line")}, {_v(12, "doc_id")}, 1 FROM ({_SHARED})) GROUP BY src, dst"""
_TEXT_POSTINGS = f"""
  SELECT DISTINCT kw, vid FROM (
    SELECT lower(lang) AS kw, {_v(12, "doc_id")} AS vid FROM documents
    UNION ALL SELECT lower(source), {_v(16, _number("source"))} FROM documents
    UNION ALL SELECT 'quality_' || quality, {_v(12, "doc_id")} FROM labels
    UNION ALL SELECT 'toxic_' || toxic, {_v(12, "doc_id")} FROM labels) WHERE kw IS NOT NULL"""

_TURN = _v(14, "conv_id * 100 + turn")
_DIALOGUE_EDGES = f"""
  SELECT src, dst, min(w) AS w FROM (
    SELECT {_TURN} AS src, {_v(14, "conv_id * 100 + nxt")} AS dst, CAST(1 AS BIGINT) AS w FROM (SELECT conv_id, turn, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS nxt FROM conversations) WHERE nxt IS NOT NULL
    UNION ALL SELECT {_TURN}, {_v(15, "conv_id")}, 1 FROM conversations) GROUP BY src, dst"""
_DIALOGUE_POSTINGS = f"""
  SELECT DISTINCT kw, vid FROM (
    SELECT unnest(regexp_extract_all(lower(text), '[a-z]+')) AS kw, {_TURN} AS vid FROM conversations) WHERE length(kw) >= 4
  UNION SELECT lower(role), {_TURN} FROM conversations WHERE role IS NOT NULL"""

EDGES = {
    "g1": _TRADE_EDGES,
    "g1u": f"SELECT src, dst, CAST(1 AS BIGINT) AS w FROM ({_TRADE_EDGES})",
    "g1r": f"SELECT src, dst, min(w) AS w FROM (SELECT * FROM ({_TRADE_EDGES}) UNION ALL SELECT dst, src, w + 1 FROM ({_TRADE_EDGES})) GROUP BY src, dst",
    "g2": _WEB_EDGES,
    "g3": _COPURCHASE_EDGES,
    "g4": _JOURNEY_EDGES,
    "g6": _TEXT_EDGES,
    "g6c": _DIALOGUE_EDGES,
}
POSTINGS = {"g1": _TRADE_POSTINGS, "g1u": _TRADE_POSTINGS, "g1r": _TRADE_POSTINGS, "g2": _WEB_POSTINGS, "g3": _COPURCHASE_POSTINGS, "g4": _JOURNEY_POSTINGS, "g6": _TEXT_POSTINGS, "g6c": _DIALOGUE_POSTINGS}


def graph_ctes(name: str) -> str:
    return f"edges AS ({EDGES[name]}), postings AS ({POSTINGS[name]})"
