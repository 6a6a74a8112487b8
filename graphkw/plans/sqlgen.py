"""A search as SQL text over the views of a graph, for small thresholds.

Spark's recursive queries allow UNION ALL only, which walks every path; the engine's loop is the way for anything larger.
"""

from __future__ import annotations

from graphkw.schema import Graph, KeywordQuery


def publish_views(graph: Graph, prefix: str = "graph") -> None:
    """Temporary views ``<prefix>_edges`` and ``<prefix>_postings``."""
    graph.edges.createOrReplaceTempView(f"{prefix}_edges")
    graph.postings.createOrReplaceTempView(f"{prefix}_postings")


def to_sql(query: KeywordQuery, prefix: str = "graph") -> str:
    """Spark SQL that returns (rank, root, score)."""
    words = ", ".join("'" + w.replace("'", "''") + "'" for w in query.keywords)
    return f"""
WITH RECURSIVE walk(kw, vid, d) AS (
  SELECT kw, vid, 0L FROM {prefix}_postings WHERE kw IN ({words})
  UNION ALL SELECT w.kw, e.src, w.d + e.w FROM walk w JOIN {prefix}_edges e ON e.dst = w.vid WHERE w.d + e.w <= {query.tau}),
near AS (SELECT kw, vid, min(d) AS d FROM walk GROUP BY kw, vid),
complete AS (SELECT vid AS root, sum(d) AS score FROM near GROUP BY vid HAVING count(*) = {len(query.keywords)})
SELECT CAST(row_number() OVER (ORDER BY score, root) AS INT) AS rank, root, score FROM complete ORDER BY score, root LIMIT {query.k}"""
