from pyspark.sql import functions as F

from graphkw.operators import waves
from graphkw.operators.checks import bounds_fall, missing_roots, rounds_bounded, worsened
from graphkw.operators.tree import explain_match, match_tree, steiner_weight
from graphkw.plans.experiments import straggler_ratio
from graphkw.plans.search import Search, search
from graphkw.plans.sqlgen import publish_views, to_sql
from graphkw.schema import Graph, KeywordQuery
from graphkw.sources.files import load_edge_list, load_graph, load_triples, save_graph
from tests.test_engine import W1_EDGES, W1_POSTINGS, make

QUERY = KeywordQuery(("a", "b"), 6, 2)


def test_generated_sql_gives_the_answers(spark):
    publish_views(make(spark, W1_EDGES, W1_POSTINGS))
    assert [tuple(r) for r in spark.sql(to_sql(QUERY)).collect()] == [(1, 2, 4), (2, 21, 7)]


def test_invariants_hold(spark):
    g = make(spark, W1_EDGES, W1_POSTINGS)
    run = Search(g, [QUERY], "two_phase")
    first = waves.origins(g.postings, run.query)
    result = run.run()
    assert worsened(first, result.labels).isEmpty() and missing_roots(result.labels, result.answers).isEmpty()
    assert bounds_fall(result.trace) and rounds_bounded(result.trace, QUERY.tau)


def test_tree_paths_and_weight(spark):
    g = make(spark, W1_EDGES, W1_POSTINGS)
    r = search(g, QUERY)
    tree = match_tree(g, r.answers, r.labels, r.query, 4)
    paths = {(x.root, x.kw): x.path for x in explain_match(tree, g).collect()}
    assert paths == {(2, "a"): "2 > 4", (2, "b"): "2 > 5", (21, "a"): "21 > 31 > 4", (21, "b"): "21 > 5"}
    assert {x.root: x.weight for x in steiner_weight(tree, r.answers).collect()} == {2: 4, 21: 7}


def test_files_round_trip(spark, tmp_path):
    g = make(spark, W1_EDGES, W1_POSTINGS)
    save_graph(g, str(tmp_path / "store"), 3)
    back = load_graph(spark, str(tmp_path / "store"))
    assert sorted(map(tuple, back.edges.collect())) == sorted(W1_EDGES) and back.postings.count() == 6
    (tmp_path / "e.tsv").write_text("1\t2\t3\n1\t2\t1\n2\t2\t9\n")
    (tmp_path / "p.tsv").write_text(" Word \t2\n\t1\n")
    g = load_edge_list(spark, str(tmp_path / "e.tsv"), postings=str(tmp_path / "p.tsv"), separator="\t")
    assert [tuple(r) for r in g.edges.collect()] == [(1, 2, 1)] and [tuple(r) for r in g.postings.collect()] == [("word", 2)]
    (tmp_path / "t.nt").write_text('<x> <knows> <y> .\n<y> <name> "Ann Lee" .\n# nothing\n')
    g = load_triples(spark, str(tmp_path / "t.nt"))
    assert g.edges.count() == 1 and sorted(r.kw for r in g.postings.collect()) == ["ann", "lee"] and g.vertices.count() == 2


def test_straggler_ratio():
    assert straggler_ratio([{"pops": {0: 3, 1: 1}}, {"pops": {0: 0, 1: 0}}]) == 1.5


def _plan(df):
    return df._jdf.queryExecution().executedPlan().toString() + df._jdf.queryExecution().optimizedPlan().toString()


def test_rounds_read_the_held_edges_and_limit_ranks(spark, tmp_path):
    """No round goes back to the source tables, the edges aren't moved again, and ranks are cut before they are moved."""
    edges = spark.createDataFrame(W1_EDGES, "src long, dst long, w long")
    edges.write.parquet(str(tmp_path / "source"))
    g = make(spark, W1_EDGES, W1_POSTINGS)
    g = Graph(g.vertices, spark.read.parquet(str(tmp_path / "source")), g.postings)
    run = Search(g, [QUERY], "two_phase")
    held = run._held_edges("dst")
    start = run._keep(waves.origins(g.postings, run.query).withColumn("done", F.lit(None).cast("long"))).select(*waves.KEY, "p")
    files = waves.relax(start, held, run._limits()).inputFiles()
    assert files and not any("/source" in f for f in files)
    assert "WindowGroupLimit" in _plan(run.run().answers)


def test_hubs_are_split(spark):
    edges = spark.createDataFrame([(i, 0, 1) for i in range(1, 41)] + [(0, 50, 1), (1, 50, 1)], "src long, dst long, w long")
    hub = waves.hubs(edges, 10)
    assert [tuple(r) for r in hub.collect()] == [(0, 4)]
    split = waves.split_edges(edges, hub)
    assert split.filter("dst = 0").select("part").distinct().count() == 4 and split.filter("dst = 50 AND part <> 0").isEmpty()
    front = spark.createDataFrame([(0, 0, 0, 0), (0, 0, 50, 50)], "qid int, kid int, vid long, p long")
    limits = spark.createDataFrame([(0, 3)], "qid int, cap long")
    got, want = (sorted(map(tuple, x.collect())) for x in (waves.relax_split(front, split, hub, limits), waves.relax(front, edges, limits)))
    assert got == want and len(got) == 42
