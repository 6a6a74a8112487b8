from graphkw import queries
from graphkw.operators.reach import spread

EDGES = [(1, 2, 1), (2, 3, 2), (3, 4, 1), (1, 4, 9), (5, 2, 1)]


def test_spread_from_seeds_with_their_own_start(spark):
    edges = spark.createDataFrame(EDGES, "src long, dst long, w long")
    seeds = spark.createDataFrame([(0, 1, 2), (0, 2, 0), (0, 2, 5), (1, 5, 4), (1, 4, 9)], "key long, vid long, d long")
    ahead = {tuple(r) for r in spread(edges, seeds, 6, backwards=False).collect()}
    assert ahead == {(0, 1, 2), (0, 2, 0), (0, 3, 2), (0, 4, 3), (1, 5, 4), (1, 2, 5)}
    assert {tuple(r) for r in spread(edges, seeds.select("key", "vid"), 2).collect()} == {(0, 1, 0), (0, 2, 0), (0, 5, 1), (1, 5, 0), (1, 4, 0), (1, 3, 1)}
    assert not spread(edges, seeds.filter("d > 6"), 6).count()


def test_step1_queries_spread_once_per_direction(spark, monkeypatch):
    seen = []
    monkeypatch.setattr(queries, "spread", lambda *a, **k: seen.append(k) or spread(*a, **k))
    assert queries.QUERIES["selector_step1"](spark, "/root/testdata/sf0.001").count()
    assert len(seen) == 2
