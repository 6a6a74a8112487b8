from graphkw import queries
from graphkw.operators import sketch
from graphkw.operators.reach import spread


def test_lower_bounds_spread_in_one_direction_only(spark, monkeypatch):
    seen = []
    monkeypatch.setattr(sketch, "spread", lambda *a, **k: seen.append(k) or spread(*a, **k))
    for name in ("sketch_lower_lb1", "sketch_lower_lb2"):
        assert queries.QUERIES[name](spark, "/root/testdata/sf0.001").count()
    assert len(seen) == 2


def test_bounds_that_meet_no_distance_are_not_made(spark, monkeypatch):
    seen = set()
    made = sketch.keyword_sketch
    monkeypatch.setattr(sketch, "keyword_sketch", lambda out, postings: seen.update(r["kw"] for r in postings.select("kw").distinct().collect()) or made(out, postings))
    assert {r["form"]: r["n_wrong"] > 0 for r in queries.QUERIES["lb_violation_rate"](spark, "/root/testdata/sf0.001").collect()} == {"lb1": False, "lb2": False, "as_printed": True}
    assert seen == set(queries.Q4)
