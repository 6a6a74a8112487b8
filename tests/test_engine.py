import math
import random
from dataclasses import replace

import pytest

from graphkw.operators import partition, sketch
from graphkw.operators.bounds import BoundBoard, TopKList, assemble
from graphkw.operators.kernel import Fragment, Output, Task
from graphkw.plans import selector
from graphkw.plans.experiments import growth
from graphkw.plans.program import Subtask, run_program, to_single_task
from graphkw.plans.search import keyword_distances, search, search_batch
from graphkw.reference import brute_force, distances, sequential
from graphkw.schema import Graph, KeywordQuery, merge_edges
from graphkw.streaming.incremental import Continuous

#: Worked example: holders, edges and what must come out.
W1_EDGES = [(2, 4, 2), (2, 5, 2), (1, 6, 4), (1, 7, 4), (3, 5, 1), (31, 4, 4), (21, 31, 1), (21, 5, 2), (22, 7, 2), (22, 8, 8), (4, 32, 2), (6, 32, 2), (8, 32, 2), (9, 32, 2)]
W1_EDGES += [(40 + i, 9, 5) for i in (1, 2, 3)] + [(40 + i, 7, 5) for i in (1, 2, 3)]
W1_POSTINGS = [("a", v) for v in (4, 6, 8, 9)] + [("b", v) for v in (5, 7)]


def make(spark, edges, postings, vertices=()):
    ids = sorted({v for e in edges for v in e[:2]} | {v for _, v in postings} | set(vertices))
    return Graph(spark.createDataFrame([(v, "node") for v in ids], "vid long, kind string"), spark.createDataFrame(edges, "src long, dst long, w long"), spark.createDataFrame(postings, "kw string, vid long"))


def drawn(seed):
    draw = random.Random(seed)
    n = draw.randint(5, 40)
    edges = {}
    for _ in range(draw.randint(n, 4 * n)):
        u, v = draw.randrange(n), draw.randrange(n)
        if u != v:
            edges[u, v] = draw.randint(1, draw.choice([1, 3, 9]))
    q = draw.randint(1, 4)
    postings = [(f"k{i}", v) for i in range(q) for v in draw.sample(range(n), draw.randint(1, 4))]
    return [(u, v, w) for (u, v), w in edges.items()], postings, KeywordQuery(tuple(f"k{i}" for i in range(q)), draw.randint(0, 12), draw.randint(1, 6))


def test_worked_example_scores():
    query = KeywordQuery(("a", "b"), 6, 10)
    assert brute_force(W1_EDGES, W1_POSTINGS, query) == [(2, 4), (21, 7), (1, 8), (41, 10), (42, 10), (43, 10)]
    assert sequential(W1_EDGES, W1_POSTINGS, KeywordQuery(("a", "b"), 6, 2))[0] == [(2, 4), (21, 7)]
    assert distances(W1_EDGES, [4, 6, 8, 9], 6)[31] == 4


@pytest.mark.parametrize("seed", range(400))
def test_sequential_equals_brute_force(seed):
    edges, postings, query = drawn(seed)
    assert sequential(edges, postings, query)[0] == brute_force(edges, postings, query)


def test_queries_are_normalised():
    assert KeywordQuery((" A ", "a", "b")).keywords == ("a", "b")
    for bad in (dict(keywords=()), dict(keywords=("a",), tau=-1), dict(keywords=("a",), k=0)):
        with pytest.raises(ValueError):
            KeywordQuery(**bad)


def test_list_and_assemble():
    top = TopKList(2)
    assert top.bound == math.inf and top.offer(1, 9) and top.bound == math.inf
    assert top.offer(1, 5) and len(top.best) == 1  # a root fills one slot
    assert top.offer(2, 7) and top.bound == 7
    assert not top.offer(3, 8) and top.offer(3, 6) and top.rows() == [(1, 5), (3, 6)]
    assert not top.offer(9, 6) and top.offer(2, 6) and top.rows() == [(1, 5), (2, 6)]  # ties: the smaller root
    lists = [[(15, 4), (17, 3)], [(11, 4), (6, 4)], [(4, 2), (5, 5)]]
    assert assemble(lists, 2) == [(4, 2), (17, 3)]


def test_board_bounds_and_counters():
    lists = [[(17, 3), (15, 4)], [(6, 4), (11, 4)], [(4, 2), (5, 5)]]
    for mode, want in (("min", 4), ("union", 3)):
        board = BoundBoard(3, 2, mode=mode)
        for i, rows in enumerate(lists):
            board.report(i, rows[-1][1], rows)
            assert all(board.bound <= s for s in board.local.values())
        assert board.bound == want and board.trace == sorted(board.trace, reverse=True)
    board = BoundBoard(3, 2, threshold=2)
    board.local, board.counter = {0: 4, 1: 6, 2: 5}, {0: 3, 1: 0, 2: 3}
    assert board.lagging() == [1]
    board.threshold = 3
    assert board.lagging() == []
    assert board.push(1) == 4 and board.local[1] == 4
    with pytest.raises(ValueError):
        BoundBoard(2, 1, mode="max")


def test_selector_rules():
    assert selector.backward_budget(3, 7, 4) == 4 and selector.backward_budget(3, 6, 4) == 3
    assert selector.indicator([]) == math.inf and selector.indicator([4, 2]) == 3
    assert selector.preemptive(4, 2, 1) == "f" and selector.preemptive(2, 4, 1) == "b" and selector.preemptive(2, 2, 1) == "f"
    assert selector.preemptive(math.inf, math.inf, 1) == "idle"
    assert [selector.alternate(1, 1, s) for s in (1, 2, 3)] == ["b", "f", "b"]
    assert selector.backward_first(9, 1, 1) == "b" and selector.forward_first(1, 9, 1) == "f"
    names = lambda t: Subtask(t, (t,), lambda w: w.append(f"{t} partial"), lambda w: w.append(f"{t} incremental"))
    program, done = to_single_task((names("b"), names("f"))), []
    for kind in (selector.PARTIAL, "f", "b"):
        program(kind, done)
    assert done == ["b partial", "f partial", "f incremental", "b incremental"]


def test_kernel_ships_borders_and_demands():
    f = Fragment(0, 1, 5, 5, [(1, 2, 2, 0, 1), (3, 1, 1, 0, 0), (9, 1, 1, 1, 0)], [], [])
    out = Output()
    f.backward(Task("b", math.inf, (0,)), [(0, 0, 2, 2)], out)
    assert f.label[1, 0] == (2, 2) and f.label[3, 0] == (3, 2) and out.to_copies == [(1, 2, 0, 1, 2)]
    g, out = Fragment(0, 1, 5, 5, [(1, 2, 2, 0, 1)], [], []), Output()
    g.forward(Task("f", math.inf, (-1,)), [(1, 0, 3), (1, 0, 1)], {}, out, False)
    assert out.to_owners == [(1, 2, 0, 1)] and out.served[0] == (1, 0, 3)
    again = Output()
    g.forward(Task("f", math.inf, (-1,)), [(1, 0, 2)], {(1, 0): 3}, again, False)
    assert again.to_owners == []  # a smaller budget is not served again


@pytest.mark.parametrize("variant", ["exhaustive", "two_phase", "sketch"])
def test_relational_search(spark, variant):
    for seed in (1, 5):
        edges, postings, query = drawn(seed)
        g = make(spark, edges, postings)
        index = sketch.Index.build(g, 4, 12, iterations=2) if variant == "sketch" else None
        got = search(g, query, variant, index=index)
        assert [(r.root, r.score) for r in got.answers.orderBy("rank").collect()] == brute_force(edges, postings, query)


def test_batch_and_result_forms(spark):
    g = make(spark, W1_EDGES, W1_POSTINGS)
    queries = [KeywordQuery(("a", "b"), 6, 2, 0), KeywordQuery(("a",), 6, 3, 1), KeywordQuery(("a", "nobody"), 6, 3, 2)]
    r = search_batch(g, queries, "two_phase", delta=2)
    rows = sorted((x.qid, x.rank, x.root, x.score) for x in r.answers.collect())
    assert rows == [(0, 1, 2, 4), (0, 2, 21, 7), (1, 1, 4, 0), (1, 2, 6, 0), (1, 3, 8, 0)]
    maps = {x.root: x.dists for x in r.maps().filter("qid = 0").collect()}
    assert maps[2]["a"].leaf == 4 and maps[21]["b"].dist == 2
    assert {(x.kw, x.vid): x.d for x in keyword_distances(g, queries[0]).collect()}["a", 21] == 5
    with pytest.raises(ValueError):
        search(g, queries[0], "fastest")


def test_stop_counter_example(spark):
    """A root reached by its keywords through different fragments, each stopped by the other's far frontier."""
    names = {n: i for i, n in enumerate(["a0", "m", "x1", "x2", "y", "b0", "n", "z1", "z2", "yy", "u"])}
    text = "m-a0 10, x1-a0 1, x2-x1 1, u-x2 1, y-m 10, n-b0 10, z1-b0 1, z2-z1 1, u-z2 1, yy-n 10"
    edges = [(names[p.split("-")[0]], names[p.split("-")[1].split()[0]], int(p.split()[1])) for p in text.split(", ")]
    postings = [("a", names["a0"]), ("a", names["n"]), ("b", names["b0"]), ("b", names["m"])]
    query = KeywordQuery(("a", "b"), 20, 1)
    g = make(spark, edges, postings)
    frags = [(v, 2 if n == "u" else 0 if n in ("a0", "m", "x1", "x2", "y") else 1) for n, v in names.items()]
    g = Graph(g.vertices, g.edges, g.postings, spark.createDataFrame(frags, "vid long, frag int"))
    assert run_program(g, query, "exchange", m=3).answers == [(names["u"], 6)]
    assert [(r.root, r.score) for r in search(g, query).answers.collect()] == [(names["u"], 6)]


@pytest.mark.parametrize("variant", ["two_phase", "exchange", "preemptive"])
def test_program_equals_brute_force(spark, variant):
    edges, postings, query = drawn(11)
    run = run_program(make(spark, edges, postings), query, variant, m=3, micro=8)
    assert run.answers == brute_force(edges, postings, query)
    assert run.parts > len(run.steps) if variant != "two_phase" else run.parts == len(run.steps)
    assert (sum(run.steps[0]["ahead"].values()) > 0) == (variant == "preemptive")


def test_a_large_fragment_is_dealt_into_cells(spark):
    edges, postings, query = drawn(11)
    g = make(spark, edges, postings)
    whole, dealt = (run_program(g, query, "two_phase", m=2, cell_edges=c) for c in (1 << 18, 12))
    assert dealt.answers == whole.answers == brute_force(edges, postings, query)
    # A superstep takes several jobs where cells of a fragment read each other's rows.
    assert whole.parts == len(whole.steps) and dealt.parts > len(dealt.steps)


def test_a_bound_moves_within_a_superstep():
    """A fragment that pauses goes on with the other's better bound and leaves what that bound rules out."""
    chain = [(i + 1, i, 1, 0, 0) for i in range(30)]
    f, out = Fragment(0, 1, 30, 5, chain, [], []), Output()
    f.backward(Task("b", math.inf, (0,), micro=3), [(0, 0, 0, 0)], out)
    assert out.stopped and out.pops == 3 and out.left
    rest = Output()
    f.backward(Task("b", 4, (0,), micro=100), out.left, rest)
    alone = Output()
    Fragment(0, 1, 30, 50, chain, [], []).backward(Task("b", math.inf, (0,)), [(0, 0, 0, 0)], alone)
    assert not rest.stopped and out.pops + rest.pops < alone.pops


def test_border_rules_out_searches_that_stay_inside():
    f = Fragment(0, 2, 3, 5, [(1, 2, 2, 0, 0), (2, 3, 2, 0, 1)], [(1, 0, 0, 1)], [])
    free, bound = Task("f", math.inf, (9, 0)), Task("f", math.inf, (9, 0), border=True)
    assert f.border() == {3: 0, 2: 2}
    assert f.roots(free, math.inf) == [(1, 1, 3)] and f.roots(bound, math.inf) == []
    assert f.roots(bound, math.inf, [(2, 1, 2, 2)]) == [(1, 1, 3)]  # its own frontier may still reach it


def test_lower_bounds_hold_and_the_printed_one_fails(spark):
    edges, postings = [(1, 2, 1), (1, 9, 10), (3, 9, 2), (2, 9, 9)], [("a", 2), ("a", 3)]
    g = make(spark, edges, postings)
    centres = spark.createDataFrame([(9, 9)], "key long, vid long")
    out, inward = sketch.landmarks(g, centres, 20)
    ko, ki = sketch.keyword_sketch(out, g.postings), sketch.keyword_sketch(inward, g.postings)
    one = {r.vid: r.lb for r in sketch.lower_bound_out(out, ko, g.postings).collect()}
    printed = {r.vid: r.lb for r in sketch.lower_bound_as_printed(out, ko).collect()}
    true = distances(edges, [2, 3])
    assert one[1] == 1 == true[1] and printed[1] == 8
    assert all(r.lb <= true.get(r.vid, math.inf) for r in sketch.lower_bound_in(inward, ki).collect())
    assert all(r.ub >= true[r.vid] for r in sketch.upper_bound(out, ki).collect())


def test_partitioners_own_each_vertex_once(spark):
    edges, postings, _ = drawn(3)
    g = make(spark, edges, postings)
    for how in ("hash", "range", "by_kind", "balanced_lp", "greedy_stream"):
        p = partition.partition(g, 3, how)
        assert p.frags.count() == p.frags.select("vid").distinct().count() == p.frags.filter("frag BETWEEN 0 AND 2").count()
    with pytest.raises(ValueError):
        partition.partition(g, 3, "best")


def test_edges_are_merged_and_checked(spark):
    rows = merge_edges(spark.createDataFrame([(1, 2, 3), (1, 2, 1), (2, 2, 1)], "src long, dst long, w long")).collect()
    assert [tuple(r) for r in rows] == [(1, 2, 1)]
    with pytest.raises(Exception, match="not positive"):
        merge_edges(spark.createDataFrame([(1, 2, 0)], "src long, dst long, w long")).collect()


def test_insertions_equal_a_new_search(spark):
    edges, postings, query = drawn(21)
    half = len(edges) // 2
    standing = Continuous.start(make(spark, edges[:half], postings, range(40)), query)
    standing.insert(spark.createDataFrame(edges[half:], "src long, dst long, w long"))
    got = [(r.root, r.score) for r in standing.answers().orderBy("rank").collect()]
    assert got == brute_force(edges, postings, query)


def test_exhaustive_baseline_ships_every_complete_match(spark):
    for seed in (2, 3):
        edges, postings, query = drawn(seed)
        g = make(spark, edges, postings)
        base, ours = (run_program(g, query, v, m=3) for v in ("exhaustive", "two_phase"))
        assert base.answers == ours.answers == brute_force(edges, postings, query)
        assert base.message_bytes >= len(brute_force(edges, postings, replace(query, k=10**6))) * (16 + 16 * len(query.keywords))


def test_growth_of_a_sweep():
    rows = [("by_k", v, "", 1, s) for v, s in (("a", 2.0), ("b", 1.0), ("a", 3.0), ("b", 1.0))]
    assert growth(rows) == {"a": 50.0, "b": 0.0}
