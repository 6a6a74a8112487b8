"""The fragment program's kernel under a plain-Python coordinator, against brute force on random graphs."""

import math
import random
import tracemalloc
from collections import defaultdict
from dataclasses import replace

import numpy as np
import pandas as pd
import pytest

from graphkw.operators.bounds import BoundBoard, assemble
from graphkw.operators.kernel import Fragment, Output, Task
from graphkw.plans import selector
from graphkw.plans.program import _step
from graphkw.reference import brute_force
from graphkw.schema import KeywordQuery

COLUMNS = ["tag", "frag", "a", "b", "c", "d"]
ARRIVED = {"msg_b": "pending", "msg_a": "answer", "msg_d": "demand"}


def simulate(edges, postings, query, m, choose, exchange=True, threshold=2, micro=1 << 30, border=False, partial=False, seen=None):
    """One run with all state in memory; returns the answers and the trace of the global bound."""
    n, frag_of = len(query.keywords), lambda v: (v * 7919) % m
    own = {f: [] for f in range(m)}
    for u, v, w in edges:
        for f in {frag_of(u), frag_of(v)}:
            own[f].append((f, u, v, w, frag_of(u), frag_of(v)))
    state = set()
    for kw, v in postings:
        q = query.keywords.index(kw)
        state.add(("pending", frag_of(v), 0, q, v, v))
        state |= {("pending", frag_of(u), 0, q, v, v) for u, x, _ in edges if x == v and frag_of(u) != frag_of(v)}
    state, board, known, quiet = list(state), BoundBoard(m, query.k, threshold), dict.fromkeys(range(m), math.inf), False
    settled = False
    for step in range(1, 300):
        minima = [min((a for t, _, a, b, _, _ in state if t == "pending" and b == q), default=math.inf) for q in range(n)]
        final = sum(minima) > board.bound or min(minima) > min(query.tau, board.bound)
        tasks = {}
        for f in range(m):
            back = [a for t, g, a, *_ in state if g == f and (t == "answer" or t == "pending" and not final)]
            dem = [c for t, g, _, _, c, _ in state if g == f and t == "demand"]
            bound = min(known[f], board.local[f])
            sb = selector.indicator([selector.backward_budget(a, bound, query.tau) for a in back])
            kind = selector.PARTIAL if partial and step == 1 else choose(sb, selector.indicator([selector.forward_budget(c, query.tau) for c in dem]), step)
            tasks[f] = Task(kind, bound, tuple(minima), not exchange and step > 1, not final, micro, border)
        if all(t.kind == selector.IDLE for t in tasks.values()):
            if quiet:
                return assemble(board.lists.values(), query.k), board.trace
            tasks = {f: Task(selector.FORWARD, min(board.bound, known[f], board.local[f]), tuple(minima), micro=micro, border=border) for f in tasks}
            quiet = True
            if not settled:
                state, settled = [r for r in state if r[0] != "served"], True
        out = state
        while any(t.kind != selector.IDLE for t in tasks.values()):
            run, held, out = _step(n, query.tau, query.k, tasks), out, []
            for f in range(m):
                rows, graph = pd.DataFrame([r for r in held if r[1] == f], columns=COLUMNS), pd.DataFrame(own[f], columns=["frag", "src", "dst", "w", "src_frag", "dst_frag"])
                if len(rows) or len(graph):
                    out += run(graph, rows).itertuples(index=False, name=None)
            lists, paused = defaultdict(list), {f for t, f, _, _, c, _ in out if t == "metric" and c}
            if seen is not None:
                seen += [(step, a, b) for t, _, a, b, _, _ in out if t == "metric"]
            for t, f, a, b, _, _ in out:
                if t == "list":
                    lists[f].append((a, b))
            for f, found in lists.items():
                found.sort(key=lambda x: (x[1], x[0]))
                board.report(f, found[-1][1] if len(found) == query.k else math.inf, found)
            if exchange:
                for f in board.lagging():
                    known[f] = min(known[f], board.push(f))
            tasks = {f: replace(t, bound=min(t.bound, known[f], board.local[f])) if f in paused else replace(t, kind=selector.IDLE) for f, t in tasks.items()}
            out = [r for r in out if r[0] not in ("list", "metric")]
        messages = any(r[0] in ARRIVED for r in out)
        quiet = quiet and not messages
        state = [(ARRIVED.get(r[0], r[0]), *r[1:]) for r in out]
    raise AssertionError("no end")


@pytest.mark.parametrize("seed", range(14))
def test_every_order_gives_the_exact_answers(seed):
    draw = random.Random(seed)
    n, edges = draw.randint(5, 40), {}
    for _ in range(draw.randint(n, 4 * n)):
        u, v = draw.randrange(n), draw.randrange(n)
        if u != v:
            edges[u, v] = draw.randint(1, draw.choice([1, 3, 9]))
    q = draw.randint(1, 4)
    postings = [(f"k{i}", v) for i in range(q) for v in draw.sample(range(n), draw.randint(1, 5))]
    edges = [(u, v, w) for (u, v), w in edges.items()]
    query = KeywordQuery(tuple(f"k{i}" for i in range(q)), draw.randint(0, 12), draw.randint(1, 6))
    want = brute_force(edges, postings, query)
    for choose, exchange in ((selector.backward_first, False), (selector.preemptive, True), (selector.alternate, False), (selector.forward_first, True)):
        got, trace = simulate(edges, postings, query, draw.choice([1, 2, 3, 5]), choose, exchange)
        assert got == want, choose.__name__
        assert trace == sorted(trace, reverse=True)


@pytest.mark.parametrize("seed", range(40))
def test_pauses_borders_and_partial_steps_keep_answers_exact(seed):
    draw = random.Random(100 + seed)
    n, edges = draw.randint(5, 40), {}
    for _ in range(draw.randint(n, 4 * n)):
        u, v = draw.randrange(n), draw.randrange(n)
        if u != v:
            edges[u, v] = draw.randint(1, draw.choice([1, 3, 9]))
    q = draw.randint(1, 4)
    postings = [(f"k{i}", v) for i in range(q) for v in draw.sample(range(n), draw.randint(1, 5))]
    edges = [(u, v, w) for (u, v), w in edges.items()]
    query = KeywordQuery(tuple(f"k{i}" for i in range(q)), draw.randint(0, 12), draw.randint(1, 6))
    want = brute_force(edges, postings, query)
    for choose in (selector.backward_first, selector.preemptive, selector.alternate, selector.forward_first):
        for partial in (False, True):
            got, trace = simulate(edges, postings, query, draw.choice([1, 2, 3, 5]), choose, True, draw.choice([0, 2]), draw.choice([1, 3, 10]), draw.random() < 0.7, partial)
            assert got == want, (choose.__name__, partial)
            assert trace == sorted(trace, reverse=True)


def simulate_cells(edges, postings, query, m, cells, choose, exchange=True, threshold=2, micro=1 << 30, border=False, partial=False):
    """The same with every fragment dealt into cells; the superstep goes on until a fragment's cells have read each other's rows."""
    n, cell_of = len(query.keywords), lambda v: (v * 7919) % m * cells + (v * 31 + 7) % 101 % cells
    own = defaultdict(list)
    for u, v, w in edges:
        for c in {cell_of(u), cell_of(v)}:
            own[c].append((c, u, v, w, cell_of(u), cell_of(v)))
    state = set()
    for kw, v in postings:
        q = query.keywords.index(kw)
        state |= {("pending", c, 0, q, v, v) for c in {cell_of(v)} | {cell_of(u) for u, x, _ in edges if x == v}}
    state, board, known, quiet, settled, lists = list(state), BoundBoard(m, query.k, threshold), dict.fromkeys(range(m), math.inf), False, False, {}
    for step in range(1, 300):
        minima = [min((a for t, _, a, b, _, _ in state if t == "pending" and b == q), default=math.inf) for q in range(n)]
        final = sum(minima) > board.bound or min(minima) > min(query.tau, board.bound)
        tasks = {}
        for f in range(m):
            back = [a for t, g, a, *_ in state if g // cells == f and (t == "answer" or t == "pending" and not final)]
            dem = [c for t, g, _, _, c, _ in state if g // cells == f and t == "demand"]
            bound = min(known[f], board.local[f])
            sb = selector.indicator([selector.backward_budget(a, bound, query.tau) for a in back])
            kind = selector.PARTIAL if partial and step == 1 else choose(sb, selector.indicator([selector.forward_budget(c, query.tau) for c in dem]), step)
            tasks[f] = Task(kind, bound, tuple(minima), not exchange and step > 1, not final, micro, border)
        if all(t.kind == selector.IDLE for t in tasks.values()):
            if quiet:
                return assemble(board.lists.values(), query.k), board.trace
            tasks = {f: Task(selector.FORWARD, min(board.bound, known[f], board.local[f]), tuple(minima), micro=micro, border=border) for f in tasks}
            quiet = True
            if not settled:
                state, settled = [r for r in state if r[0] != "served"], True
        active, out, inside = {c: tasks[c // cells] for c in range(m * cells)}, state, False
        while any(t.kind != selector.IDLE for t in active.values()):
            run, held, out = _step(n, query.tau, query.k, active, cells=cells), out, []
            for c in range(m * cells):
                rows, graph = pd.DataFrame([r for r in held if r[1] == c], columns=COLUMNS), pd.DataFrame(own[c], columns=["frag", "src", "dst", "w", "src_frag", "dst_frag"])
                if len(rows) or len(graph):
                    out += run(graph, rows).itertuples(index=False, name=None)
            on, found = {c for t, c, _, _, p, _ in out if t == "metric" and p}, defaultdict(list)
            for t, c, a, b, _, _ in out:
                if t == "list":
                    found[c].append((a, b))
                if t == "woken":
                    inside = True
                    if tasks[c // cells].kind in (selector.PARTIAL, selector.FORWARD if a else selector.BACKWARD):
                        on.add(c)
            lists |= found
            for f in sorted({c // cells for c in found}):
                best = assemble((lists.get(c, ()) for c in range(f * cells, (f + 1) * cells)), query.k)
                board.report(f, best[-1][1] if len(best) == query.k else math.inf, best)
            if exchange:
                for f in board.lagging():
                    known[f] = min(known[f], board.push(f))
            active = {c: replace(t, kind=tasks[c // cells].kind if c in on else selector.IDLE, bound=min(t.bound, known[c // cells], board.local[c // cells])) for c, t in active.items()}
            out = [r for r in out if r[0] not in ("list", "metric", "woken")]
        quiet = quiet and not inside and not any(r[0] in ARRIVED for r in out)
        state = [(ARRIVED.get(r[0], r[0]), *r[1:]) for r in out]
    raise AssertionError("no end")


@pytest.mark.parametrize("seed", range(10))
def test_cells_of_a_fragment_keep_answers_exact(seed):
    draw = random.Random(700 + seed)
    n, edges = draw.randint(5, 40), {}
    for _ in range(draw.randint(n, 4 * n)):
        u, v = draw.randrange(n), draw.randrange(n)
        if u != v:
            edges[u, v] = draw.randint(1, draw.choice([1, 3, 9]))
    q = draw.randint(1, 4)
    postings = [(f"k{i}", v) for i in range(q) for v in draw.sample(range(n), draw.randint(1, 5))]
    edges = [(u, v, w) for (u, v), w in edges.items()]
    query = KeywordQuery(tuple(f"k{i}" for i in range(q)), draw.randint(0, 12), draw.randint(1, 6))
    want = brute_force(edges, postings, query)
    for choose in (selector.backward_first, selector.preemptive, selector.alternate, selector.forward_first):
        for exchange in (False, True):
            m, cells, micro = draw.choice([1, 2, 3]), draw.choice([2, 3, 5]), draw.choice([1, 3, 10]) if exchange else 1 << 30
            got, trace = simulate_cells(edges, postings, query, m, cells, choose, exchange, draw.choice([0, 2]), micro, exchange and draw.random() < 0.7, exchange and draw.random() < 0.5)
            assert got == want, (choose.__name__, exchange)
            assert trace == sorted(trace, reverse=True)


def test_demands_of_a_keyword_share_one_search():
    """Many roots before one hub: each vertex is met once for all of them, not once for each."""
    n, hub = 300, 10_000
    edges = [(i, hub, 1, 0, 0) for i in range(n)] + [(hub, 20_000 + i, 1, 0, 0) for i in range(n)] + [(20_000, 30_000, 1, 0, 1)]
    f, out = Fragment(0, 1, 3, 5, edges, [(20_001, 0, 0, 20_001)], []), Output()
    f.forward(Task("f", math.inf, (-1,)), [(i, 0, 3) for i in range(n)], {}, out, False)
    assert {f.label[i, 0] for i in range(n)} == {(2, 20_001)}
    assert list(out.to_owners) == [(1, 30_000, 0, 0)]
    assert out.pops <= len(f.ids)


def test_a_fragment_of_many_edges_is_held_in_arrays():
    """A million edges, of which no Python object is made: under 100 bytes an edge at the most."""
    n = 1_000_000
    columns = tuple(np.asarray(x) for x in (np.arange(1, n + 1), np.arange(n), np.ones(n, int), np.zeros(n, int), np.zeros(n, int)))
    tracemalloc.start()
    f = Fragment(0, 1, 3, 5, columns, [], [])
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert len(f.ids) == n + 1 and most < 100 * n
