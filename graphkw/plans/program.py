"""The multi-task program over fragments: supersteps, buffers, bound exchange, selector, assemble.

Each superstep is one cogrouped job: a fragment's edges meet its state rows, the
kernel runs the task chosen for it, and returns new state, messages and its k best.
State stays in the shared folder; the driver holds k rows and a few numbers per
cell. Whenever fragments pause the coordinator updates its board and pushes bounds.

A large fragment is dealt into cells by its vertices, and a cell's edges and state are
all that a Python worker holds. Rows that one cell of a fragment has for another go
straight to its buffers; the superstep goes on until the fragment's cells have read
them all. Only what leaves the fragment is a message.
"""

from __future__ import annotations

import math
import time
from collections.abc import Callable, Sequence
from dataclasses import dataclass, field, replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphkw.operators.bounds import BoundBoard, assemble
from graphkw.operators.kernel import Fragment, Output, Rows, Task
from graphkw.operators.partition import framed_edges, hold
from graphkw.plans.selector import BACKWARD, FORWARD, IDLE, PARTIAL, SELECTORS, backward_budget, forward_budget, indicator
from graphkw.schema import Graph, KeywordQuery, query_frame
from graphkw.storage import Bucketed, Snapshot

#: Fixed widths of messages, as the accounting counts them.
MATCH_BYTES, DEMAND_BYTES, BOUND_BYTES = 28, 20, 12
#: A list of no bound: the baseline's.
EVERY = 1 << 60
#: The edges, about, that leave the vertices of one cell.
CELL_EDGES = 1 << 18
#: What a row for another cell of the fragment becomes there, and whether a backward (0) or a forward step (1) reads it.
NEAR = {"msg_b": ("pending", 0), "msg_a": ("answer", 0), "msg_d": ("demand", 1)}
#: Messages that were sent in this superstep and arrive in the next.
ON_THE_WAY = ("msg_b", "msg_a", "msg_d")
ROWS = "tag string, frag int, a long, b long, c long, d long"


@dataclass
class Run:
    """Answers and counters of one run."""

    answers: list[tuple[int, int]]
    steps: list[dict] = field(default_factory=list)
    message_bytes: int = 0
    messages: int = 0
    visited: int = 0
    pops: int = 0
    notified: int = 0
    pushed: int = 0
    ahead_pops: int = 0
    forward_roots: int = 0
    parts: int = 0
    seconds: float = 0.0
    bounds: list[float] = field(default_factory=list)

    def frame(self, spark) -> DataFrame:
        return spark.createDataFrame([(0, i + 1, r, s) for i, (r, s) in enumerate(self.answers)], "qid int, rank int, root long, score long")


#: name: (sketches, exchange, selector). ``exhaustive`` is the distributed baseline: no bound at all, every complete match
#: within tau goes to the coordinator, which verifies them and takes the k best.
LADDER = {
    "exhaustive": (False, False, "backward_first"),
    "two_phase": (False, False, "backward_first"),
    "sketch": (True, False, "backward_first"),
    "exchange": (True, True, "backward_first"),
    "preemptive": (True, True, "preemptive"),
    "single_task": (False, False, "alternate"),
}


@dataclass
class Work:
    """A fragment's buffers and what its subtasks make of them in one superstep (or a part of one)."""

    fragment: Fragment
    task: Task
    pending: Rows
    answers: Rows
    demands: Rows
    served: Rows
    #: What the wave passes on, and what answers and searches ahead pass on.
    wave: Output = field(default_factory=Output)
    back: Output = field(default_factory=Output)


@dataclass(frozen=True)
class Subtask:
    """One task of the program: the tags of its message buffers, its step in the first superstep and its step in later ones."""

    name: str
    buffers: tuple[str, ...]
    partial: Callable[[Work], None]
    incremental: Callable[[Work], None]


def _spread(work: Work) -> None:
    # Answers to demands flow back whether or not the wave has ended.
    if work.answers:
        work.fragment.backward(replace(work.task, force=True), work.answers, work.back)
        work.answers = Rows()
    if work.task.wave:
        work.fragment.backward(work.task, work.pending, work.wave)
        work.pending = work.wave.left
        work.wave.left = Rows()
    best = work.wave if work.task.wave else work.back
    work.wave.answers = best.answers


def _ahead(work: Work, missing: bool = False) -> None:
    f, out = work.fragment, Output()
    f.forward(work.task, work.demands, work.served, out, True, work.pending, missing)
    work.demands, work.wave.answers = out.demands_left, out.answers
    work.served = out.served
    back = work.back
    back.left, back.to_copies, back.to_owners = back.left + out.left, back.to_copies + out.to_copies, back.to_owners + out.to_owners
    back.pops, back.refined, back.roots, back.skipped = back.pops + out.pops, back.refined + out.refined, back.roots + out.roots, back.skipped + out.skipped
    back.ahead += out.ahead
    back.stopped |= out.stopped


def _first_ahead(work: Work) -> None:
    """Searches from partial roots for what they lack altogether, as soon as this fragment's own wave has ended."""
    if not (work.wave.stopped or work.back.stopped):
        _ahead(work, missing=True)


SUBTASKS = (Subtask(BACKWARD, ("pending", "answer"), _spread, _spread), Subtask(FORWARD, ("demand",), _first_ahead, _ahead))


def to_single_task(subtasks: Sequence[Subtask] = SUBTASKS) -> Callable[[str, Work], None]:
    """Compiles subtasks into one function of the chosen task: all partial steps in order, or one incremental step."""
    partial, later = [t.partial for t in subtasks], {t.name: t.incremental for t in subtasks}

    def perform(kind: str, work: Work) -> None:
        for step in partial if kind == PARTIAL else [later[kind]]:
            step(work)

    return perform


def _step(n: int, tau: int, k: int, tasks: dict[int, Task], subtasks: Sequence[Subtask] = SUBTASKS, cells: int = 1):
    """The kernel as a cogrouped function; rows are tagged (see ``ROWS``). Messages on the way pass through untouched.

    Fragments of several cells: ``frag`` and the keys of ``tasks`` are cells, numbered through, ``cells`` to a fragment.
    """

    def run(edges: pd.DataFrame, state: pd.DataFrame) -> pd.DataFrame:
        frag = int(state["frag"].iloc[0] if len(state) else edges["frag"].iloc[0])
        task = tasks.get(frag)
        if task is None or task.kind == IDLE:
            return state[["tag", "frag", "a", "b", "c", "d"]]
        codes, tags = pd.factorize(state["tag"])
        number, rows = {t: i for i, t in enumerate(tags)}, np.stack([state[c].to_numpy(np.int64) for c in "abcd"], axis=1)

        def buffer(tag: str, width: int = 4) -> Rows:
            return Rows(rows[codes == number[tag], :width], width) if tag in number else Rows((), width)

        pending, answers, demands, served = buffer("pending"), buffer("answer"), buffer("demand", 3), buffer("served", 3)
        on_the_way = {t: buffer(t) for t in ON_THE_WAY}
        lower = buffer("lower", 3)
        named = [pending.array[:, 2], answers.array[:, 2], demands.array[:, 0], served.array[:, 0]]
        leaves = np.concatenate([pending.array[:, 3], answers.array[:, 3]])
        f = Fragment(frag, n, tau, k, tuple(edges[c].to_numpy(np.int64) for c in ("src", "dst", "w", "src_frag", "dst_frag")), buffer("label"), (), lower, np.concatenate(named), leaves)
        del rows, codes
        work = Work(f, task, pending, answers, demands, served)
        to_single_task(subtasks)(task.kind, work)
        out, back = work.wave, work.back
        own = [("lower", frag, lower), *((t, frag, r) for t, r in on_the_way.items()), ("label", frag, f.labels()), ("pending", frag, work.pending), ("answer", frag, work.answers + back.left)]
        own += [("demand", frag, work.demands), ("served", frag, work.served)]
        if k < EVERY:
            own.append(("list", frag, Rows(out.answers, 2)))
        own.append(("metric", frag, Rows([(out.pops + back.pops, back.ahead, int(out.stopped or back.stopped), back.roots)])))

        def send(tag: str, to: np.ndarray, rows: Rows) -> None:
            near = to // cells == frag // cells
            own.append((tag, to[~near], Rows(rows.array[~near])))
            if near.any():
                buffer, kind = NEAR[tag]
                own.append((buffer, to[near], Rows(rows.array[near])))
                woken = np.unique(to[near])
                own.append(("woken", woken, Rows.of(np.full(len(woken), kind), 0, 0, 0)))

        # Messages: rows of other fragments, marked as on the way; each once, the best.
        for tag, sent in (("msg_b", out.to_copies), ("msg_a", back.to_copies)):
            to, d, q, v, leaf = sent.array.T
            best = np.lexsort((leaf, d, v, q, to))
            to, d, q, v, leaf = sent.array[best].T
            new = np.ones(len(to), dtype=bool)
            new[1:] = (to[1:] != to[:-1]) | (q[1:] != q[:-1]) | (v[1:] != v[:-1])
            send(tag, to[new], Rows.of(d[new], q[new], v[new], leaf[new]))
        to, v, q, b = back.to_owners.array.T
        send("msg_d", to, Rows.of(v, q, b, frag))
        own = [x for x in own if len(x[2])]
        table = {"tag": np.repeat(np.array([t for t, _, _ in own], dtype=object), [len(r) for _, _, r in own]), "frag": np.concatenate([np.broadcast_to(np.asarray(g, dtype=np.int64), len(r)) for _, g, r in own])}
        for i, c in enumerate("abcd"):
            table[c] = np.concatenate([r.array[:, i] if i < r.array.shape[1] else np.zeros(len(r), dtype=np.int64) for _, _, r in own])
        return pd.DataFrame(table)

    return run


def _latest(rows: DataFrame) -> DataFrame:
    """Messages of a superstep's parts as they are sent at its end: of each, the best only."""
    labels = rows.filter("tag IN ('msg_b', 'msg_a')").groupBy("tag", "frag", "b", "c").agg(F.min(F.struct("a", "d")).alias("m")).select("tag", "frag", "m.a", "b", "c", "m.d")
    asked = rows.filter("tag = 'msg_d'").groupBy("tag", "frag", "a", "b", "d").agg(F.max("c").alias("c"))
    return rows.filter("tag NOT IN ('msg_b', 'msg_a', 'msg_d')").unionByName(labels).unionByName(asked)


def run_program(graph: Graph, query: KeywordQuery, variant: str = "preemptive", m: int = 4, how: str = "hash", threshold: float = 2, bound: str = "union", index=None, selector=None, max_steps: int = 200, micro: int = 20_000, cell_edges: int = CELL_EDGES) -> Run:
    """Runs one query on ``m`` fragments. ``selector``: a name or a function of (backward indicator, forward indicator, step).

    With exchange, a fragment pauses after ``micro`` expansions: lists are reported and bounds pushed, then it goes on in the
    same superstep with the bound it was given; messages between fragments still wait for the superstep's end.
    ``cell_edges``: a fragment of more edges is dealt into cells. Answers are the same; a vertex can be expanded more often.
    """
    sketches, exchange, chosen = LADDER[variant]
    choose = SELECTORS[selector or chosen] if selector is None or isinstance(selector, str) else selector
    began = time.time()
    spark, n = graph.edges.sparkSession, len(query.keywords)
    if graph.frags is None:
        graph = hold(graph, m, how)
    q = query_frame(spark, [query])
    cells = max(1, -(-graph.edges.filter(F.col("w") <= query.tau).count() // (m * cell_edges)))
    if cells > 1:
        graph = replace(graph, frags=graph.frags.select("vid", (F.col("frag") * cells + F.pmod(F.xxhash64("vid"), F.lit(cells))).cast("int").alias("frag")))
    # No way within tau takes a heavier edge. Into a fragment only a vertex and where it has copies is told, not each edge.
    framed_table = Snapshot(framed_edges(graph).filter(F.col("w") <= query.tau))
    framed = framed_table.df
    into = framed.filter("src_frag <> dst_frag").groupBy("dst", "src_frag", "dst_frag").agg(F.min("src").alias("src"), F.min("w").alias("w")).withColumn("frag", F.col("dst_frag"))
    held_edges = Bucketed(framed.withColumn("frag", F.col("src_frag")).unionByName(into).select("frag", "src", "dst", "w", "src_frag", "dst_frag"), "frag")
    edges = held_edges.df
    asked = graph.postings.join(F.broadcast(q.select("kw", "kid")), "kw").join(graph.frags, "vid")
    start = asked.select(F.lit("pending").alias("tag"), "frag", F.lit(0).cast("long").alias("a"), F.col("kid").cast("long").alias("b"), F.col("vid").alias("c"), F.col("vid").alias("d"))
    # Copies of holders in other fragments start there too.
    cross = framed.filter("src_frag <> dst_frag").select(F.col("dst").alias("vid"), F.col("src_frag").alias("frag")).distinct()
    copies = asked.drop("frag").join(cross, "vid").select(F.lit("pending").alias("tag"), "frag", F.lit(0).cast("long").alias("a"), F.col("kid").cast("long").alias("b"), F.col("vid").alias("c"), F.col("vid").alias("d"))
    state = start.unionByName(copies)
    run, board = Run([]), BoundBoard(m, query.k, threshold, bound)
    fragment, own_lists = F.expr(f"CAST(frag div {cells} AS INT)"), {}
    seed = math.inf
    if sketches and index is not None:
        low = index.lower_bounds(q).join(F.broadcast(q.select("kw", "kid")), "kw").filter("lb > 0").join(graph.frags, "vid")
        state = state.unionByName(low.select(F.lit("lower").alias("tag"), "frag", F.col("vid").alias("a"), F.col("kid").cast("long").alias("b"), F.col("lb").alias("c"), F.lit(0).cast("long").alias("d")))
        seed = index.seed_bounds(graph, q, {query.qid: query}).get(query.qid, math.inf)
    held = Snapshot(state.select("tag", "frag", "a", "b", "c", "d"))
    framed_table.drop()
    known = dict.fromkeys(range(m), seed)
    quiet_forward, every = False, variant == "exhaustive"
    settled = False
    pause = micro if exchange else 1 << 30
    for step in range(1, max_steps + 1):
        buffers = {(r["frag"], r["tag"]): r for r in held.df.filter("tag IN ('pending', 'answer', 'demand')").groupBy(fragment.alias("frag"), "tag").agg(F.count("*").alias("n"), F.sum("a").alias("sa"), F.sum("c").alias("sc")).collect()}
        minima = [math.inf] * n
        for r in held.df.filter("tag = 'pending'").groupBy("b").agg(F.min("a").alias("d")).collect():
            minima[r["b"]] = r["d"]
        final = not every and sum(minima) > board.bound or min(minima) > min(query.tau, board.bound)
        tasks: dict[int, Task] = {}
        started = held.df
        for frag in range(m):
            parts = [x for x in (None if final else buffers.get((frag, "pending")), buffers.get((frag, "answer"))) if x]
            n_back, d_back, f = sum(x["n"] for x in parts), sum(x["sa"] for x in parts), buffers.get((frag, "demand"))
            bound_i = min(known[frag], board.local[frag])
            sb = backward_budget(d_back / n_back, bound_i, query.tau) if n_back else math.inf
            sf = forward_budget(f["sc"] / f["n"], query.tau) if f else math.inf
            kind = choose(sb, sf, step)
            if variant == "preemptive" and step == 1:
                kind = PARTIAL
            tasks[frag] = Task(kind, bound_i, tuple(minima), every or not exchange and step > 1, every or not final, pause, sketches)
        if all(t.kind == IDLE for t in tasks.values()):
            if quiet_forward or every:
                break
            # All buffers are empty: every fragment searches ahead for what its own roots lack.
            for frag, t in tasks.items():
                bound_i = min(board.bound, known[frag], board.local[frag])
                tasks[frag] = Task(FORWARD, bound_i, tuple(minima), micro=pause, border=sketches)
            quiet_forward = True
            if not settled:
                # A search made while waves still ran may have passed labels that came later: it does not count as served.
                started, settled = held.df.filter("tag <> 'served'"), True
        pops, ahead, parts, rows = dict.fromkeys(range(m), 0), dict.fromkeys(range(m), 0), 0, started
        active = {c: tasks[c // cells] for c in range(m * cells)}
        written, inside = [], False
        while any(t.kind != IDLE for t in active.values()):
            written.append(Snapshot(edges.groupBy("frag").cogroup(rows.groupBy("frag")).applyInPandas(_step(n, query.tau, EVERY if every else query.k, active, cells=cells), ROWS)))
            parts += 1
            lists: dict[int, list[tuple[int, int]]] = {}
            on = set()
            for r in written[-1].df.filter("tag IN ('list', 'metric')").collect():
                if r["tag"] == "list":
                    lists.setdefault(r["frag"], []).append((r["a"], r["b"]))
                else:
                    pops[r["frag"] // cells] += r["a"]
                    ahead[r["frag"] // cells] += r["b"]
                    run.forward_roots += r["d"]
                    if r["c"]:
                        on.add(r["frag"])
            own_lists |= lists
            for frag in sorted({c // cells for c in lists}):
                found = assemble((own_lists.get(c, ()) for c in range(frag * cells, (frag + 1) * cells)), query.k)
                board.report(frag, found[-1][1] if len(found) == query.k else math.inf, found)
            if exchange:
                for frag in board.lagging():
                    known[frag] = min(known[frag], board.push(frag))
            if cells > 1:
                for r in written[-1].df.filter("tag = 'woken'").select("frag", "a").distinct().collect():
                    inside = True
                    if tasks[r["frag"] // cells].kind in (PARTIAL, FORWARD if r["a"] else BACKWARD):
                        on.add(r["frag"])
            active = {c: replace(t, kind=tasks[f].kind, bound=min(t.bound, known[f], board.local[f])) if c in on else replace(t, kind=IDLE) for c, t in active.items() for f in [c // cells]}
            rows = written[-1].df.filter("tag NOT IN ('list', 'metric', 'woken')")
        if parts > 1:
            rows = _latest(rows)
        if cells > 1:
            # What goes to several cells of a fragment, or comes from several, is one message.
            far = rows.filter("tag IN ('msg_b', 'msg_a', 'msg_d')")
            of = lambda c, d: F.when(F.col("tag") == "msg_d", F.expr(d)).otherwise(F.expr(c))
            counted = far.select("tag", fragment.alias("frag"), of("c", "a").alias("v"), "b", of("0L", f"d div {cells}").alias("by")).distinct()
        else:
            counted = rows
        sent = {r["tag"]: r["n"] for r in counted.filter("tag IN ('msg_b', 'msg_a', 'msg_d')").groupBy("tag").agg(F.count("*").alias("n")).collect()}
        n_b, n_d = sent.get("msg_b", 0) + sent.get("msg_a", 0), sent.get("msg_d", 0)
        if n_b or n_d or any(t.kind in (BACKWARD, PARTIAL) for t in tasks.values()):
            quiet_forward = quiet_forward and not (n_b or n_d)
        quiet_forward = quiet_forward and not inside
        run.messages += n_b + n_d
        run.message_bytes += n_b * MATCH_BYTES + n_d * DEMAND_BYTES
        run.pops += sum(pops.values())
        run.ahead_pops += sum(ahead.values())
        run.parts += parts
        run.bounds.append(board.bound)
        run.steps.append({"step": step, "tasks": {f: t.kind for f, t in tasks.items()}, "pops": pops, "ahead": ahead, "parts": parts, "msg_b": n_b, "msg_d": n_d, "bound": board.bound})
        nxt = rows.select(F.when(F.col("tag") == "msg_b", "pending").when(F.col("tag") == "msg_a", "answer").when(F.col("tag") == "msg_d", "demand").otherwise(F.col("tag")).alias("tag"), "frag", "a", "b", "c", "d")
        fresh = Snapshot(nxt)
        for table in [*written, held]:
            table.drop()
        held = fresh
    else:
        raise RuntimeError(f"no end after {max_steps} supersteps")
    run.visited = held.df.filter("tag = 'label'").select("a").distinct().count()
    shipped = sum(len(x) for x in board.lists.values())
    if every:
        owned = held.df.filter("tag = 'label'").join(graph.frags.select(F.col("vid").alias("a"), "frag"), ["a", "frag"])
        complete = Snapshot(owned.groupBy("a").agg(F.count("*").alias("found"), F.sum("c").alias("score")).filter(F.col("found") == n), [F.count("*").alias("n")])
        shipped = complete.seen["n"]
        run.answers = [(r["a"], r["score"]) for r in complete.df.orderBy("score", "a").limit(query.k).collect()]
        complete.drop()
    else:
        run.answers = assemble(board.lists.values(), query.k)
    held_edges.drop()
    run.notified, run.pushed = board.notified, board.pushed
    run.message_bytes += (board.notified + board.pushed) * BOUND_BYTES + shipped * (16 + 16 * n)
    run.seconds = time.time() - began
    return run

