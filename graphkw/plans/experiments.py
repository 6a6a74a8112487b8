"""The experiments as sweeps over the given tables; each returns one row per run.

``python -m graphkw.plans.experiments NAME SF_DIR [QUERIES]`` prints a sweep as JSON lines.
"""

from __future__ import annotations

import json
import math
import sys
import time
from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame, SparkSession

from graphkw.functions.workload import generate
from graphkw.operators.partition import partition
from graphkw.operators.sketch import Index
from graphkw.plans.program import run_program
from graphkw.plans.baseline import sequential_answers
from graphkw.schema import Graph, KeywordQuery
from graphkw.sources.tables import build_graph, synthetic

SCHEMA = "experiment string, variant string, setting string, queries int, seconds double, supersteps double, messages double, bytes double, expansions double, visited double, notified double, pushed double, slowest_share double, forward_roots double, speedup double, bytes_share double"
VARIANTS = ("exhaustive", "two_phase", "sketch", "exchange", "preemptive")
DEFAULTS = {"size": 4, "tau": 3, "k": 10, "m": 8}


def straggler_ratio(steps: list[dict]) -> float:
    """Mean over supersteps of the busiest fragment's expansions over the mean fragment's."""
    shares = [max(p) / (sum(p) / len(p)) for s in steps if sum(p := list(s["pops"].values()))]
    return sum(shares) / len(shares) if shares else 1.0


def measure(name: str, graph: Graph, queries: list[KeywordQuery], setting: str, m: int, variants=VARIANTS, **options) -> Iterator[tuple]:
    """Means over the queries, a row per variant; speed-up over the exhaustive baseline and share of its bytes, where it is among them."""
    graph = partition(graph, m, options.pop("how", "hash")) if graph.frags is None else graph
    index = Index.build(graph, 8, 2 * max(q.tau for q in queries), iterations=5) if set(variants) - {"exhaustive", "two_phase", "single_task"} else None
    base = None
    for variant in variants:
        runs = [run_program(graph, q, variant, m, index=index, **options) for q in queries]
        mean = lambda f: sum(map(f, runs)) / len(runs)  # noqa: B023, E731
        seconds, sent = mean(lambda r: r.seconds), mean(lambda r: r.message_bytes)
        if variant == "exhaustive":
            base = seconds, sent
        ratios = (base[0] / seconds, sent / base[1] if base[1] else math.nan) if base else (math.nan, math.nan)
        yield (name, variant, setting, len(runs), seconds, mean(lambda r: len(r.steps)), mean(lambda r: r.messages), sent, mean(lambda r: r.pops), mean(lambda r: r.visited), mean(lambda r: r.notified), mean(lambda r: r.pushed), mean(lambda r: straggler_ratio(r.steps)), mean(lambda r: r.forward_roots), *ratios)


def growth(rows: list[tuple]) -> dict[str, float]:
    """By how many per cent each variant's mean seconds differ between the first and the last setting of a sweep."""
    by: dict[str, list[float]] = {}
    for r in rows:
        by.setdefault(r[1], []).append(r[4])
    return {v: 100 * (s[-1] / s[0] - 1) for v, s in by.items() if s[0]}


def _drawn(graph: Graph, n: int, **changes) -> list[KeywordQuery]:
    at = DEFAULTS | changes
    return generate(graph, n, at["size"], at["tau"], at["k"])


def by_size(spark, sf_dir, n):
    g = build_graph(spark, sf_dir, "g1u")
    for size in (2, 3, 4, 5, 6):
        yield from measure("by_size", g, _drawn(g, n, size=size), f"keywords={size}", DEFAULTS["m"])


def by_workers(spark, sf_dir, n):
    g = build_graph(spark, sf_dir, "g1u")
    for m in (2, 4, 8, 12):
        yield from measure("by_workers", g, _drawn(g, n), f"m={m}", m)


def by_graph(spark, sf_dir, n):
    for part in (1, 2, 3, 4, 5):
        g = synthetic(spark, 2_000 * part, 50_000 * part)
        yield from measure("by_graph", g, _drawn(g, n), f"x{part}", 12)


def by_tau(spark, sf_dir, n):
    g = build_graph(spark, sf_dir, "g1u")
    for tau in (3, 4, 5, 6):
        yield from measure("by_tau", g, _drawn(g, n, tau=tau), f"tau={tau}", DEFAULTS["m"])


def by_k(spark, sf_dir, n):
    g = build_graph(spark, sf_dir, "g1u")
    for k in (5, 10, 15, 20, 25, 30):
        yield from measure("by_k", g, _drawn(g, n, k=k), f"k={k}", DEFAULTS["m"])


def communication(spark, sf_dir, n):
    for name in ("g1r", "g2"):
        g = build_graph(spark, sf_dir, name)
        yield from measure("communication", g, _drawn(g, n), name, DEFAULTS["m"])


def by_threshold(spark, sf_dir, n):
    g = build_graph(spark, sf_dir, "g1r")
    for threshold in (0, 1, 2, 3, 4, 6, math.inf):
        yield from measure("by_threshold", g, _drawn(g, n), f"threshold={threshold}", DEFAULTS["m"], ("exchange", "preemptive"), threshold=threshold)


def by_partitioner(spark, sf_dir, n):
    g = build_graph(spark, sf_dir, "g2")
    for how in ("hash", "balanced_lp", "greedy_stream"):
        yield from measure("by_partitioner", g, _drawn(g, n), how, DEFAULTS["m"], how=how)


def versus_sequential(spark, sf_dir, n):
    g = build_graph(spark, sf_dir, "g1u")
    queries = _drawn(g, n)
    yield from measure("versus_sequential", g, queries, "m=8", DEFAULTS["m"], ("preemptive",))
    # The one-machine baseline reads the whole graph in one task by definition; the driver gets its k answers.
    for q in queries:
        began = time.time()
        sequential_answers(g, q).collect()
        yield ("versus_sequential", "sequential", f"q{q.qid}", 1, time.time() - began, 1.0, *[0.0] * 6, 1.0, 0.0, math.nan, math.nan)


def stragglers(spark, sf_dir, n):
    g = build_graph(spark, sf_dir, "g1r")
    yield from measure("stragglers", g, _drawn(g, n), "by_kind", DEFAULTS["m"], how="by_kind")


EXPERIMENTS: dict[str, Callable[[SparkSession, str, int], Iterator[tuple]]] = {f.__name__: f for f in (by_size, by_workers, by_graph, by_tau, by_k, communication, by_threshold, by_partitioner, versus_sequential, stragglers)}


def experiment(spark: SparkSession, sf_dir: str, name: str, queries: int = 50) -> DataFrame:
    return spark.createDataFrame([tuple(float(x) if i > 3 else x for i, x in enumerate(r)) for r in EXPERIMENTS[name](spark, sf_dir, queries)], SCHEMA)


def trajectory(spark: SparkSession, graph: Graph, query: KeywordQuery, variant: str = "preemptive", m: int = 2, **options) -> DataFrame:
    """Bound, messages and expansions of each superstep and fragment."""
    run = run_program(graph, query, variant, m, **options)
    rows = [(s["step"], f, s["tasks"][f], p, s["msg_b"], s["msg_d"], None if s["bound"] == math.inf else float(s["bound"])) for s in run.steps for f, p in s["pops"].items()]
    return spark.createDataFrame(rows, "step int, frag int, task string, expansions long, msg_b long, msg_d long, bound double")


if __name__ == "__main__":
    session = SparkSession.builder.master("local[*]").config("spark.sql.shuffle.partitions", "8").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    session.sparkContext.setLogLevel("ERROR")
    for row in EXPERIMENTS[sys.argv[1]](session, sys.argv[2], int(sys.argv[3]) if len(sys.argv) > 3 else 50):
        print(json.dumps(dict(zip([c.split()[0] for c in SCHEMA.split(", ")], row, strict=True))), flush=True)
