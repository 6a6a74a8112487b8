"""Answer lists and the upper bounds that fragments and coordinator exchange."""

from __future__ import annotations

import heapq
import math
from collections.abc import Iterable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def top_answers(complete: DataFrame, ks: dict[int, int]) -> DataFrame:
    """The k best (score, root) of each query, ranked; ``ks``: k by query.

    The filter by a literal lets Spark cut each partition to as many rows before any row is moved.
    """
    rank = F.row_number().over(Window.partitionBy("qid").orderBy("score", "root"))
    ranked = complete.select("qid", F.col("vid").alias("root"), "score").withColumn("rank", rank).filter(F.col("rank") <= F.lit(max(ks.values())))
    if len(set(ks.values())) > 1:
        asked = complete.sparkSession.createDataFrame(sorted(ks.items()), "qid int, k int")
        ranked = ranked.join(F.broadcast(asked), "qid").filter("rank <= k")
    return ranked.select("qid", "rank", "root", "score")


class TopKList:
    """A fragment's list: at most k roots, each once; its bound is infinite while it is short."""

    def __init__(self, k: int):
        self.k, self.best = k, {}

    def offer(self, root: int, score: int) -> bool:
        """Takes a root that is new and good enough, or a better score of one it holds."""
        if root in self.best:
            if score < self.best[root]:
                self.best[root] = score
                return True
            return False
        if len(self.best) == self.k:
            worst = max(self.best, key=lambda r: (self.best[r], r))
            if (score, root) >= (self.best[worst], worst):
                return False
            del self.best[worst]
        self.best[root] = score
        return True

    @property
    def bound(self) -> float:
        return max(self.best.values()) if len(self.best) == self.k else math.inf

    def rows(self) -> list[tuple[int, int]]:
        return sorted(((r, s) for r, s in self.best.items()), key=lambda x: (x[1], x[0]))


def assemble(lists: Iterable[Iterable[tuple[int, int]]], k: int) -> list[tuple[int, int]]:
    """The k best (root, score) of all local lists, each root once."""
    best: dict[int, int] = {}
    for rows in lists:
        for root, score in rows:
            best[root] = min(score, best.get(root, score))
    return heapq.nsmallest(k, best.items(), key=lambda x: (x[1], x[0]))


class BoundBoard:
    """The coordinator's table of local bounds with its notification counters.

    ``mode`` "min": the least local bound; "union": the k-th score over all reported lists, which is never larger.
    """

    def __init__(self, m: int, k: int, threshold: float = 2, mode: str = "union"):
        if mode not in ("min", "union"):
            raise ValueError(f"no such bound: {mode}")
        self.k, self.threshold, self.mode = k, threshold, mode
        self.local = dict.fromkeys(range(m), math.inf)
        self.counter = dict.fromkeys(range(m), 0)
        self.lists: dict[int, list[tuple[int, int]]] = {}
        self.notified = self.pushed = 0
        self.trace: list[float] = []

    @property
    def bound(self) -> float:
        least = min(self.local.values())
        if self.mode == "min":
            return least
        best = assemble(self.lists.values(), self.k)
        return min(least, best[-1][1]) if len(best) == self.k else least

    def report(self, frag: int, bound: float, rows: Iterable[tuple[int, int]] = ()) -> None:
        """A fragment notifies the coordinator of its list and bound; only a refinement counts."""
        rows = list(rows)
        if bound < self.local[frag] or rows != self.lists.get(frag, []):
            self.local[frag] = min(self.local[frag], bound)
            self.lists[frag] = rows
            self.counter[frag] += 1
            self.notified += 1
            self.trace.append(self.bound)

    def lagging(self) -> list[int]:
        """Fragments that fell behind the busiest notifier by more than the threshold with a bound above the global one."""
        most, s = max(self.counter.values()), self.bound
        return [i for i, n in self.counter.items() if most - n > self.threshold and self.local[i] > s]

    def push(self, frag: int) -> float:
        self.local[frag] = min(self.local[frag], self.bound)
        self.counter[frag] = max(self.counter.values())
        self.pushed += 1
        return self.local[frag]
