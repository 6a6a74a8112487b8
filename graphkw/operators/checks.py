"""Invariants of a run: monotone labels, bounded rounds, completeness of what was visited."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def worsened(before: DataFrame, after: DataFrame) -> DataFrame:
    """Labels that a later state lost or made larger: empty for a monotone run. Both: (qid, kid, vid, p)."""
    later = after.select("qid", "kid", "vid", F.col("p").alias("later"))
    return before.select("qid", "kid", "vid", "p").join(later, ["qid", "kid", "vid"], "left").filter("later IS NULL OR later > p")


def missing_roots(labels: DataFrame, answers: DataFrame) -> DataFrame:
    """Answer roots (qid, root) that no wave has visited: must be empty."""
    return answers.select("qid", "root").join(labels.select("qid", F.col("vid").alias("root")).distinct(), ["qid", "root"], "left_anti")


def bounds_fall(trace: list[dict]) -> bool:
    """Whether no query's bound ever rose from round to round."""
    last: dict[int, float] = {}
    for step in trace:
        for qid, s in step["bounds"].items():
            if s > last.get(qid, math.inf):
                return False
            last[qid] = s
    return True


def rounds_bounded(trace: list[dict], tau: int, lightest: int = 1, delta: int = 1) -> bool:
    """Whether the backward wave took at most tau / min(delta, lightest) + 1 rounds and as many again for re-expansions within a step."""
    return sum(s["phase"] == "backward" for s in trace) <= (tau // min(delta, lightest) + 1) * max(1, delta)
