"""Which subtask a fragment runs next: budgets, staleness indicators and selectors."""

from __future__ import annotations

import math
from collections.abc import Callable

BACKWARD, FORWARD, IDLE = "b", "f", "idle"
#: The first superstep of the multi-task model: the partial steps of all subtasks.
PARTIAL = "all"


def backward_budget(d: int, s: float, tau: int) -> float:
    """How far a backward message may still expand, as the indicator counts it."""
    return min(s - d, tau)


def forward_budget(budget: int, tau: int) -> float:
    return min(budget, tau)


def indicator(budgets: list[float]) -> float:
    """Mean budget of a buffer; infinite if it is empty."""
    return sum(budgets) / len(budgets) if budgets else math.inf


def preemptive(sb: float, sf: float, step: int) -> str:
    """Backward only if its indicator is strictly less."""
    if sb == sf == math.inf:
        return IDLE
    return BACKWARD if sb < sf else FORWARD


def alternate(sb: float, sf: float, step: int) -> str:
    """The single-task order: odd steps backward, even steps forward, unless that buffer is empty."""
    first, second = ((sb, BACKWARD), (sf, FORWARD)) if step % 2 else ((sf, FORWARD), (sb, BACKWARD))
    return first[1] if first[0] < math.inf else second[1] if second[0] < math.inf else IDLE


def backward_first(sb: float, sf: float, step: int) -> str:
    return BACKWARD if sb < math.inf else FORWARD if sf < math.inf else IDLE


def forward_first(sb: float, sf: float, step: int) -> str:
    return FORWARD if sf < math.inf else BACKWARD if sb < math.inf else IDLE


SELECTORS: dict[str, Callable[[float, float, int], str]] = {"preemptive": preemptive, "alternate": alternate, "backward_first": backward_first, "forward_first": forward_first}
