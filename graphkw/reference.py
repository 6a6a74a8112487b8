"""Searches in plain Python: the brute-force reference and the sequential baseline."""

from __future__ import annotations

import heapq
import math
from collections import defaultdict
from collections.abc import Iterable

from graphkw.schema import KeywordQuery


def distances(edges: Iterable[tuple[int, int, int]], holders: Iterable[int], cap: float = math.inf, backwards: bool = True) -> dict[int, int]:
    """Least distance from each vertex to a holder (or, forwards, from the holders to each vertex)."""
    ahead = defaultdict(list)
    for u, v, w in edges:
        ahead[v if backwards else u].append((u if backwards else v, w))
    best = dict.fromkeys(holders, 0)
    heap = [(0, v) for v in best]
    heapq.heapify(heap)
    while heap:
        d, v = heapq.heappop(heap)
        if d > best[v]:
            continue
        for u, w in ahead[v]:
            if (n := d + w) <= cap and n < best.get(u, math.inf):
                best[u] = n
                heapq.heappush(heap, (n, u))
    return best


def brute_force(edges: Iterable[tuple[int, int, int]], postings: Iterable[tuple[str, int]], query: KeywordQuery) -> list[tuple[int, int]]:
    """(root, score) of the k best by (score, root)."""
    edges, holders = list(edges), defaultdict(set)
    for kw, v in postings:
        holders[kw].add(v)
    reach = [distances(edges, holders[kw], query.tau) for kw in query.keywords]
    roots = set(reach[0]).intersection(*reach[1:])
    return heapq.nsmallest(query.k, ((r, sum(d[r] for d in reach)) for r in roots), key=lambda x: (x[1], x[0]))


def sequential(edges: Iterable[tuple[int, int, int]], postings: Iterable[tuple[str, int]], query: KeywordQuery) -> tuple[list[tuple[int, int]], dict]:
    """One heap for all keywords, smallest distance first, until no unseen root can enter the list; then forward searches for what partial roots lack."""
    inward, outward, holders = defaultdict(list), defaultdict(list), defaultdict(set)
    for u, v, w in edges:
        inward[v].append((u, w))
        outward[u].append((v, w))
    for kw, v in postings:
        holders[kw].add(v)
    n = len(query.keywords)
    label: list[dict[int, int]] = [dict.fromkeys(holders[kw], 0) for kw in query.keywords]
    settled: list[set[int]] = [set() for _ in range(n)]
    heaps = [[(0, v) for v in sorted(lab)] for lab in label]
    best: dict[int, int] = {}

    def bound() -> float:
        return heapq.nsmallest(query.k, best.values())[-1] if len(best) >= query.k else math.inf

    pops, s = 0, math.inf
    while True:
        for i in range(n):
            while heaps[i] and heaps[i][0][1] in settled[i]:
                heapq.heappop(heaps[i])
        tops = [h[0][0] if h else math.inf for h in heaps]
        if min(tops) == math.inf or sum(tops) > s:
            break
        i = min(range(n), key=lambda j: tops[j])
        d, v = heapq.heappop(heaps[i])
        settled[i].add(v)
        pops += 1
        if all(v in x for x in settled):
            best[v] = sum(lab[v] for lab in label)
            s = bound()
        for u, w in inward[v]:
            if (m := d + w) <= query.tau and m < label[i].get(u, math.inf):
                label[i][u] = m
                heapq.heappush(heaps[i], (m, u))
    tops = [h[0][0] if h else math.inf for h in heaps]
    forward = 0
    for u in sorted(set().union(*settled)):
        lower = [label[i][u] if u in settled[i] else tops[i] for i in range(n)]
        if u in best or sum(lower) > s:
            continue
        exact = list(lower)
        for i in range(n):
            if u in settled[i]:
                continue
            left, dist, heap, exact[i] = min(query.tau, s - (sum(exact) - exact[i])), {u: 0}, [(0, u)], math.inf
            while heap:
                d, v = heapq.heappop(heap)
                if d > dist[v] or d > left:
                    continue
                forward += 1
                if v in holders[query.keywords[i]]:
                    exact[i] = d
                    break
                for x, w in outward[v]:
                    if d + w < dist.get(x, math.inf):
                        dist[x] = d + w
                        heapq.heappush(heap, (d + w, x))
            if exact[i] == math.inf:
                break
        if sum(exact) < math.inf and max(exact) <= query.tau:
            best[u] = sum(exact)
            s = bound()
    answers = heapq.nsmallest(query.k, best.items(), key=lambda x: (x[1], x[0]))
    return answers, {"settled": pops, "forward": forward}
