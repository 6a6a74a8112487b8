"""One fragment's work in one superstep, over its own edges and state rows.

A fragment owns vertices; it holds the edges that leave them, and copies of the
foreign vertices these edges reach. Labels spread backwards over those edges, also
from copies. Demands for foreign vertices go to their owners; improved labels of
owned vertices go to all fragments that hold a copy.

All state is in arrays over the fragment's vertices. A wave takes all vertices of one
keyword at one distance at once; between two of these the list and its bound are
brought up to date. Demands of one keyword are searched together: what is passed on
is the largest budget with which any of them reaches a vertex.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np

#: A label in one long: the distance, then the number of its leaf among those that the fragment has met.
_LEAF = 40
_NONE = np.int64(1) << 62


class Rows:
    """Rows of whole numbers in one array, read as tuples."""

    def __init__(self, rows=(), width: int = 4):
        self.array = rows.array if isinstance(rows, Rows) else np.asarray(rows, dtype=np.int64).reshape(-1, width)

    @classmethod
    def of(cls, *columns) -> Rows:
        return cls(np.stack(np.broadcast_arrays(*columns), axis=1).astype(np.int64, copy=False), len(columns))

    def __len__(self) -> int:
        return len(self.array)

    def __iter__(self) -> Iterator[tuple]:
        return map(tuple, self.array.tolist())

    def __getitem__(self, i: int) -> tuple:
        return tuple(self.array[i].tolist())

    def __eq__(self, other) -> bool:
        return list(self) == list(other)

    def __add__(self, other: Rows) -> Rows:
        if not len(self) or not len(other):
            return self if len(self) else other
        return Rows(np.concatenate([self.array, other.array]), self.array.shape[1])

    __hash__ = None


@dataclass
class Task:
    """What the coordinator tells a fragment."""

    kind: str
    bound: float
    minima: tuple[float, ...]
    force: bool = False
    wave: bool = True
    micro: int = 1 << 30
    border: bool = False


@dataclass
class Output:
    left: Rows = field(default_factory=Rows)
    to_copies: Rows = field(default_factory=lambda: Rows((), 5))
    to_owners: Rows = field(default_factory=Rows)
    demands_left: Rows = field(default_factory=lambda: Rows((), 3))
    served: Rows = field(default_factory=lambda: Rows((), 3))
    answers: list[tuple[int, int]] = field(default_factory=list)
    pops: int = 0
    ahead: int = 0
    refined: int = 0
    roots: int = 0
    skipped: int = 0
    stopped: bool = False


class _Steps:
    """Edges by the vertex they are walked from: ``meet`` gives, for vertices, the number of each step's vertex, its other end and weight."""

    def __init__(self, at: np.ndarray, to: np.ndarray, w: np.ndarray, n: int):
        order = np.argsort(at, kind="stable")
        self.to, self.w = to[order], w[order]
        self.begin = np.zeros(n + 1, dtype=np.int64)
        np.cumsum(np.bincount(at, minlength=n), out=self.begin[1:])

    def meet(self, v: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        first = self.begin[v]
        n = self.begin[v + 1] - first
        which = np.repeat(np.arange(len(v)), n)
        at = np.arange(len(which)) + np.repeat(first - (np.cumsum(n) - n), n)
        return which, self.to[at], self.w[at]


class _Labels:
    """The fragment's labels read as {(v, q): (d, leaf)}."""

    def __init__(self, fragment: Fragment):
        self.f = fragment

    def __getitem__(self, key: tuple[int, int]) -> tuple[float, int]:
        v, q = key
        p = self.f.p[q, self.f.at(np.array([v]))[0]]
        return (math.inf, v) if p == _NONE else (int(p >> _LEAF), int(self.f.leaves[p & ((1 << _LEAF) - 1)]))


class Fragment:
    """State of one fragment during a superstep. ``others``: vertices and ``leaves``: holders that its buffers name beside edges and labels."""

    def __init__(self, frag: int, n: int, tau: int, k: int, edges, labels, holders, lower=None, others=(), leaves=()):
        self.frag, self.n, self.tau, self.k = frag, n, tau, k
        u, v, w, fu, fv = edges if isinstance(edges, tuple) else Rows(edges, 5).array.T
        labels, holders = Rows(labels), Rows(holders, 2).array
        lower = lower if isinstance(lower, Rows) else Rows([(x, q, d) for (x, q), d in (lower or {}).items()], 3)
        # Of an edge into the fragment only its target, and where a copy of that is.
        own = fu == frag
        came = ~own & (fv == frag)
        named = [u[own], v[own], v[came], labels.array[:, 0], holders[:, 0], lower.array[:, 0], np.asarray(others, dtype=np.int64)]
        self.ids = np.unique(np.concatenate(named))
        size = len(self.ids)
        src, dst, ow = self.at(u[own]).astype(np.int32), self.at(v[own]).astype(np.int32), w[own].astype(np.int32)
        self.inward, self.outward = _Steps(dst, src, ow, size), _Steps(src, dst, ow, size)
        self.owner = np.full(size, frag, dtype=np.int32)
        self.owner[dst] = fv[own]
        self.mine = self.owner == frag
        pairs = np.unique(np.stack([self.at(v[came]), fu[came]], axis=1), axis=0) if came.any() else np.zeros((0, 2), dtype=np.int64)
        self.copies = _Steps(pairs[:, 0], pairs[:, 1], np.zeros(len(pairs), dtype=np.int32), size)
        self.leaves = np.unique(np.concatenate([labels.array[:, 3], named[3], holders[:, 0], named[-1], np.asarray(leaves, dtype=np.int64)]))
        self.p = np.full((n, size), _NONE, dtype=np.int64)
        if len(labels):
            x, q, d, leaf = labels.array.T
            np.minimum.at(self.p, (q, self.at(x)), self._packed(d, leaf))
        self.lower = np.zeros((n, size), dtype=np.int32) if len(lower) else None
        if len(lower):
            self.lower[lower.array[:, 1], self.at(lower.array[:, 0])] = lower.array[:, 2]

    @property
    def label(self) -> _Labels:
        return _Labels(self)

    def labels(self) -> Rows:
        """(v, q, d, leaf) of all labels."""
        q, i = np.nonzero(self.p < _NONE)
        return Rows.of(self.ids[i], q, *self._apart(self.p[q, i]))

    def at(self, v: np.ndarray) -> np.ndarray:
        """The numbers of vertices in this fragment."""
        i = np.searchsorted(self.ids, v)
        if len(i) and (i.max() >= len(self.ids) or (self.ids[i] != v).any()):
            raise KeyError("a vertex that the fragment does not know")
        return i

    def _packed(self, d: np.ndarray, leaf: np.ndarray) -> np.ndarray:
        i = np.searchsorted(self.leaves, leaf)
        if len(i) and (i.max() >= len(self.leaves) or (self.leaves[i] != leaf).any()):
            # A holder met for the first time: the numbers of all others may move.
            q, x = np.nonzero(self.p < _NONE)
            d0, leaf0 = self._apart(self.p[q, x])
            self.leaves = np.union1d(self.leaves, leaf)
            self.p[q, x] = (d0 << _LEAF) | np.searchsorted(self.leaves, leaf0)
            i = np.searchsorted(self.leaves, leaf)
        return (np.asarray(d, dtype=np.int64) << _LEAF) | i

    def _apart(self, p: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return p >> _LEAF, self.leaves[p & ((1 << _LEAF) - 1)]

    def _distance(self, q, i) -> np.ndarray:
        p = self.p[q, i]
        return np.where(p == _NONE, math.inf, p >> _LEAF)

    def _lower(self, q: int, i: np.ndarray, d: np.ndarray, to: np.ndarray) -> np.ndarray:
        """Takes what is less of labels ``to`` for vertices ``i``; the vertices that got better."""
        better = to < self.p[q, i]
        i, to = i[better], to[better]
        np.minimum.at(self.p[q], i, to)
        return np.unique(i)

    def owns(self, v: int) -> bool:
        return bool(self.mine[self.at(np.array([v]))[0]])

    def _offer(self, top: list, i: np.ndarray | None, out: Output) -> list:
        """The k best (score, root) of ``top`` and the complete vertices among ``i`` (None: all that are owned)."""
        if self.k >= len(self.ids) + 1 and self.k >= 1 << 30:
            return top
        i = np.nonzero(self.mine)[0] if i is None else i[self.mine[i]]
        done = i[(self.p[:, i] < _NONE).all(axis=0)]
        if not len(done):
            return top
        score = (self.p[:, done] >> _LEAF).sum(axis=0)
        if len(done) > self.k:
            cut = np.partition(score, self.k - 1)[self.k - 1]
            done, score = done[score <= cut], score[score <= cut]
        root = self.ids[done]
        if len(root) > self.k:
            order = np.lexsort((root, score))[: self.k]
            root, score = root[order], score[order]
        best = {r: s for s, r in top}
        for r, s in zip(root.tolist(), score.tolist(), strict=True):
            best[r] = min(s, best.get(r, s))
        after = sorted((s, r) for r, s in best.items())[: self.k]
        out.refined += after != top
        return after

    def _bound(self, top: list) -> float:
        return top[-1][0] if len(top) == self.k else math.inf

    def backward(self, task: Task, queue, out: Output) -> None:
        """Expands (d, q, v, leaf), nearest first. Stops by the frontier sum or after ``micro`` pops; what is left stays pending."""
        d0, q0, v0, leaf0 = Rows(queue).array.T
        i0, p0 = self.at(v0), self._packed(d0, leaf0)
        wait, changed = np.zeros(self.p.shape, dtype=bool), np.zeros(self.p.shape, dtype=bool)
        top = self._offer([], None, out)
        for q in range(self.n):
            of = q0 == q
            changed[q, self._lower(q, i0[of], d0[of], p0[of])] = True
            wait[q, i0[of][p0[of] == self.p[q, i0[of]]]] = True
        top = self._offer(top, np.nonzero(changed.any(axis=0))[0], out)
        open_ = [np.nonzero(row)[0] for row in wait]
        while True:
            dists = [self.p[q, i] >> _LEAF for q, i in enumerate(open_)]
            tops = [d.min() if len(d) else math.inf for d in dists]
            s, least = min(task.bound, self._bound(top)), min(tops)
            if least == math.inf or least > min(self.tau, s):
                break
            # The local frontier says nothing about keywords that arrive by other fragments: their global minima count.
            if not task.force and sum(min(t, m) for t, m in zip(tops, task.minima, strict=True)) > s:
                break
            if out.pops >= task.micro:
                out.stopped = True
                break
            q = tops.index(least)
            now = open_[q][dists[q] == least][: task.micro - out.pops]
            out.pops += len(now)
            wait[q, now] = False
            which, to, w = self.inward.meet(now)
            near = least + w <= min(self.tau, s)
            which, to, w = which[near], to[near], w[near].astype(np.int64)
            better = self._lower(q, to, w, self.p[q, now][which] + (w << _LEAF))
            wait[q, better] = changed[q, better] = True
            top = self._offer(top, better, out)
            open_[q] = np.nonzero(wait[q])[0]
        limit = min(self.tau, task.bound, self._bound(top))
        q, i = np.nonzero(wait)
        d, leaf = self._apart(self.p[q, i])
        out.left = out.left + Rows(np.stack([d, q, self.ids[i], leaf], axis=1)[d <= limit])
        self._ship(changed, out)
        out.answers = [(r, x) for x, r in top]

    def _ship(self, changed: np.ndarray, out: Output) -> None:
        q, i = np.nonzero(changed)
        which, to, _ = self.copies.meet(i)
        q, i = q[which], i[which]
        d, leaf = self._apart(self.p[q, i])
        out.to_copies = out.to_copies + Rows.of(to, d, q, self.ids[i], leaf)

    def _border(self) -> np.ndarray:
        best = np.where(self.mine, _NONE, 0)
        wait = ~self.mine
        while wait.any():
            i = np.nonzero(wait)[0]
            least = best[i].min()
            now = i[best[i] == least]
            wait[now] = False
            _, to, w = self.inward.meet(now)
            d = least + w
            nearer = (d <= self.tau) & (d < best[to])
            np.minimum.at(best, to[nearer], d[nearer])
            wait[to[nearer]] = True
        return best

    def border(self) -> dict[int, int]:
        """Distance from each owned vertex to the nearest foreign one, within tau."""
        best = self._border()
        return dict(zip(self.ids[best < _NONE].tolist(), best[best < _NONE].tolist(), strict=True))

    def roots(self, task: Task, s: float, queue=(), missing: bool = False, seen: Output | None = None) -> Rows:
        """(v, q, budget) of owned vertices that may still be answers, for keywords they lack or (unless ``missing``) hold provisionally.

        With ``task.border``, a keyword is not searched for within a budget that reaches neither a foreign vertex nor the
        fragment's own frontier ``queue``: every path that short lies inside, where the wave has passed already.
        """
        border, nearest = self._border() if task.border else None, [math.inf] * self.n
        queue = Rows(queue).array
        for q in range(self.n):
            nearest[q] = queue[queue[:, 1] == q, 0].min(initial=1 << 60) if len(queue) else math.inf
        i = np.nonzero(self.mine & (self.p < _NONE).any(axis=0))[0]

        def least(q: int, d: np.ndarray) -> np.ndarray:
            m = task.minima[q]
            known = self.lower[q, i] if self.lower is not None else 0
            return np.where(d <= m, d, np.maximum(np.minimum(d, m), known))

        total, worst = np.zeros(len(i)), np.zeros(len(i))
        for q in range(self.n):
            low = least(q, self._distance(q, i))
            total, worst = total + low, np.maximum(worst, low)
        i, total = i[may := (worst <= self.tau) & (total <= s)], total[may]
        found = [Rows((), 3)]
        for q in range(self.n):
            d = self._distance(q, i)
            low = least(q, d)
            budget = np.minimum(np.minimum(self.tau, d), s - (total - low))
            asks = (d > task.minima[q]) & ((d == math.inf) | (not missing)) & (budget >= low)
            if task.border:
                inside = asks & (border[i] > budget) & (nearest[q] > budget)
                if seen:
                    seen.skipped += int(inside.sum())
                asks &= ~inside
            found.append(Rows.of(self.ids[i[asks]], q, np.floor(budget[asks]).astype(np.int64)))
        return Rows(np.concatenate([r.array for r in found]), 3)

    def forward(self, task: Task, demands, served, out: Output, own_roots: bool, queue=(), missing: bool = False) -> None:
        """Searches ahead for each (v, q, budget) not served as far yet, those of a keyword together; found labels are passed on backwards next time."""
        demands = Rows(demands, 3)
        served = served if isinstance(served, Rows) else Rows([(v, q, b) for (v, q), b in served.items()], 3)
        top = self._offer([], None, out)
        ahead = self.roots(task, min(task.bound, self._bound(top)), queue, missing, out) if own_roots else Rows((), 3)
        out.roots += len(np.unique(ahead.array[:, 0]))
        done, asked, todo = (np.full(self.p.shape, -1, dtype=np.int32) for _ in range(3))
        for table, rows in ((done, served), (asked, demands), (todo, demands), (todo, ahead)):
            np.maximum.at(table, (rows.array[:, 1], self.at(rows.array[:, 0])), rows.array[:, 2])
        todo[todo <= done] = -1
        q0, i0 = np.nonzero(todo >= 0)
        order = np.lexsort((q0, i0, -todo[q0, i0]))
        q0, i0 = q0[order], i0[order]
        began, changed, first = out.pops, np.zeros(self.p.shape, dtype=bool), 0
        while first < len(q0):
            if out.pops - began >= task.micro:
                # What others asked for stays in the buffer; own roots are listed anew.
                rest = np.zeros(self.p.shape, dtype=bool)
                rest[q0[first:], i0[first:]] = True
                out.demands_left = out.demands_left + Rows(demands.array[rest[demands.array[:, 1], self.at(demands.array[:, 0])]], 3)
                out.stopped = True
                break
            part = slice(first, first + max(1, task.micro - (out.pops - began)))
            first = min(part.stop, len(q0))
            for q in np.unique(q0[part]).tolist():
                i = i0[part][q0[part] == q]
                better = self._search(q, i, todo[q, i], task.minima[q], done, out)
                # Whoever asked may hold an older label, so a demand is answered even by what was known.
                changed[q, better] = True
                changed[q, i[(asked[q, i] >= 0) & (self.p[q, i] < _NONE)]] = True
                top = self._offer(top, better, out)
        q, i = np.nonzero(changed)
        d, leaf = self._apart(self.p[q, i])
        out.left = out.left + Rows.of(d, q, self.ids[i], leaf)
        self._ship(changed, out)
        out.ahead += out.pops - began
        q, i = np.nonzero((done >= 0).T)[::-1]
        out.served = Rows.of(self.ids[i], q, done[q, i])
        out.answers = [(r, x) for x, r in top]

    def _search(self, q: int, i: np.ndarray, budget: np.ndarray, minimum: float, done: np.ndarray, out: Output) -> np.ndarray:
        """Spreads budgets from ``i``, then labels back over the vertices they reached; returns what got better. Marks ``done`` and sends demands."""
        left = np.full(len(self.ids), -1, dtype=np.int64)
        left[i] = budget
        done[q, i] = budget
        wait = left >= 0
        # A label that is final, and a foreign vertex, end the way.
        ends = ~self.mine | (self._distance(q, slice(None)) <= minimum)
        while wait.any():
            at = np.nonzero(wait)[0]
            now = at[left[at] == left[at].max()]
            out.pops += len(now)
            wait[now] = False
            now = now[~ends[now]]
            which, to, w = self.outward.meet(now)
            # Beyond the label that a vertex has, nothing is nearer.
            b = np.minimum(left[now], np.where(self.p[q, now] == _NONE, _NONE, self.p[q, now] >> _LEAF))[which] - w
            more = b > left[to]
            np.maximum.at(left, to[more], b[more])
            wait[to[more]] = True
        out_of = np.nonzero((left >= 0) & ~self.mine & ~(self._distance(q, slice(None)) <= minimum))[0]
        out_of = out_of[left[out_of] > done[q, out_of]]
        out.to_owners = out.to_owners + Rows.of(self.owner[out_of], self.ids[out_of], q, left[out_of])
        done[q, out_of] = left[out_of]
        wait = (left >= 0) & (self.p[q] < _NONE)
        inside, better = (left >= 0) & ~ends, np.zeros(len(self.ids), dtype=bool)
        while wait.any():
            at = np.nonzero(wait)[0]
            d = self.p[q, at] >> _LEAF
            now = at[d == d.min()]
            wait[now] = False
            which, to, w = self.inward.meet(now)
            w = w.astype(np.int64)
            p = self.p[q, now][which] + (w << _LEAF)
            ok = inside[to] & (p >> _LEAF <= left[to])
            nearer = self._lower(q, to[ok], w[ok], p[ok])
            better[nearer] = wait[nearer] = True
        return np.nonzero(better)[0]
