"""Online anomaly scorers over an ordered stream: an adaptive histogram forest and the scorers it is compared with.

Each kernel has ``step(x) -> score``, learns before it scores and keeps state whose size does not depend on the
stream's length. ``replay`` runs a kernel over each key of a table in order; ``score_stream`` keeps it as state of
a streaming query, one kernel a key.
"""

from __future__ import annotations

import math
import pickle
from bisect import bisect_left
from collections import deque
from functools import lru_cache
from itertools import accumulate
from operator import sub

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


class _Cell:
    __slots__ = ("h", "lo", "hi", "q", "cut", "kids")

    def __init__(self, h: float, lo: list[float], hi: list[float]):
        self.h, self.lo, self.hi, self.q, self.cut, self.kids = h, lo, hi, -1, 0.0, None

    def widen(self, x: list[float]) -> bool:
        """Stretches the box to hold x; whether that was needed."""
        lo, hi, moved = self.lo, self.hi, False
        for q, v in enumerate(x):
            if v < lo[q]:
                lo[q], moved = v, True
            if v > hi[q]:
                hi[q], moved = v, True
        return moved


@lru_cache
def _leaf_terms(eta: int, clamp: bool, most: int) -> list[float]:
    """What a leaf of each height up to ``most`` adds to its depth."""
    terms = [math.log2(max(h, 1e-12) / eta) for h in range(most + 1)]
    return [max(0.0, v) for v in terms] if clamp else terms


def _total(v: list[float]) -> float:
    """The sum in the order in which numpy adds up to 128 numbers."""
    if len(v) > 128:
        return float(np.add.reduce(v))
    out, at = 0.0, 0
    if len(v) >= 8:
        r, at = v[:8], 8
        while at + 8 <= len(v):
            r, at = [a + b for a, b in zip(r, v[at : at + 8], strict=True)], at + 8
        out = ((r[0] + r[1]) + (r[2] + r[3])) + ((r[4] + r[5]) + (r[6] + r[7]))
    for x in v[at:]:
        out += x
    return out


class AdaptiveHistogramForest:
    """Trees of histograms that split where the last ``omega`` points are dense and merge where they thin out.

    A leaf at depth k splits at eta * 2**k points, with a random cut; its children start from points drawn in its
    box. Forgetting lowers heights and merges a node that falls under the same bound. ``omega`` > ``eta``.
    Boxes and points are lists: at these lengths they are faster than arrays.
    """

    def __init__(self, omega: int = 2048, trees: int = 32, eta: int = 32, seed: int = 1, clamp: bool = True, forget: str = "buffer"):
        if omega <= eta:
            raise ValueError("omega must exceed eta")
        if forget not in ("buffer", "sampled"):
            raise ValueError(f"unknown way to forget: {forget}")
        self.omega, self.eta, self.clamp, self.forget, self.seen = omega, eta, clamp, forget, 0
        self.limit = math.log2(omega / eta)
        self.bounds = [eta * 2**k for k in range(math.ceil(self.limit) + 2)]
        self.window: deque = deque()
        self.rng = np.random.Generator(np.random.PCG64(seed))
        self.roots: list[_Cell | None] = [None] * trees

    def step(self, x: np.ndarray) -> float:
        return self._step(np.asarray(x, float).tolist())

    def run(self, x: np.ndarray, at_once: int = 16_384) -> np.ndarray:
        """The scores of ``step`` on each row in turn."""
        x, out = np.asarray(x, float), np.zeros(len(x))
        for at in range(0, len(x), at_once):  # lists of few rows at a time
            out[at : at + at_once] = [self._step(row) for row in x[at : at + at_once].tolist()]
        return out

    def _step(self, x: list[float]) -> float:
        self.seen += 1
        at = [self._learn(t, x) for t in range(len(self.roots))]
        if self.forget == "buffer":
            self.window.append(x)
            if len(self.window) > self.omega:
                gone = self.window.popleft()
                for t, root in enumerate(self.roots):
                    if self._forget(root, gone):
                        at[t] = None
        elif self.seen > self.omega:  # no buffer: each tree forgets a point drawn from its own histogram
            for t, root in enumerate(self.roots):
                if self._forget(root, self._drawn(root)):
                    at[t] = None
        terms, depths = _leaf_terms(self.eta, self.clamp, 2 * self.omega), []
        for root, leaf in zip(self.roots, at, strict=True):
            depths.append(leaf[1] + terms[leaf[0].h] if leaf is not None and leaf[0].h < len(terms) else self.depth(root, x))
        return 2.0 ** (-_total(depths) / len(depths) / self.limit)

    def _learn(self, t: int, x: list[float]) -> tuple[_Cell, int] | None:
        """Counts x along its path; its leaf and the leaf's depth, or None where the leaf was divided."""
        node = self.roots[t]
        if node is None:
            node = self.roots[t] = _Cell(0, x.copy(), x.copy())
        depth = 0
        while True:
            node.h += 1
            kids = node.kids
            if kids is None:
                break
            node = kids[x[node.q] > node.cut]
            depth += 1
        for v, a, b in zip(x, node.lo, node.hi):  # noqa: B905  strict costs time here
            if v < a or v > b:
                self._widen(self.roots[t], x)
                break
        if node.h >= self.bounds[depth] and depth < self.limit:
            self._divide(node)
            return None
        return node, depth

    def _widen(self, node: _Cell, x: list[float]) -> None:
        path = [node]
        while node.kids is not None:
            node = node.kids[x[node.q] > node.cut]
            path.append(node)
        for above in reversed(path):  # a box lies within the box above it
            if not above.widen(x):
                break

    def _divide(self, node: _Cell) -> None:
        q = int(self.rng.integers(len(node.lo)))
        cut = float(self.rng.uniform(node.lo[q], node.hi[q]))
        drawn = self.rng.uniform(node.lo, node.hi, (int(node.h), len(node.lo)))
        right = drawn[:, q] > cut
        node.q, node.cut, node.kids = q, cut, []
        for side in (~right, right):
            part = drawn[side]
            if len(part):
                node.kids.append(_Cell(len(part), part.min(axis=0).tolist(), part.max(axis=0).tolist()))
            else:  # an empty side starts as a point on the cut
                at = [(a + b) / 2 for a, b in zip(node.lo, node.hi, strict=True)]
                at[q] = cut
                node.kids.append(_Cell(0, at.copy(), at.copy()))

    def _forget(self, node: _Cell, x: list[float]) -> bool:
        """Lowers the heights along the path of x; whether a node was merged."""
        for bound in self.bounds:
            h = node.h
            h = node.h = h - 1 if h > 1 else 0
            kids = node.kids
            if kids is None:
                return False
            if h < bound:
                a, b = kids
                node.lo, node.hi = list(map(min, a.lo, b.lo)), list(map(max, a.hi, b.hi))
                node.q, node.kids = -1, None
                return True
            node = kids[x[node.q] > node.cut]
        return False

    def _drawn(self, node: _Cell) -> list[float]:
        """A point of a leaf, leaves by their heights."""
        random = self.rng.random
        while node.kids is not None:
            a, b = node.kids
            total = a.h + b.h
            node = b if total > 0 and random() * total >= a.h else a
        return [lo + (hi - lo) * u for lo, hi, u in zip(node.lo, node.hi, random(len(node.lo)).tolist(), strict=True)]

    def size(self) -> int:
        """Nodes of all trees and points of the buffer: what the state grows with."""
        nodes, todo = 0, [r for r in self.roots if r is not None]
        while todo:
            n = todo.pop()
            nodes += 1
            todo += n.kids or []
        return nodes + len(self.window)

    def depth(self, node: _Cell, x: np.ndarray) -> float:
        k = 0
        while node.kids is not None:
            node, k = node.kids[int(x[node.q] > node.cut)], k + 1
        return k + (max(0.0, math.log2(max(node.h, 1e-12) / self.eta)) if self.clamp else math.log2(max(node.h, 1e-12) / self.eta))


def expected_depth(omega: int, eta: int) -> tuple[int, int]:
    """Average and worst depth of a tree that has seen a full window."""
    return math.floor(0.5 * math.log2(omega / eta) + 1), math.floor(math.log2((omega + 1) / eta) + 1)


class HalfSpaceTrees:
    """Complete trees of mid-point cuts on scaled data; a score from the mass of the previous window, low mass is anomalous. Until a first window is full every score is 0.5."""

    def __init__(self, d: int, window: int = 250, trees: int = 32, depth: int = 15, seed: int = 1):
        rng = np.random.Generator(np.random.PCG64(seed))
        self.window, self.depth, self.trees = window, depth, trees
        centre = rng.random((trees, d))
        reach = 2 * np.maximum(centre, 1 - centre)
        self.lo, self.hi = centre - reach, centre + reach
        self.seed, self.seen = seed, 0
        self.now: list[dict] = [{} for _ in range(trees)]
        self.old: list[dict] = [{} for _ in range(trees)]

    def step(self, x: np.ndarray) -> float:
        total = 0.0
        for t in range(self.trees):
            lo, hi, node, score, now, old = self.lo[t].copy(), self.hi[t].copy(), 1, None, self.now[t], self.old[t]
            for k in range(self.depth + 1):
                now[node] = now.get(node, 0) + 1
                mass = old.get(node, 0)
                if score is None and (mass <= 0.1 * self.window or k == self.depth):
                    score = mass * 2.0**k
                q = (node * 2654435761 + t * 40503 + self.seed) % len(lo)
                mid = (lo[q] + hi[q]) / 2
                node = node * 2 + int(x[q] >= mid)
                (lo if x[q] >= mid else hi)[q] = mid
            total += score
        early = self.seen < self.window
        self.seen += 1
        if self.seen % self.window == 0:
            self.old, self.now = self.now, [{} for _ in range(self.trees)]
        return 0.5 if early else 1 / (1 + total / self.trees / self.window)

    def run(self, x: np.ndarray) -> np.ndarray:
        """The scores of ``step`` on each row in turn. What a row is scored by is fixed within a window, so a window's rows go down the trees together."""
        if self.depth > 30:  # node numbers times the multiplier would leave 64 bits
            return np.array([self.step(row) for row in x])
        x, out, at = np.asarray(x, float), np.zeros(len(x)), 0
        while at < len(x):
            rows = x[at : at + self.window - self.seen % self.window]
            total = np.zeros(len(rows))
            for t in range(self.trees):
                total += self._tree_scores(t, rows)
            out[at : at + len(rows)] = np.where(self.seen + np.arange(len(rows)) < self.window, 0.5, 1 / (1 + total / self.trees / self.window))
            at, self.seen = at + len(rows), self.seen + len(rows)
            if self.seen % self.window == 0:
                self.old, self.now = self.now, [{} for _ in range(self.trees)]
                whole = min(len(x) - at, max(1, 16_384 // self.window) * self.window) // self.window * self.window
                if len(rows) == self.window and whole:
                    out[at : at + whole] = self._windows(x[at - self.window : at + whole])
                    at, self.seen = at + whole, self.seen + whole
        return out

    def _windows(self, x: np.ndarray) -> np.ndarray:
        """The scores of whole windows after the first one in ``x``, which has been counted already.

        A node of level k is the first k + 1 bits of the leaves below it, so among the sorted leaves of a window its mass is a range.
        """
        window = np.arange(len(x)) // self.window << (self.depth + 1)
        total = np.zeros(len(x) - self.window)
        for t in range(self.trees):
            leaf = self._leaves(t, x)
            order = np.argsort(window + leaf, kind="stable")
            key = (window + leaf)[order]
            each = order[self.window :]  # sorted by window first, so these are the rows after the first window
            before, own, score = window[each] - (1 << (self.depth + 1)), leaf[each], np.zeros(len(x))
            for k in range(self.depth + 1):
                below = self.depth - k
                first = before + (own >> below << below)
                mass = np.searchsorted(key, first + (1 << below)) - np.searchsorted(key, first)
                ends = (mass <= 0.1 * self.window) | (k == self.depth)
                score[each[ends]] = mass[ends] * 2.0**k
                each, before, own = each[~ends], before[~ends], own[~ends]
                if not len(each):
                    break
            total += score[self.window :]
            count: dict = {}
            met, times = np.unique(leaf[-self.window :], return_counts=True)
            for n, c in zip(met.tolist(), times.tolist(), strict=True):
                while n:
                    count[n] = count.get(n, 0) + c
                    n >>= 1
            self.old[t] = count
        return 1 / (1 + total / self.trees / self.window)

    def _leaves(self, t: int, x: np.ndarray) -> np.ndarray:
        """The deepest node of each row."""
        lo, hi, node = np.repeat(self.lo[t], len(x)), np.repeat(self.hi[t], len(x)), np.ones(len(x), np.int64)
        each, flat = np.arange(len(x)), np.ascontiguousarray(x.T).ravel()
        for _ in range(self.depth):
            at = (node * 2654435761 + t * 40503 + self.seed) % x.shape[1] * len(x) + each
            low, high = lo[at], hi[at]
            mid = (low + high) / 2
            right = flat[at] >= mid
            node = node * 2 + right
            lo[at], hi[at] = np.where(right, mid, low), np.where(right, high, mid)
        return node

    def _tree_scores(self, t: int, x: np.ndarray) -> np.ndarray:
        """Counts the rows in every node they pass and returns the mass each is scored by."""
        each, now, old = np.arange(len(x)), self.now[t], self.old[t]
        lo, hi, node = np.repeat(self.lo[t][None], len(x), axis=0), np.repeat(self.hi[t][None], len(x), axis=0), np.ones(len(x), np.int64)
        score, open_ = np.zeros(len(x)), np.ones(len(x), bool)
        for k in range(self.depth + 1):
            met, back, count = np.unique(node, return_inverse=True, return_counts=True)
            for n, c in zip(met.tolist(), count.tolist(), strict=True):
                now[n] = now.get(n, 0) + c
            mass = np.array([old.get(n, 0) for n in met.tolist()])[back]
            ends = open_ & ((mass <= 0.1 * self.window) | (k == self.depth))
            score[ends] = mass[ends] * 2.0**k
            open_ &= ~ends
            q = (node * 2654435761 + t * 40503 + self.seed) % x.shape[1]
            mid = (lo[each, q] + hi[each, q]) / 2
            right = x[each, q] >= mid
            node = node * 2 + right
            lo[each[right], q[right]] = mid[right]
            hi[each[~right], q[~right]] = mid[~right]
        return score

    def size(self) -> int:
        return sum(map(len, self.now)) + sum(map(len, self.old))


class WindowAxisForest:
    """Axis-parallel isolation forest over the last window, rebuilt when the share of high scores drifts."""

    def __init__(self, omega: int = 2048, trees: int = 32, psi: int = 256, drift: float = 0.5, seed: int = 1):
        self.omega, self.trees, self.psi, self.drift, self.seed = omega, trees, psi, drift, seed
        self.buffer: list[np.ndarray] = []
        self.forest, self.high, self.built = None, 0, 0

    def step(self, x: np.ndarray) -> float:
        from ..operators.isolation import Forest

        self.buffer.append(np.asarray(x, np.float32))
        if self.forest is None and len(self.buffer) >= min(self.psi, self.omega):
            self.forest = Forest("axis", min(self.psi, len(self.buffer)), seed=self.seed).fit(np.array(self.buffer), self.trees)
        if self.forest is None:
            return 0.5
        score = float(self.forest.score(self.buffer[-1][None])[0])
        self.high += score > 0.5
        if len(self.buffer) >= self.omega:
            if self.high > self.drift * self.omega or not self.built:
                self.built += 1
                self.forest = Forest("axis", self.psi, seed=self.seed + self.built).fit(np.array(self.buffer), self.trees)
            self.buffer, self.high = [], 0
        return score

    def run(self, x: np.ndarray) -> np.ndarray:
        """The scores of ``step`` on each row in turn. The forest changes only where a window ends, so the rows before that are scored together."""
        x, out, at = np.asarray(x, np.float32), np.zeros(len(x)), 0
        while at < len(x):
            room = self.omega - len(self.buffer) - 1  # rows up to the one that may change the forest
            if self.forest is None or room < 1:
                out[at], at = self.step(x[at]), at + 1
                continue
            rows = x[at : at + room]
            out[at : at + len(rows)] = score = self.forest.score(rows)
            self.buffer += list(rows)
            self.high, at = self.high + int((score > 0.5).sum()), at + len(rows)
        return out


class PeriodicAxisForest:
    """The offline forest retrained after every ``omega`` points, without a look at drift."""

    def __init__(self, omega: int = 2048, trees: int = 32, psi: int = 256, seed: int = 1):
        self.omega, self.trees, self.psi, self.seed = omega, trees, psi, seed
        self.buffer: list[np.ndarray] = []
        self.forest, self.built = None, 0

    def step(self, x: np.ndarray) -> float:
        from ..operators.isolation import Forest

        self.buffer.append(np.asarray(x, np.float32))
        if len(self.buffer) >= (self.omega if self.built else min(self.psi, self.omega)):
            self.built += 1
            self.forest = Forest("axis", min(self.psi, len(self.buffer)), seed=self.seed + self.built).fit(np.array(self.buffer), self.trees)
            self.buffer = []
        return 0.5 if self.forest is None else float(self.forest.score(np.asarray(x, np.float32)[None])[0])

    def run(self, x: np.ndarray) -> np.ndarray:
        """The scores of ``step`` on each row in turn, the rows between two forests together."""
        x, out, at = np.asarray(x, np.float32), np.zeros(len(x)), 0
        while at < len(x):
            room = self.omega - len(self.buffer) - 1
            if self.forest is None or room < 1:
                out[at], at = self.step(x[at]), at + 1
                continue
            rows = x[at : at + room]
            out[at : at + len(rows)] = self.forest.score(rows)
            self.buffer += list(rows)
            at += len(rows)
        return out


class RandomCutForest:
    """Trees cut in proportion to side lengths, with insertion and deletion; the score is the largest displacement ratio on the path."""

    def __init__(self, trees: int = 32, psi: int = 256, seed: int = 1):
        self.psi, self.rng = psi, np.random.Generator(np.random.PCG64(seed))
        self.roots: list[list | None] = [None] * trees
        self.window: deque = deque()
        self.drawn: list[float] = []  # the next draws, last first

    # a node is [lo, hi, size, q, cut, left, right, parent]; points and boxes are lists and never changed in place
    def _insert(self, t: int, x: list[float]) -> list:
        leaf = [x, x, 1, -1, 0.0, None, None, None]
        node, parent, side, drawn = self.roots[t], None, 0, self.drawn
        if node is None:
            self.roots[t] = leaf
            return leaf
        while True:
            lo = [a if a < v else v for a, v in zip(node[0], x)]  # noqa: B905  strict costs a third here
            hi = [b if b > v else v for b, v in zip(node[1], x)]  # noqa: B905
            ends = list(accumulate(map(sub, hi, lo)))
            total = ends[-1]
            if total > 0:
                if not drawn:
                    drawn += self.rng.random(4096)[::-1].tolist()
                r = total * drawn.pop()
                q = bisect_left(ends, r, 0, len(ends) - 1)
                cut = lo[q] + ends[q] - r
                if cut < node[0][q] or cut >= node[1][q]:
                    left = x[q] <= cut
                    top = [lo, hi, node[2] + 1, q, cut, leaf if left else node, node if left else leaf, parent]
                    leaf[7] = node[7] = top
                    self._attach(t, parent, side, top)
                    break
            if node[5] is None:  # a repeated point: it stands beside its copy
                top = [lo, hi, node[2] + 1, 0, x[0], node, leaf, parent]
                leaf[7] = node[7] = top
                self._attach(t, parent, side, top)
                break
            node[0], node[1] = lo, hi
            node[2] += 1
            parent, side = node, 5 if x[node[3]] <= node[4] else 6
            node = node[side]
        return leaf

    def _attach(self, t: int, parent, side: int, node) -> None:
        if parent is None:
            self.roots[t] = node
        else:
            parent[side] = node

    def _delete(self, t: int, leaf: list) -> None:
        parent = leaf[7]
        if parent is None:
            self.roots[t] = None
            return
        sibling = parent[6] if parent[5] is leaf else parent[5]
        above = parent[7]
        sibling[7] = above
        self._attach(t, above, 5 if above is not None and above[5] is parent else 6, sibling)
        shrinks = True
        while above is not None:
            above[2] -= 1
            if shrinks:  # boxes above one that stays the same stay the same
                a, b = above[5], above[6]
                lo, hi = [u if u < v else v for u, v in zip(a[0], b[0])], [u if u > v else v for u, v in zip(a[1], b[1])]  # noqa: B905
                shrinks = lo != above[0] or hi != above[1]
                above[0], above[1] = lo, hi
            above = above[7]

    def step(self, x: np.ndarray) -> float:
        return self._step(np.asarray(x, float).tolist())

    def run(self, x: np.ndarray) -> np.ndarray:
        """The scores of ``step`` on each row in turn."""
        x, out = np.asarray(x, float), np.zeros(len(x))
        for at in range(0, len(x), 16_384):  # lists of few rows at a time
            out[at : at + 16_384] = [self._step(row) for row in x[at : at + 16_384].tolist()]
        return out

    def _step(self, x: list[float]) -> float:
        leaves, total = [], 0.0
        for t in range(len(self.roots)):
            leaf = self._insert(t, x)
            leaves.append(leaf)
            own, above, best = 1, leaf[7], 0.0
            while above is not None:
                size = above[2]
                ratio = (size - own) / own
                if ratio > best:
                    best = ratio
                own, above = size, above[7]
            total += best
        self.window.append(leaves)
        if len(self.window) > self.psi:
            for t, leaf in enumerate(self.window.popleft()):
                self._delete(t, leaf)
        return total / len(self.roots)


class ProjectionHistograms:
    """Equal-width histograms of sparse random projections; mean negative log density of what was seen."""

    def __init__(self, d: int, cuts: int = 32, bins: int = 100, seed: int = 1, warm: int = 256):
        rng = np.random.Generator(np.random.PCG64(seed))
        self.w = np.zeros((cuts, d))
        k = max(1, int(math.sqrt(d)))
        for row in self.w:
            row[rng.choice(d, k, replace=False)] = rng.normal(size=k)
        self.bins, self.warm, self.first, self.counts, self.n = bins, warm, [], None, 0

    def step(self, x: np.ndarray) -> float:
        z = self.w @ np.asarray(x, float)
        if self.counts is None:
            self.first.append(z)
            if len(self.first) < self.warm:
                return 0.0
            f = np.array(self.first)
            self.lo, self.width = f.min(axis=0), np.maximum((f.max(axis=0) - f.min(axis=0)) / self.bins, 1e-12)
            self.counts = np.zeros((len(z), self.bins + 2))
            for row in f:
                self._add(row)
            self.first = []
            return self._score(z)
        self._add(z)
        return self._score(z)

    def run(self, x: np.ndarray) -> np.ndarray:
        """The scores of ``step`` on each row in turn: a row's count is that before these rows and its rank among those in the same bin."""
        x, at, out = np.asarray(x, float), 0, np.zeros(len(x))
        while at < len(x) and self.counts is None:
            out[at], at = self.step(x[at]), at + 1
        for at in range(at, len(x), 16_384):
            z = np.array([self.w @ row for row in x[at : at + 16_384]])
            bins, each = self._bin(z), np.arange(len(z))
            count = np.empty(z.shape)
            for j, own in enumerate(bins.T):
                order = np.argsort(own, kind="stable")
                first = np.cumsum(met := np.bincount(own, minlength=self.bins + 2)) - met
                count[order, j] = self.counts[j][own[order]] + each - first[own[order]] + 1
                self.counts[j] += met
            density = (count + 1) / (self.n + 1 + each + self.bins)[:, None] / self.width
            out[at : at + len(z)] = -np.log(density).mean(axis=1)
            self.n += len(z)
        return out

    def _bin(self, z):
        return np.clip(np.floor((z - self.lo) / self.width), -1, self.bins).astype(int) + 1

    def _add(self, z):
        self.counts[np.arange(len(z)), self._bin(z)] += 1
        self.n += 1

    def _score(self, z):
        density = (self.counts[np.arange(len(z)), self._bin(z)] + 1) / (self.n + self.bins) / self.width
        return float(-np.log(density).mean())


KERNELS = {
    "adaptive": lambda d, seed, **k: AdaptiveHistogramForest(seed=seed, **k),
    "half_space": lambda d, seed, **k: HalfSpaceTrees(d, seed=seed, **k),
    "window_axis": lambda d, seed, **k: WindowAxisForest(seed=seed, **k),
    "periodic_axis": lambda d, seed, **k: PeriodicAxisForest(seed=seed, **k),
    "cut_forest": lambda d, seed, **k: RandomCutForest(seed=seed, **k),
    "projections": lambda d, seed, **k: ProjectionHistograms(d, seed=seed, **k),
}


def replay(df: DataFrame, features: list[str], order: list[str], method: str = "adaptive", key: str | None = None, seed: int = 1, segment: int | None = None, warm: int = 4096, keep: tuple[str, ...] = (), **how) -> DataFrame:
    """Batch twin of the stream: each key's rows in order through one kernel. Output: the order columns, key, the columns to ``keep`` and score.

    With ``segment`` the stream is dealt into runs of about that many ids of the first (integer) order column; a task
    scores one run after it has learned from the rows of the ``warm`` ids before it. Kernels remember a bounded window,
    so tasks stay small and independent; the first run equals the plain replay.
    """
    keyed = df.withColumn("_key", F.col(key).cast("string") if key else F.lit("all")).select("_key", *order, *keep, *[F.col(f).cast("double").alias(f) for f in features])
    schema = keyed.select("_key", *order, *keep).schema.add("score", "double")
    if segment:
        own, ahead = F.floor(F.col(order[0]) / segment), F.floor((F.col(order[0]) + warm) / segment)
        keyed = keyed.withColumn("_run", F.explode(F.sequence(own, ahead))).withColumn("_own", own == F.col("_run"))
    else:
        keyed = keyed.withColumn("_run", F.lit(0).cast("long")).withColumn("_own", F.lit(True))

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(order, kind="stable")
        own = pdf["_own"].to_numpy(bool)
        if not own.any():  # nothing but warm-up rows after the last run
            return pdf[["_key", *order, *keep]].head(0).assign(score=pd.Series(dtype=float))
        kernel = KERNELS[method](len(features), seed, **how)
        x = pdf[features].to_numpy(float)
        ok = np.isfinite(x).all(axis=1)
        score = np.full(len(x), np.nan)
        score[ok] = kernel.run(x[ok]) if hasattr(kernel, "run") else [kernel.step(row) for row in x[ok]]
        return pdf[["_key", *order, *keep]].assign(score=score)[own]

    return keyed.repartition(64, "_key", "_run").groupBy("_key", "_run").applyInPandas(run, schema)  # stated since adaptive execution sees small rows and not their steps


def score_stream(stream: DataFrame, features: list[str], order: str, key: str, method: str = "adaptive", seed: int = 1, **how) -> DataFrame:
    """Streaming twin: one kernel a key as state, pickled; rows of a micro-batch are taken in order. Output: key, order, score."""
    from pyspark.sql.streaming.state import GroupStateTimeout

    def run(k, frames, state):
        rows = pd.concat(list(frames)).sort_values(order, kind="stable")
        kernel = pickle.loads(state.get[0]) if state.exists else KERNELS[method](len(features), seed, **how)
        scores = [kernel.step(r) for r in rows[features].to_numpy(float)]
        state.update((pickle.dumps(kernel),))
        yield pd.DataFrame({key: rows[key], order: rows[order], "score": scores})

    kinds = {f.name: f.dataType.simpleString() for f in stream.schema}
    return stream.groupBy(key).applyInPandasWithState(run, f"{key} {kinds[key]}, {order} {kinds[order]}, score double", "kernel binary", "append", GroupStateTimeout.NoTimeout)
