"""Preference embedding and isolation forests: nearest-seed cells, threshold min-hash, axis and oblique cuts; local outlier factor.

Kernels are plain numpy over a batch. On Spark a forest is built from t * psi sampled rows, one task a tree, and
all rows are scored by mapInArrow with the models and the forest broadcast: both have sizes fixed by parameters,
preferences never leave a batch, and scoring does not shuffle.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.rng import bottom_k
from .families import FAMILIES, Family, sample_models

EULER = 0.5772156649015329
AHEAD, FULL = 256, 50_000_000  # models a hash split looks at first; most cells of a dense copy (200 MB)


def c_iso(n: int, b: int = 2) -> float:
    """Average depth of an unsuccessful search among n points in a binary tree; ``b`` branches shorten it by log2(b)."""
    return (0.0 if n <= 1 else 1.0 if n == 2 else 2 * (math.log(n - 1) + EULER) - 2 * (n - 1) / n) / math.log2(max(2, b))


@dataclass
class Sparse:
    """Preferences by row: the entries of row i are cols and vals from starts[i] to starts[i + 1]; m columns in all."""

    starts: np.ndarray
    cols: np.ndarray
    vals: np.ndarray
    m: int
    _full: np.ndarray | None = field(default=None, repr=False, compare=False)

    def __len__(self) -> int:
        return len(self.starts) - 1

    @property
    def shape(self) -> tuple[int, int]:
        return len(self), self.m

    @classmethod
    def of(cls, dense: np.ndarray) -> Sparse:
        rows, cols = np.nonzero(dense)
        return cls(np.searchsorted(rows, np.arange(len(dense) + 1)), cols, dense[rows, cols], dense.shape[1])

    def entries(self, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Places of all entries of the rows, and where each row begins among them."""
        size = self.starts[rows + 1] - self.starts[rows]
        begin = np.cumsum(size) - size
        return np.repeat(self.starts[rows] - begin, size) + np.arange(size.sum()), begin

    def __getitem__(self, rows) -> Sparse:
        rows = np.arange(len(self))[rows]
        at, begin = self.entries(rows)
        return Sparse(np.append(begin, len(at)), self.cols[at], self.vals[at], self.m)

    def dot(self, w: np.ndarray, rows: np.ndarray) -> np.ndarray:
        """Products of the rows with a vector."""
        at, begin = self.entries(rows)
        out = np.zeros(len(rows))
        some = np.flatnonzero(self.starts[rows + 1] > self.starts[rows])
        if len(some):
            out[some] = np.add.reduceat(self.vals[at] * w[self.cols[at]], begin[some])
        return out

    def dense(self) -> np.ndarray:
        out = np.zeros((len(self), self.m), np.float32)
        out[np.repeat(np.arange(len(self)), np.diff(self.starts)), self.cols] = self.vals
        return out

    def full(self) -> np.ndarray | None:
        """:meth:`dense`, made once and kept where at least one cell in fifty is an entry; else None."""
        if 50 * len(self.cols) < len(self) * self.m or len(self) * self.m > FULL:
            return None
        if self._full is None:
            self._full = self.dense()
        return self._full


def sparse_preference(x: np.ndarray, models: list[tuple[Family, np.ndarray]], eps: float | dict[str, float], kind: str = "gauss", k_sigma: float = 3.0) -> Sparse:
    """:func:`preference` without the zeros: memory follows the inliers, not rows times models."""
    rows, cols, vals = [], [], []
    for j, (family, theta) in enumerate(models):
        e = eps[family.name] if isinstance(eps, dict) else eps
        delta = family.residual(x, theta)
        inside = np.flatnonzero(delta <= e)
        rows.append(inside)
        cols.append(np.full(len(inside), j, np.int32))
        vals.append(agreement(delta[inside], e, kind, k_sigma))
    if not rows:
        return Sparse(np.zeros(len(x) + 1, np.int64), np.zeros(0, np.int32), np.zeros(0, np.float32), 0)
    row = np.concatenate(rows)
    order = np.argsort(row, kind="stable")
    return Sparse(np.searchsorted(row[order], np.arange(len(x) + 1)), np.concatenate(cols)[order], np.concatenate(vals)[order].astype(np.float32), len(models))


def agreement(delta: np.ndarray, eps: float, kind: str, k_sigma: float = 3.0) -> np.ndarray:
    """Preference of residuals that lie within eps."""
    if kind == "binary":
        return np.ones(len(delta))
    if kind == "gauss":
        return np.exp(-0.5 * (delta * k_sigma / eps) ** 2)
    if kind == "gauss05":
        return np.exp(delta**2 * math.log(0.05) / eps**2)
    raise ValueError(f"unknown preference kind {kind}")


def preference(x: np.ndarray, models: list[tuple[Family, np.ndarray]], eps: float | dict[str, float], kind: str = "gauss", k_sigma: float = 3.0) -> np.ndarray:
    """(n, m) agreements: 0 beyond eps; inside 1 (``binary``), a Gaussian of scale eps / k (``gauss``) or one worth 0.05 at eps (``gauss05``)."""
    out = np.zeros((len(x), len(models)), np.float32)
    for j, (family, theta) in enumerate(models):
        e = eps[family.name] if isinstance(eps, dict) else eps
        delta = family.residual(x, theta)
        inside = delta <= e
        out[inside, j] = agreement(delta[inside], e, kind, k_sigma)
    return out


def distance(p: np.ndarray, q: np.ndarray, kind) -> np.ndarray:
    """(len(p), len(q)) distances: l2, l1, cosine, jaccard, tanimoto, ruzicka, or any function of (p, q). Preference rows that share nothing are at distance 1."""
    if callable(kind):
        return np.asarray(kind(p, q), float)
    if kind == "l1":
        return np.stack([np.abs(p - row).sum(1) for row in q], axis=1) if len(q) else np.zeros((len(p), 0))
    if kind == "cosine":
        norm = np.sqrt((p**2).sum(1))[:, None] * np.sqrt((q**2).sum(1))[None]
        return 1 - np.divide(p @ q.T, norm, out=np.zeros((len(p), len(q))), where=norm > 0)
    if kind == "l2":
        return np.sqrt(np.maximum((p**2).sum(1)[:, None] + (q**2).sum(1)[None] - 2 * p @ q.T, 0))
    if kind == "jaccard":
        a, b = (p > 0).astype(np.float32), (q > 0).astype(np.float32)
        common = a @ b.T
        whole = a.sum(1)[:, None] + b.sum(1)[None] - common
    elif kind == "tanimoto":
        common = p @ q.T
        whole = (p**2).sum(1)[:, None] + (q**2).sum(1)[None] - common
    elif kind == "ruzicka":
        common = np.stack([np.minimum(p[:, held], row[held]).sum(1) for row in q for held in (np.flatnonzero(row),)], axis=1) if len(q) else np.zeros((len(p), 0))
        whole = p.sum(1)[:, None] + q.sum(1)[None] - common
    else:
        raise ValueError(f"unknown distance {kind}")
    return 1 - np.divide(common, whole, out=np.zeros_like(common), where=whole > 0)


@dataclass
class Node:
    size: int
    depth: int
    split: tuple | None = None
    children: dict | None = None


class Forest:
    """kind: cell (with ``dist``), table (cells on given distances, rows are their numbers), hash, axis or oblique.

    ``b`` branches; None lets a hash split have one branch a model, as it comes out of the hash. ``min_split``: fewest
    points of a node that splits. ``c_base`` "b" scales the expected depth to ``b`` branches, "binary" leaves it at two.
    ``exact`` draws (model, threshold) pairs until one is accepted, which makes collisions equal the similarity.
    """

    def __init__(self, kind: str, psi: int, b: int | None = 2, dist="tanimoto", seed: int = 1, depth_limit: int | None = None, c_base: str = "b", min_split: int | None = None, exact: bool = False, table: np.ndarray | None = None):
        if kind not in ("cell", "table", "hash", "axis", "oblique"):
            raise ValueError(f"unknown forest {kind}")
        if c_base not in ("b", "binary"):
            raise ValueError(f"unknown base {c_base}")
        if b is None and kind != "hash":
            raise ValueError("only hash splits have a branch a model")
        if b is not None and (b < 2 or psi < b):
            raise ValueError("b must be 2 or more and psi at least b")
        self.kind, self.psi, self.b, self.dist, self.seed = kind, psi, b if kind in ("cell", "table", "hash") else 2, dist, seed
        self.c_base, self.exact, self.table = c_base, exact, table
        self.least = max(2, min_split or self.b or 2)
        self.limit = depth_limit or max(1, math.ceil(round(math.log(psi, self.b or 2), 9)))
        self.trees: list[Node] = []

    def _rng(self, *ids: int) -> np.random.Generator:
        return np.random.Generator(np.random.PCG64([self.seed, *ids]))

    def c(self, n: int) -> float:
        return c_iso(n, self.b if self.c_base == "b" and self.b else 2)

    def _draws(self, split: tuple, cols: np.ndarray) -> np.ndarray:
        """The 64-bit draw of each model in a split: threshold in the high half, place in the low one."""
        h = (cols.astype(np.uint64) + np.uint64(hash((self.seed, *split)) & (2**64 - 1))) * np.uint64(0x9E3779B97F4A7C15)
        h ^= h >> np.uint64(31)
        h *= np.uint64(0xBF58476D1CE4E5B9)
        h ^= h >> np.uint64(29)
        h *= np.uint64(0x94D049BB133111EB)
        h ^= h >> np.uint64(32)
        return h

    def _hashed(self, split: tuple, x: Sparse, rows: np.ndarray) -> np.ndarray:
        """Branch of each row. Where rows have many entries the models with the first AHEAD places are looked at before all others: nearly every row accepts one of them."""
        full = x.full() if self.b and not self.exact and x.m > 4 * AHEAD else None
        if full is None or (x.starts[rows + 1] - x.starts[rows]).sum() < 2 * x.m:
            return self._hashed_all(split, x, rows)
        h = self._draws(split, np.arange(x.m))
        place = (h & np.uint64(0xFFFFFFFF)).astype(np.int64)
        ahead = np.argpartition(place, AHEAD)[:AHEAD]
        ahead = ahead[np.argsort(place[ahead], kind="stable")]
        active = full[rows[:, None], ahead] > (h[ahead] >> np.uint64(32)).astype(np.float64) / 2.0**32
        first = active.argmax(axis=1)
        out = place[ahead[first]] % self.b
        late = ~active[np.arange(len(rows)), first]
        if late.any():
            out[late] = self._hashed_all(split, x, rows[late])
        return out

    def _hashed_all(self, split: tuple, x: Sparse, rows: np.ndarray) -> np.ndarray:
        """Branch of each row from its non-zero entries alone: what a draw does to a model is a number, whether a row has the model or not."""
        at, begin = x.entries(rows)
        cols, vals = x.cols[at], x.vals[at]
        none = np.iinfo(np.int64).max
        rng = self._rng(*split) if self.exact or not self.b else None
        if self.exact:  # draws of a model arrive at random times; the first accepted one of all is the hash
            hit, arrive = np.full(len(cols), none), np.zeros(x.m)
            for _ in range(16):  # what is not accepted by then would come last
                arrive += rng.exponential(size=x.m)
                fresh = (hit == none) & (vals > rng.random(x.m)[cols])
                hit[fresh] = ((arrive[cols[fresh]] * 2.0**35).astype(np.int64) << 20) | cols[fresh]
                if (hit < none).all():
                    break
            fold = None
        elif self.b:  # thresholds binarise, the first active model in a random order is folded to b branches by the low bits of its place
            h = self._draws(split, cols)
            hit = np.where(vals > (h >> np.uint64(32)).astype(np.float64) / 2.0**32, (h & np.uint64(0xFFFFFFFF)).astype(np.int64), none)
            fold = None
        else:
            threshold, place = rng.random(x.m), rng.permutation(x.m)
            hit = np.where(vals > threshold[cols], place[cols], none)
            fold = np.arange(x.m + 1)
        first = np.full(len(rows), none)
        some = np.flatnonzero(x.starts[rows + 1] > x.starts[rows])
        if len(some):
            first[some] = np.minimum.reduceat(hit, begin[some])
        if self.exact:
            place = np.where(first == none, x.m, first & (2**20 - 1))
            return place if not self.b else np.where(first == none, hash((self.seed, *split, 1)) % self.b, (first >> 20) % self.b)
        if fold is None:
            return np.where(first == none, hash((self.seed, *split, 1)) % self.b, first % self.b)
        return fold[np.where(first == none, len(fold) - 1, first)]

    def _route(self, split: tuple, x, rows: np.ndarray) -> np.ndarray:
        kind = split[0]
        if kind == "hash":
            return self._hashed(split[1], x, rows)
        if kind == "cell":
            return distance(x[rows], split[1], self.dist).argmin(axis=1)
        if kind == "table":
            return self.table[x[rows, 0][:, None], split[1]].argmin(axis=1)
        if kind == "axis":
            return (x[rows, split[1]] >= split[2]).astype(int)
        full = x.full() if isinstance(x, Sparse) else x
        side = x.dot(split[1], rows) if full is None else full[rows] @ split[1]
        return (side > split[2] @ split[1]).astype(int)

    def _split(self, x, rows: np.ndarray, tree: int, node: int) -> tuple | None:
        rng = self._rng(tree, node)
        if self.kind == "hash":
            return ("hash", (tree, node))
        if self.kind == "cell":
            return ("cell", x[rows[rng.choice(len(rows), self.b, replace=False)]])
        if self.kind == "table":
            return ("table", x[rows[rng.choice(len(rows), self.b, replace=False)], 0])
        if self.kind == "axis":
            for q in rng.permutation(x.shape[1]):  # the first dimension in random order that varies
                lo, hi = x[rows, q].min(), x[rows, q].max()
                if hi > lo:
                    return ("axis", int(q), float(rng.uniform(lo, hi)))
            return None
        full = x.full() if isinstance(x, Sparse) else x
        own = x[rows].dense() if full is None else full[rows]
        lo, hi = own.min(axis=0), own.max(axis=0)
        return ("oblique", rng.normal(size=x.shape[1]).astype(np.float32), rng.uniform(lo, hi).astype(np.float32)) if (hi > lo).any() else None

    def _form(self, x):
        if self.kind == "hash":
            return x if isinstance(x, Sparse) else Sparse.of(x)
        return x.dense() if isinstance(x, Sparse) and self.kind != "oblique" else x

    def build_tree(self, x, tree: int) -> Node:
        def grow(rows: np.ndarray, depth: int, node: int) -> Node:
            made = Node(len(rows), depth)
            if depth >= self.limit or len(rows) < self.least:
                return made
            split = self._split(x, rows, tree, node)
            if split is None:
                return made
            to = self._route(split, x, rows)
            made.split = split
            branches = range(self.b) if self.b else np.unique(to).tolist()
            made.children = {j: grow(rows[to == j], depth + 1, node * (self.b or x.m + 1) + j + 1) for j in branches}
            return made

        return grow(np.arange(len(x)), 0, 1)

    def fit(self, x, trees: int = 100) -> Forest:
        x = self._form(x)
        for t in range(trees):
            pick = self._rng(t, 0, 7).choice(len(x), min(self.psi, len(x)), replace=False)
            self.trees.append(self.build_tree(x[pick], t))
        return self

    def path_lengths(self, x, tree: Node) -> np.ndarray:
        x = self._form(x)
        out = np.zeros(len(x))
        todo = [(tree, np.arange(len(x)))]
        while todo:
            node, rows = todo.pop()
            if node.split is None:
                out[rows] = node.depth + self.c(node.size)
                continue
            to = self._route(node.split, x, rows)
            for j in np.unique(to).tolist():
                child = node.children.get(j)
                if child is None:  # no sampled point took this branch: an empty leaf
                    out[rows[to == j]] = node.depth + 1
                else:
                    todo.append((child, rows[to == j]))
        return out

    def score(self, x) -> np.ndarray:
        if not self.trees or not len(x):
            return np.zeros(len(x))
        x = self._form(x)
        mean = np.mean([self.path_lengths(x, t) for t in self.trees], axis=0)
        return 2.0 ** (-mean / max(self.c(min(self.psi, self.trees[0].size)), 1e-12))

    def counters(self) -> dict[str, int]:
        """Trees, nodes, leaves and greatest depth."""
        nodes = leaves = deepest = 0
        todo = list(self.trees)
        while todo:
            n = todo.pop()
            nodes, leaves, deepest = nodes + 1, leaves + (n.split is None), max(deepest, n.depth)
            todo += (n.children or {}).values()
        return {"trees": len(self.trees), "nodes": nodes, "leaves": leaves, "depth": deepest}


def ordered_residual_similarity(residuals: np.ndarray, step: int = 10) -> np.ndarray:
    """(n, n) similarity of points by the models they are closest to: what the first h, 2h, ... of two orders share, early steps weighing more."""
    n, m = residuals.shape
    order = np.argsort(residuals, axis=1, kind="stable")
    ends = range(step, m - m % step + 1, step)
    weight = 1.0 / np.arange(1, len(ends) + 1)
    out, before = np.zeros((n, n)), np.zeros((n, n))
    held = np.zeros((n, m), np.float32)
    for w, end in zip(weight / weight.sum(), ends, strict=True):
        held[np.arange(n)[:, None], order[:, end - step : end]] = 1
        common = held @ held.T
        out += w * (common - before) / step
        before = common
    return out


def classical_scaling(d: np.ndarray, dims: int = 2) -> np.ndarray:
    """Points in the plane whose distances come near the given ones: eigenvectors of the centred squared distances."""
    centre = np.eye(len(d)) - 1.0 / max(1, len(d))
    values, vectors = np.linalg.eigh(-0.5 * centre @ (d**2) @ centre)
    return vectors[:, ::-1][:, :dims] * np.sqrt(np.maximum(values[::-1][:dims], 0))


def lof(x: np.ndarray, k: int, dist="l2") -> np.ndarray:
    """Local outlier factor under any of the distances; ties by row."""
    return lof_of(distance(x, x, dist), k)


def lof_of(table: np.ndarray, k: int) -> np.ndarray:
    """Local outlier factor from a distance matrix."""
    d, x = table.astype(float), table
    np.fill_diagonal(d, np.inf)
    k = min(k, len(x) - 1)
    if k < 1:
        return np.ones(len(x))
    near = np.argsort(d, axis=1, kind="stable")[:, :k]
    kth = d[np.arange(len(x)), near[:, -1]]
    reach = np.maximum(kth[near], np.take_along_axis(d, near, 1))
    density = k / np.maximum(reach.sum(axis=1), 1e-12)
    return density[near].mean(axis=1) / density


def auc(score: np.ndarray, label: np.ndarray) -> float:
    """Tie-aware area under the curve; nan with one class only."""
    label = np.asarray(label).astype(bool)
    n1, n0 = label.sum(), (~label).sum()
    if not n1 or not n0:
        return float("nan")
    _, inverse, count = np.unique(score, return_inverse=True, return_counts=True)
    rank = (np.cumsum(count) - (count - 1) / 2)[inverse]
    return float((rank[label].sum() - n1 * (n1 + 1) / 2) / n1 / n0)


def fit_scorer(points: DataFrame, family: str | None, eps: float, m: int = 400, trees: int = 100, psi: int = 256, b: int = 2, forest: str = "hash", dist: str = "tanimoto", kind: str = "gauss", seed: int = 1):
    """Models and forest from one bounded sample of ``points`` (pid, x array): max(4 psi, trees * psi / 8) rows at most.

    ``family`` None isolates in ambient space.
    """
    n = points.count()
    rows = bottom_k(points.select("pid", "x"), max(4 * psi, trees * psi // 8), "fit", "pid", total=n, seed=seed).orderBy("pid").collect()
    x = np.array([r["x"] for r in rows], float).reshape(len(rows), -1)
    models = [(FAMILIES[family], t) for t in sample_models(x, FAMILIES[family], m, seed)] if family else None
    embedded = (sparse_preference if forest == "hash" else preference)(x, models, eps, kind) if models is not None else x.astype(np.float32)
    return models, Forest(forest, min(psi, max(b, len(x))), b, dist, seed).fit(embedded, trees) if len(x) >= b else None


def score_points(points: DataFrame, models, forest: Forest | None, eps: float, kind: str = "gauss") -> DataFrame:
    """pid and isolation score; map-only."""
    import pyarrow as pa

    shared = points.sparkSession.sparkContext.broadcast((models, forest))

    def run(batches):
        models_, forest_ = shared.value
        for batch in batches:
            if not batch.num_rows:
                continue
            x = np.array(batch.column(1).to_pylist(), float).reshape(batch.num_rows, -1)
            parts = []
            for at in range(0, len(x), 2048):
                part = x[at : at + 2048]
                e = (sparse_preference if forest_ is not None and forest_.kind == "hash" else preference)(part, models_, eps, kind) if models_ is not None else part.astype(np.float32)
                parts.append(forest_.score(e) if forest_ is not None else np.zeros(len(e)))
            yield pa.record_batch([batch.column(0), pa.array(np.concatenate(parts))], ["pid", "score"])

    return points.select(F.col("pid").cast("long").alias("pid"), "x").mapInArrow(run, "pid long, score double")


def structure_scores(points: DataFrame, family: str | None, eps: float, kind: str = "gauss", **how) -> DataFrame:
    """Fit and score: the batch structure scorer."""
    models, forest = fit_scorer(points, family, eps, kind=kind, **how)
    return score_points(points, models, forest, eps, kind)


def windowed_scores(grid: DataFrame, omega: int, family: str = "plane", eps: float = 0.05, m: int = 60, trees: int = 20, psi: int = 64, b: int = 4, forest: str = "hash", seed: int = 1) -> DataFrame:
    """grid: pid, gx, gy, x array. Half-overlapping windows of side omega, local models and forest in each, mean score of each point.

    ``omega`` as large as the grid is the global scorer. A window has at most omega * omega points.
    """
    half = max(1, omega // 2)
    spots = F.array(*[F.struct((F.floor(F.col("gx") / half) - i).cast("int").alias("wx"), (F.floor(F.col("gy") / half) - j).cast("int").alias("wy")) for i in (0, 1) for j in (0, 1)])
    dealt = grid.select("pid", "x", F.explode(spots).alias("w")).where("w.wx >= 0 and w.wy >= 0").select("pid", "x", "w.wx", "w.wy")
    return _in_windows(dealt, family, eps, m, trees, psi, b, forest, seed)


def _in_windows(dealt: DataFrame, family: str, eps: float, m: int, trees: int, psi: int, b: int, forest: str, seed: int) -> DataFrame:
    import pandas as pd

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("pid")
        x = np.array(pdf["x"].tolist(), float)
        f = FAMILIES[family]
        local = seed * 1_000_003 + (int(key[0]) * 1009 + int(key[1])) % (2**31)
        models = [(f, t) for t in sample_models(x, f, m, local)]
        score = np.zeros(len(x))
        if models and len(x) >= b:
            e = (sparse_preference if forest == "hash" else preference)(x, models, eps)
            score = Forest(forest, min(psi, max(b, len(x))), b, seed=local).fit(e, trees).score(e)
        return pd.DataFrame({"pid": pdf["pid"], "score": score})

    return dealt.groupBy("wx", "wy").applyInPandas(run, "pid long, score double").groupBy("pid").agg(F.avg("score").alias("score"), F.count(F.lit(1)).alias("windows"))


def timed_window_scores(rows: DataFrame, seconds: int, key: str | None = None, family: str = "line", eps: float = 0.05, m: int = 60, trees: int = 20, psi: int = 64, b: int = 4, forest: str = "hash", seed: int = 1) -> DataFrame:
    """The windowed scorer where windows are of time, or of time and a key: rows of pid, ts (seconds), x array in half-overlapping windows of so many seconds."""
    half = max(1, seconds // 2)
    group = F.col(key).cast("string") if key else F.lit("")
    first = F.floor(F.col("ts") / half)
    dealt = rows.select("pid", "x", F.pmod(F.xxhash64(group), F.lit(2**31 - 1)).cast("int").alias("wy"), F.explode(F.array((first - 1).cast("int"), first.cast("int"))).alias("wx"))
    return _in_windows(dealt, family, eps, m, trees, psi, b, forest, seed)


def scores_on_relation(relation: DataFrame, sample: DataFrame, trees: int = 50, psi: int = 64, b: int = 2, far: float = 1.0, seed: int = 1) -> DataFrame:
    """pid and score of a cell forest that knows points by distances only: relation (a, b, d) with b from ``sample`` (pid); pairs it lacks are ``far``.

    ``sample`` has a fixed number of rows; each point's distances to it are one array, so scoring is a map after one aggregation.
    """
    import pyarrow as pa

    ids = sorted(r["pid"] for r in sample.collect())
    place = F.broadcast(relation.sparkSession.createDataFrame([(v, i) for i, v in enumerate(ids)], "b long, place int"))
    rows = relation.join(place, "b").groupBy("a").agg(F.map_from_entries(F.collect_set(F.struct("place", "d"))).alias("near"))

    def table(maps) -> np.ndarray:
        out = np.full((len(maps), len(ids)), far)
        for i, near in enumerate(maps):
            for j, d in near:
                out[i, j] = d
        return out

    own = {r["a"]: list(r["near"].items()) for r in rows.where(F.col("a").isin(ids)).collect()}  # as many rows as the sample
    among = table([own.get(v, []) for v in ids])
    np.fill_diagonal(among, 0)
    forest = Forest("table", min(psi, max(b, len(ids))), b, seed=seed, table=among).fit(np.arange(len(ids))[:, None], trees) if len(ids) >= b else None
    shared = relation.sparkSession.sparkContext.broadcast(forest)

    def run(batches):
        f = shared.value
        for batch in batches:
            if not batch.num_rows:
                continue
            d = table(batch.column(1).to_pylist())
            where = {v: j for j, v in enumerate(ids)}
            for i, a in enumerate(batch.column(0).to_pylist()):
                if a in where:
                    d[i, where[a]] = 0
            score = np.zeros(len(d))
            if f is not None:
                f.table = d
                score = f.score(np.arange(len(d))[:, None])
            yield pa.record_batch([batch.column(0), pa.array(score)], ["pid", "score"])

    return rows.select(F.col("a").cast("long"), "near").mapInArrow(run, "pid long, score double")
