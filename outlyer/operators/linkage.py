"""Structure recovery: single linkage gated by a robust information criterion, and the clusterings it is compared with."""

from __future__ import annotations

import heapq
import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .families import FAMILIES, Family
from .isolation import distance, preference


def capped(ratio: np.ndarray, family: Family, square: str = "inside") -> np.ndarray:
    """Residuals over the noise, squared and capped at r - d; with ``square`` "outside" capped first and then squared."""
    if square not in ("inside", "outside"):
        raise ValueError(f"unknown place of the square: {square}")
    most = family.r - family.d
    return np.minimum(ratio**2, most) if square == "inside" else np.minimum(ratio, most) ** 2


def info_cost(x: np.ndarray, family: Family, theta: np.ndarray | None, sigma: float, lam1: float = 1.0, lam2: float = 2.0, square: str = "inside") -> float:
    """Capped squared residuals plus the price of points on a d-manifold and of K parameters."""
    if theta is None:
        return math.inf
    return float(capped(family.residual(x, theta) / sigma, family, square).sum() + lam1 * family.d * len(x) + lam2 * family.K)


def merge_decision(u: np.ndarray, v: np.ndarray, families: list[Family], sigma: float, lam1: float = 1.0, lam2: float = 2.0) -> tuple[bool, Family | None]:
    """Merge if the best union costs no more than the best separate pair of one family; None if no family fits yet."""
    both = np.vstack([u, v])
    able = [f for f in families if min(len(u), len(v)) >= f.s]
    if not able:
        return False, None
    union = [(info_cost(both, f, f.fit(both), sigma, lam1, lam2), f) for f in able]
    apart = min(info_cost(u, f, f.fit(u), sigma, lam1, lam2) + info_cost(v, f, f.fit(v), sigma, lam1, lam2) for f in able)
    best = min(union, key=lambda c: c[0])
    return best[0] <= apart, best[1]


def significant(x: np.ndarray, models: list, eps: float, k: float = 3.0, ratio: float = 0.75) -> list:
    """Drops models whose support grows about k-fold within k eps, as a chance model's does."""
    out = []
    for family, theta in models:
        delta = family.residual(x, theta)
        close = (delta <= eps).sum()
        if close > family.s and (delta <= k * eps).sum() < ratio * k * close:
            out.append((family, theta))
    return out


def criterion_linkage(x: np.ndarray, models: list, families: list[Family], eps: float, lam1: float = 1.0, lam2: float = 2.0, orthogonal: bool = False, counters: dict | None = None) -> tuple[np.ndarray, dict[int, str]]:
    """Cluster of each point and each cluster's family. Pairs that share no model are candidates only with ``orthogonal``. ``counters`` receives models, edges, merges and refusals.

    The edges are taken in order of distance; a pair of clusters that is refused is tried again only after one
    of them has grown. Clusters too small for any family merge when one sampled model explains all their points.
    """
    sigma = eps / math.sqrt(-math.log(0.05))
    p = preference(x, models, eps, "gauss05")
    holds = p > 0
    d = distance(p, p, "tanimoto")
    a, b = np.nonzero(np.triu(d < (1.5 if orthogonal else 1 - 1e-9), 1))
    order = np.lexsort((b, a, d[a, b]))
    count = {"models": len(models), "edges": len(a), "merges": 0, "refusals": 0}
    near: dict[int, dict[int, float]] = {i: {} for i in range(len(x))}
    heap = []
    for i, j, w in zip(a[order].tolist(), b[order].tolist(), d[a[order], b[order]].tolist(), strict=True):
        near[i][j] = near[j][i] = w
        heap.append((w, i, j))
    heapq.heapify(heap)
    points = {i: [i] for i in range(len(x))}
    shared = {i: holds[i] for i in range(len(x))}
    family_of: dict[int, str] = {}
    fresh = len(x)
    while heap:
        w, i, j = heapq.heappop(heap)
        if i not in points or j not in points or near[i].get(j) != w:
            continue
        ok, family = merge_decision(x[points[i]], x[points[j]], families, sigma, lam1, lam2)
        if family is None:
            ok = bool((shared[i] & shared[j]).any())
        count["merges" if ok else "refusals"] += 1
        if not ok:
            near[i].pop(j)
            near[j].pop(i)
            continue
        new, fresh = fresh, fresh + 1
        points[new] = points.pop(i) + points.pop(j)
        shared[new] = shared.pop(i) & shared.pop(j)
        if family is not None:
            family_of[new] = family.name
        merged: dict[int, float] = {}
        for old in (i, j):
            for other, value in near.pop(old).items():
                if other not in (i, j):
                    merged[other] = min(value, merged.get(other, 2.0))
                    near[other].pop(old, None)
        near[new] = merged
        for other, value in merged.items():
            near[other][new] = value
            heapq.heappush(heap, (value, other, new))
    if counters is not None:
        counters.update(count)
    return _labelled(points, len(x), family_of)


def _labelled(points: dict[int, list[int]], n: int, family_of: dict[int, str]) -> tuple[np.ndarray, dict[int, str]]:
    label, names = np.zeros(n, np.int64), {}
    for c, (key, rows) in enumerate(sorted(points.items(), key=lambda kv: (-len(kv[1]), min(kv[1]))), 1):
        label[rows] = c
        if key in family_of:
            names[c] = family_of[key]
    return label, names


def cluster_table(x: np.ndarray, label: np.ndarray, names: dict[int, str], families: list[Family], eps: float, lam1: float = 1.0, lam2: float = 2.0) -> list[tuple]:
    """(cluster, family, theta, n, cost, outlier): the cheapest family of each cluster; an outlier has no more points than a family needs and one."""
    sigma, out = eps / math.sqrt(-math.log(0.05)), []
    for c in np.unique(label).tolist():
        rows = x[label == c]
        able = [(info_cost(rows, f, t, sigma, lam1, lam2), f, t) for f in families if len(rows) >= f.s for t in (f.fit(rows),) if t is not None]
        if able:
            named = [a for a in able if a[1].name == names.get(c)]
            cost, f, theta = min(named or able, key=lambda a: a[0])
            theta = refined(rows, f, theta, sigma)
            out.append((c, f.name, theta.tolist(), len(rows), info_cost(rows, f, theta, sigma, lam1, lam2), int(len(rows) <= f.s + 1)))
        else:
            out.append((c, None, None, len(rows), math.inf, 1))
    return out


def refined(x: np.ndarray, family: Family, theta: np.ndarray, sigma: float, steps: int = 3) -> np.ndarray:
    """Gauss-Newton steps on the capped residuals from a least-squares fit; a step that does not lower the cost ends them. Subspaces stay as fitted, hyperplanes keep unit normals."""
    best, cost = theta, info_cost(x, family, theta, sigma)
    if family.name not in FAMILIES:
        return best
    for _ in range(steps):
        r = family.residual(x, best) / sigma
        use = r**2 < family.r - family.d
        if use.sum() < len(best):
            break
        width = 1e-6 * np.maximum(1.0, np.abs(best))
        slope = np.column_stack([(family.residual(x, best + np.where(np.arange(len(best)) == j, width, 0)) / sigma - r) / width[j] for j in range(len(best))])[use]
        step = np.linalg.lstsq(slope, -r[use], rcond=None)[0]
        trial = best + step
        if family.residual is FAMILIES["line"].residual:
            trial = trial / max(np.linalg.norm(trial[:-1]), 1e-12)
        new = info_cost(x, family, trial, sigma)
        if not np.isfinite(new) or new >= cost:
            break
        best, cost = trial, new
    return best


def line_moments(points: DataFrame, by: list[str]) -> DataFrame:
    """Sums that fix the best line of each group; sums of two groups add up to those of their union."""
    x, y = F.col("x0"), F.col("x1")
    return points.groupBy(*by).agg(F.count(F.lit(1)).alias("n"), F.sum(x).alias("sx"), F.sum(y).alias("sy"), F.sum(x * x).alias("sxx"), F.sum(y * y).alias("syy"), F.sum(x * y).alias("sxy"))


def line_angle() -> Column:
    """Direction of the best line from the sums of :func:`line_moments`."""
    n = F.col("n")
    return 0.5 * F.atan2(2 * (F.col("sxy") / n - F.col("sx") * F.col("sy") / n / n), (F.col("sxx") / n - F.col("sx") * F.col("sx") / n / n) - (F.col("syy") / n - F.col("sy") * F.col("sy") / n / n))


def line_costs(points: DataFrame, by: list[str], eps: float, lam1: float = 1.0, lam2: float = 2.0) -> DataFrame:
    """The criterion of :func:`info_cost` for the best line of each group: two passes, one for moments and one for residuals."""
    fits = line_moments(points, by).withColumn("w", line_angle()).select(*by, "n", (F.col("sx") / F.col("n")).alias("mx"), (F.col("sy") / F.col("n")).alias("my"), "w")
    off = -F.sin("w") * (F.col("x0") - F.col("mx")) + F.cos("w") * (F.col("x1") - F.col("my"))
    q = F.least(off * off * (-math.log(0.05) / eps**2), F.lit(1.0))
    return points.join(fits, by).groupBy(*by, "n").agg((F.sum(q) + lam1 * F.first("n") + lam2 * 2).alias("cost"))


def contingency(df: DataFrame, cluster: str, truth: str) -> DataFrame:
    return df.groupBy(cluster, truth).agg(F.count(F.lit(1)).alias("n"))


def matched_error(table: DataFrame, cluster: str, truth: str) -> float:
    """Misclassification error from :func:`contingency`, whose rows are as many as pairs of clusters and classes."""
    rows = table.collect()
    a, b = sorted({r[cluster] for r in rows}), sorted({r[truth] for r in rows})
    cost = np.zeros((len(a), len(b)))
    for r in rows:
        cost[a.index(r[cluster]), b.index(r[truth])] = r["n"]
    cost = cost if len(a) <= len(b) else cost.T
    return 1 - cost[np.arange(len(cost)), assignment(-cost)].sum() / cost.sum()


def linkage_by(points: DataFrame, key: str, families: list[Family], eps: float, multiple: int = 2, seed: int = 1) -> DataFrame:
    """Criterion linkage of every data set of a table: rows of (key, pid, x) to (key, pid, cluster, family). A data set is one task; sets are dealt over the cluster."""
    import pandas as pd

    from .families import sample_models

    def run(k, pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("pid")
        x = np.array(pdf["x"].tolist(), float)
        models = [(f, t) for f in families for t in sample_models(x, f, multiple * len(x), seed)]
        label, names = criterion_linkage(x, significant(x, models, eps) or models, families, eps)
        return pd.DataFrame({key: pdf[key], "pid": pdf["pid"], "cluster": label, "family": [names.get(c) for c in label]})

    kind = dict(points.dtypes)[key]
    return points.select(key, F.col("pid").cast("long").alias("pid"), "x").groupBy(key).applyInPandas(run, f"{key} {kind}, pid long, cluster long, family string")


def centroid_linkage(p: np.ndarray) -> np.ndarray:
    """Clusters represented by the element-wise minimum of their members; merges while a model explains both."""
    points = {i: [i] for i in range(len(p))}
    rep = {i: p[i] for i in range(len(p))}
    d = distance(p, p, "tanimoto")
    heap = [(float(d[i, j]), i, j) for i, j in zip(*np.nonzero(np.triu(d < 1 - 1e-9, 1)), strict=True)]
    heapq.heapify(heap)
    fresh = len(p)
    while heap:
        _, i, j = heapq.heappop(heap)
        if i not in points or j not in points:
            continue
        points[fresh], rep[fresh] = points.pop(i) + points.pop(j), np.minimum(rep.pop(i), rep.pop(j))
        keys = [k for k in points if k != fresh]
        if keys:
            to = distance(rep[fresh][None], np.array([rep[k] for k in keys]), "tanimoto")[0]
            for k, w in zip(keys, to, strict=True):
                if w < 1 - 1e-9:
                    heapq.heappush(heap, (float(w), k, fresh))
        fresh += 1
    return _labelled(points, len(p), {})[0]


def nested_linkage(x: np.ndarray, pools: list[list], eps: float, lam1: float = 1.0, lam2: float = 2.0) -> np.ndarray:
    """Centroid linkage family by family, simplest first; a cluster of a simpler family stays if the criterion prefers it."""
    sigma = eps / math.sqrt(-math.log(0.05))
    best = None
    for models in pools:
        if not models:
            continue
        label = centroid_linkage(preference(x, models, eps, "gauss05"))
        if best is None:
            best, family_of = label, {c: models[0][0] for c in np.unique(label)}
            continue
        new, fresh = best.copy(), int(best.max()) + 1
        for c in np.unique(label):
            rows = label == c
            f = models[0][0]
            if rows.sum() < f.s:
                continue
            old = sum(info_cost(x[best == o], family_of[o], family_of[o].fit(x[best == o]), sigma, lam1, lam2) for o in np.unique(best[rows]) if (best == o).sum() >= family_of[o].s)
            if info_cost(x[rows], f, f.fit(x[rows]), sigma, lam1, lam2) < old:
                new[rows] = fresh
                family_of[fresh] = f
                fresh += 1
        best = new
    return best if best is not None else np.zeros(len(x), np.int64)


def energy_labelling(x: np.ndarray, models: list, eps: float, label_cost: float = 10.0, smooth: float = 0.5, rounds: int = 10, k: int = 5) -> np.ndarray:
    """Data cost, neighbour smoothness and a price per label; alternates assignment and refit. 0 is the outlier label."""
    n = len(x)
    order = np.argsort(distance(x, x, "l2") + np.eye(n) * 1e9, axis=1)[:, :k]
    models = list(models)
    label = np.full(n, -1)
    for _ in range(rounds):
        cost = np.array([np.minimum((f.residual(x, t) / eps) ** 2, 4.0) for f, t in models] + [np.full(n, 1.0)]).T
        if label.max(initial=-1) >= 0:
            for j in range(len(models)):
                cost[:, j] += smooth * (label[order] != j).mean(axis=1)
        # greedy set of labels: the price of a label must be covered by what it saves
        current, used = cost[:, -1].copy(), []
        for _ in range(len(models)):
            saving = np.maximum(current[:, None] - cost[:, :-1], 0).sum(axis=0) - label_cost
            j = int(saving.argmax())
            if saving[j] <= 0:
                break
            used.append(j)
            current = np.minimum(current, cost[:, j])
        choice = np.array([*used, len(models)])
        new = choice[cost[:, choice].argmin(axis=1)]
        new = np.where(new == len(models), -1, new)
        kept, relabelled = [], np.full(n, -1)
        for j in used:
            rows = new == j
            f, t = models[j]
            if rows.sum() >= f.s:
                again = f.fit(x[rows])
                relabelled[rows] = len(kept)
                kept.append((f, again if again is not None else t))
        if kept == [] or np.array_equal(relabelled, label):
            label = relabelled
            break
        models, label = kept, relabelled
    return label + 1


def multi_model_energy(x: np.ndarray, models: list, eps: float, merge: float = 0.6, **how) -> np.ndarray:
    """Modes first: models that agree on most of their inliers become one; then the energy labelling of what is left."""
    inside = [(f.residual(x, t) <= eps) for f, t in models]
    order = sorted(range(len(models)), key=lambda j: -int(inside[j].sum()))
    modes: list[int] = []
    for j in order:
        if all((inside[j] & inside[o]).sum() < merge * min(inside[j].sum(), inside[o].sum()) for o in modes):
            modes.append(j)
    return energy_labelling(x, [models[j] for j in modes], eps, **how)


def progressive_models(x: np.ndarray, models: list, eps: float, least: int = 10) -> np.ndarray:
    """One structure at a time: the model with most unexplained inliers is refitted and taken while it has enough."""
    label, c = np.zeros(len(x), np.int64), 0
    inside = np.array([f.residual(x, t) <= eps for f, t in models]) if models else np.zeros((0, len(x)), bool)
    while len(inside):
        gain = (inside & (label == 0)).sum(axis=1)
        j = int(gain.argmax())
        f, t = models[j]
        if gain[j] < max(least, f.s + 1):
            break
        t = f.fit(x[inside[j] & (label == 0)])
        rows = (f.residual(x, t if t is not None else models[j][1]) <= eps) & (label == 0)
        rows |= inside[j] & (label == 0)
        c += 1
        label[rows] = c
    return label


def preference_factorisation(p: np.ndarray, k: int, rounds: int = 30, seed: int = 0) -> np.ndarray:
    """Low-rank factors of the robust similarity of preferences, then nearest of k centres."""
    s = 1 - distance(p, p, "tanimoto")
    values, vectors = np.linalg.eigh(s)
    z = vectors[:, -k:] * np.sqrt(np.maximum(values[-k:], 0))
    rng = np.random.Generator(np.random.PCG64(seed))
    centre = z[rng.choice(len(z), k, replace=False)]
    for _ in range(rounds):
        label = distance(z, centre, "l2").argmin(axis=1)
        centre = np.array([z[label == j].mean(axis=0) if (label == j).any() else centre[j] for j in range(k)])
    return label + 1


def silhouette(d: np.ndarray, label: np.ndarray) -> float:
    """Mean silhouette from a distance matrix; 0 with one cluster."""
    kinds = np.unique(label)
    if len(kinds) < 2:
        return 0.0
    mean = np.array([d[:, label == c].sum(axis=1) for c in kinds]).T
    size = np.array([(label == c).sum() for c in kinds])
    own = np.searchsorted(kinds, label)
    rows = np.arange(len(label))
    a = mean[rows, own] / np.maximum(size[own] - 1, 1)
    other = mean / size
    other[rows, own] = np.inf
    b = other.min(axis=1)
    s = np.where(size[own] > 1, (b - a) / np.maximum(np.maximum(a, b), 1e-12), 0)
    return float(s.mean())


def tune_eps(x: np.ndarray, families: list[Family], models: list, grid: list[float]) -> float:
    """The threshold of the grid whose clustering has the best silhouette."""
    scored = []
    for eps in grid:
        label, _ = criterion_linkage(x, significant(x, models, eps) or models, families, eps)
        scored.append((silhouette(distance(*(preference(x, models, eps, "gauss05"),) * 2, "tanimoto"), label), -eps))
    return -max(scored)[1]


def assignment(cost: np.ndarray) -> np.ndarray:
    """Column of each row in a cheapest one-to-one assignment (rows <= columns): shortest augmenting paths."""
    n, m = cost.shape
    u, v, match = np.zeros(n + 1), np.zeros(m + 1), np.zeros(m + 1, np.int64)
    for i in range(1, n + 1):
        match[0] = i
        least, via, done = np.full(m + 1, np.inf), np.zeros(m + 1, np.int64), np.zeros(m + 1, bool)
        j = 0
        while match[j]:
            done[j] = True
            row = match[j]
            gap = cost[row - 1] - u[row] - v[1:]
            better = ~done[1:] & (gap < least[1:])
            least[1:][better], via[1:][better] = gap[better], j
            to = int(np.where(done, np.inf, least).argmin())
            step = least[to]
            u[match[done]] += step
            v[done] -= step
            least[~done] -= step
            j = to
        while j:
            match[j] = match[via[j]]
            j = via[j]
    out = np.zeros(n, np.int64)
    out[match[1:][match[1:] > 0] - 1] = np.flatnonzero(match[1:])
    return out


def misclassification_error(label: np.ndarray, truth: np.ndarray) -> float:
    """Share of points that are wrong under the best matching of clusters and classes."""
    a, b = np.unique(label, return_inverse=True)[1], np.unique(truth, return_inverse=True)[1]
    table = np.zeros((a.max() + 1, b.max() + 1))
    np.add.at(table, (a, b), 1)
    if table.shape[0] > table.shape[1]:
        table = table.T
    return 1 - table[np.arange(len(table)), assignment(-table)].sum() / len(label)
