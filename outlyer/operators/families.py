"""Parametric model families: how many points fix a model, a minimal and a least-squares fit, residuals."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np


@dataclass(frozen=True)
class Family:
    """r: ambient dimension, s: minimal sample, d: manifold dimension, K: parameters. ``fit`` takes s or more points."""

    name: str
    r: int
    s: int
    d: int
    K: int
    fit: Callable[[np.ndarray], np.ndarray | None]
    residual: Callable[[np.ndarray, np.ndarray], np.ndarray]

    @staticmethod
    def from_callable(name: str, r: int, s: int, fit, residual, d: int = 1, K: int = 1) -> Family:
        return Family(name, r, s, d, K, fit, residual)


def _smallest(design: np.ndarray) -> np.ndarray:
    return np.linalg.eigh(design.T @ design)[1][:, 0]


def _hyperplane(x: np.ndarray) -> np.ndarray | None:
    centre = x.mean(axis=0)
    values, vectors = np.linalg.eigh((x - centre).T @ (x - centre))
    if len(values) > 1 and values[1] <= 1e-18:
        return None
    return np.append(vectors[:, 0], -vectors[:, 0] @ centre)


def _to_hyperplane(x, theta):
    return np.abs(x @ theta[:-1] + theta[-1])


def _sphere(x: np.ndarray) -> np.ndarray | None:
    design = np.column_stack([x, np.ones(len(x))])
    try:
        w = np.linalg.lstsq(design, -(x**2).sum(axis=1), rcond=None)[0]
    except np.linalg.LinAlgError:
        return None
    centre = -w[:-1] / 2
    square = centre @ centre - w[-1]
    return np.append(centre, np.sqrt(square)) if square > 0 and np.isfinite(square) and square < 1e8 else None


def _to_sphere(x, theta):
    return np.abs(np.linalg.norm(x - theta[:-1], axis=1) - theta[-1])


def _polynomial(degree: int):
    def fit(x):
        design = np.vander(x[:, 0], degree + 1)
        return np.linalg.lstsq(design, x[:, 1], rcond=None)[0] if len(np.unique(x[:, 0])) > degree else None

    def residual(x, theta):
        slope = np.polyval(np.polyder(theta), x[:, 0])
        return np.abs(np.polyval(theta, x[:, 0]) - x[:, 1]) / np.sqrt(1 + slope**2)

    return fit, residual


def _quadratic_terms(x):
    n = x.shape[1]
    pairs = [(i, j) for i in range(n) for j in range(i, n)]
    value = np.column_stack([x[:, i] * x[:, j] for i, j in pairs] + [x, np.ones(len(x))])
    return value, pairs


def _implicit_fit(x):
    value, _ = _quadratic_terms(x)
    return _smallest(value)


def _implicit_residual(x, theta):
    """First-order distance: value over gradient length."""
    value, pairs = _quadratic_terms(x)
    n = x.shape[1]
    gradient = np.tile(theta[len(pairs) : len(pairs) + n], (len(x), 1))
    for c, (i, j) in zip(theta, pairs, strict=False):
        gradient[:, i] += c * x[:, j]
        gradient[:, j] += c * x[:, i]
    return np.abs(value @ theta) / np.maximum(np.linalg.norm(gradient, axis=1), 1e-12)


def _normalised(p):
    centre = p.mean(axis=0)
    scale = np.sqrt(2) / max(1e-12, np.linalg.norm(p - centre, axis=1).mean())
    t = np.array([[scale, 0, -scale * centre[0]], [0, scale, -scale * centre[1]], [0, 0, 1]])
    return np.column_stack([(p - centre) * scale, np.ones(len(p))]), t


def _homography(x):
    a, ta = _normalised(x[:, :2])
    b, tb = _normalised(x[:, 2:])
    zero = np.zeros_like(a)
    design = np.vstack([np.hstack([a, zero, -b[:, :1] * a]), np.hstack([zero, a, -b[:, 1:2] * a])])
    h = np.linalg.solve(tb, _smallest(design).reshape(3, 3)) @ ta
    return h.ravel() / max(np.linalg.norm(h), 1e-12) if abs(np.linalg.det(h)) > 1e-12 else None


def _transfer(x, theta):
    h = theta.reshape(3, 3)
    ones = np.ones((len(x), 1))

    def to(m, p):
        q = np.hstack([p, ones]) @ m.T
        return q[:, :2] / np.where(np.abs(q[:, 2:]) < 1e-12, 1e-12, q[:, 2:])

    return np.sqrt((((to(h, x[:, :2]) - x[:, 2:]) ** 2).sum(1) + ((to(np.linalg.pinv(h), x[:, 2:]) - x[:, :2]) ** 2).sum(1)) / 2)


def _fundamental(x):
    a, ta = _normalised(x[:, :2])
    b, tb = _normalised(x[:, 2:])
    f = _smallest((b[:, :, None] * a[:, None, :]).reshape(len(x), 9)).reshape(3, 3)
    u, s, v = np.linalg.svd(f)
    f = tb.T @ (u @ np.diag([s[0], s[1], 0]) @ v) @ ta
    return f.ravel() / max(np.linalg.norm(f), 1e-12)


def _epipolar(x, theta):
    f = theta.reshape(3, 3)
    ones = np.ones((len(x), 1))
    a, b = np.hstack([x[:, :2], ones]), np.hstack([x[:, 2:], ones])
    fa, fb = a @ f.T, b @ f
    return np.abs((b * fa).sum(1)) / np.sqrt(np.maximum((fa[:, :2] ** 2).sum(1) + (fb[:, :2] ** 2).sum(1), 1e-18))


def subspace(dim: int, ambient: int, affine: bool = True) -> Family:
    """Affine (or linear) subspace of a given dimension; the residual is the norm of the orthogonal part."""

    def fit(x):
        centre = x.mean(axis=0) if affine else np.zeros(x.shape[1])
        basis = np.linalg.svd(x - centre, full_matrices=False)[2][:dim]
        return np.concatenate([centre, basis.ravel()]) if len(basis) == dim else None

    def residual(x, theta):
        n = x.shape[1]
        y, basis = x - theta[:n], theta[n:].reshape(dim, n)
        return np.sqrt(np.maximum((y**2).sum(1) - ((y @ basis.T) ** 2).sum(1), 0))

    return Family(f"{'affine' if affine else 'linear'}-subspace-{dim}", ambient, dim + affine, dim, (dim + affine) * (ambient - dim), fit, residual)


def polynomial(degree: int) -> Family:
    return Family(f"polynomial-{degree}", 2, degree + 1, 1, degree + 1, *_polynomial(degree))


FAMILIES: dict[str, Family] = {
    f.name: f
    for f in (
        Family("line", 2, 2, 1, 2, _hyperplane, _to_hyperplane),
        Family("circle", 2, 3, 1, 3, _sphere, _to_sphere),
        Family("parabola", 2, 3, 1, 3, *_polynomial(2)),
        Family("conic", 2, 5, 1, 5, _implicit_fit, _implicit_residual),
        Family("plane", 3, 3, 2, 3, _hyperplane, _to_hyperplane),
        Family("sphere", 3, 4, 2, 4, _sphere, _to_sphere),
        Family("quadric", 3, 9, 2, 9, _implicit_fit, _implicit_residual),
        Family("homography", 4, 4, 2, 8, _homography, _transfer),
        Family("fundamental", 4, 8, 3, 7, _fundamental, _epipolar),
        Family("affine-fundamental", 4, 4, 3, 4, _hyperplane, _to_hyperplane),
    )
}


def sample_models(x: np.ndarray, family: Family, m: int, seed: int, neighbours: np.ndarray | None = None) -> list[np.ndarray]:
    """m models, each fitted to a random minimal set; ``neighbours`` (n, k) draws the set near a random point."""
    rng = np.random.Generator(np.random.PCG64(seed))
    out: list[np.ndarray] = []
    for _ in range(20 * m):
        if len(out) == m or len(x) < family.s:
            break
        pick = rng.choice(len(x), family.s, replace=False) if neighbours is None else rng.choice(neighbours[rng.integers(len(x))], family.s, replace=False)
        theta = family.fit(x[pick])
        if theta is not None and np.isfinite(theta).all():
            out.append(theta)
    return out
