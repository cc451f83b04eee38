"""Solvers on arrays of one machine: what a task runs for one start or grid point, and what tests compare with.

A raw problem holds X; a compressed one holds both projections and the projectors, never X.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from .kernels import COMPRESSED, KERNELS, NONE, PART_CELLS, RESIDUAL, Penalty, residual_component


@dataclass(frozen=True)
class Problem:
    """``right``: X or X R' (d x width); ``left``: X or L' X (width x n); ``l``: d x s and ``r``: s x n, or None."""

    right: np.ndarray
    left: np.ndarray
    l: np.ndarray | None = None
    r: np.ndarray | None = None

    @property
    def shape(self) -> tuple[int, int]:
        return self.right.shape[0], self.left.shape[1]

    def near_a(self, a: np.ndarray) -> np.ndarray:
        return a if self.l is None else self.l.T @ a

    def near_b(self, b: np.ndarray) -> np.ndarray:
        return b if self.r is None else self.r @ b


def sample_range(x: np.ndarray, omega: np.ndarray, w: int) -> np.ndarray:
    """An orthonormal basis of (X X')^w X omega, orthonormalised between the powers."""
    q = np.linalg.qr(x @ omega)[0]
    for _ in range(w):
        q = np.linalg.qr(x @ np.linalg.qr(x.T @ q)[0])[0]
    return q


def compress(x: np.ndarray, s: int, w: int, seed: int) -> Problem:
    order = np.random.default_rng(seed)
    s = min(s, *x.shape)
    left = sample_range(x, order.standard_normal((x.shape[1], s)), w)
    right = sample_range(x.T, order.standard_normal((x.shape[0], s)), w).T
    return Problem(x @ right.T, left.T @ x, left, right)


def start(d: int, n: int, k: int, mean: float, seed: int) -> tuple[np.ndarray, np.ndarray]:
    order = np.random.default_rng(seed)
    scale = np.sqrt(max(mean, 1e-12) / k) * 2
    return order.random((d, k)) * scale, order.random((n, k)) * scale


def normalised(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    norm = np.sqrt((a * a).sum(0))
    norm = np.where(norm > 0, norm, 1.0)
    return a / norm, b * norm


def iterate(problem: Problem, method: str, a: np.ndarray, b: np.ndarray, penalty: Penalty = NONE, normalize: str = "sweep") -> tuple[np.ndarray, np.ndarray]:
    """One iteration. ``normalize``: unit components of A after its sweep ("sweep", the product is unchanged),
    after each component ("component", as the method is stated), or never ("none"). A is never penalised."""
    if method in RESIDUAL:
        a, b = a.copy(), b.copy()
        for j in range(a.shape[1]):
            a[:, j] = residual_component(problem.right, a, problem.near_b(b), j)
            if normalize != "none" and (size := np.linalg.norm(a[:, j])) > 0:
                a[:, j] /= size
                b[:, j] *= size if normalize == "sweep" else 1.0
            b[:, j] = residual_component(problem.left.T, b, problem.near_a(a), j, penalty)
        return a, b
    kernel = KERNELS[method]
    near = problem.near_b(b)
    if normalize == "component" and kernel is KERNELS["gram_hals"]:
        h, g, a = problem.right @ near, near.T @ near, a.copy()
        for j in range(a.shape[1]):
            if g[j, j] > 0:
                a[:, j] = np.maximum(a[:, j] + (h[:, j] - a @ g[:, j]) / g[j, j], 0)
                a[:, j] /= max(np.linalg.norm(a[:, j]), 1e-300)
    else:
        a = kernel(problem.right @ near, near.T @ near, a)
        if normalize == "sweep":
            a, b = normalised(a, b)
    near = problem.near_a(a)
    return a, kernel(problem.left.T @ near, near.T @ near, b, penalty)


def solve(x: np.ndarray, method: str, k: int, s: int, w: int, iterations: int, seed: int, penalty: Penalty = NONE, problem: Problem | None = None, normalize: str = "sweep", every: int = 1) -> tuple[np.ndarray, np.ndarray, list[tuple[int, float]]]:
    """(A, B, trace of (iteration, half squared error of the true data))."""
    if problem is None:
        problem = compress(x, s, w, seed) if method in COMPRESSED else Problem(x, x)
    a, b = start(*x.shape, k, float(x.mean()), seed)
    trace = [(0, objective(x, a, b))]
    for i in range(1, iterations + 1):
        a, b = iterate(problem, method, a, b, penalty, normalize)
        if i % every == 0 or i == iterations:
            trace.append((i, objective(x, a, b)))
    return a, b, trace


def objective(x: np.ndarray, a: np.ndarray, b: np.ndarray) -> float:
    step = max(1, PART_CELLS // max(x.shape[1], 1))
    return 0.5 * sum(float(((x[i : i + step] - a[i : i + step] @ b.T) ** 2).sum()) for i in range(0, len(x), step))


def gini(values: np.ndarray) -> float | None:
    v = np.sort(np.ravel(values))
    n, total = len(v), v.sum()
    if not n or total <= 0:
        return None
    return float(((2 * np.arange(1, n + 1) - n - 1) * v).sum() / (n * total))
