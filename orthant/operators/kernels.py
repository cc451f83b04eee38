"""Row-local updates on NumPy arrays.

Once a target H (rows x k) and a Gram matrix G (k x k) are known, every update of a factor F (rows x k)
works on each row alone. H and G come from the raw data or from their projections; kernels don't differ.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

EPS = 1e-12
#: Cells of a residual that are laid out at a time; few enough for a core's cache.
PART_CELLS = 1 << 16


@dataclass(frozen=True)
class Penalty:
    """Sparsity (alpha) is taken off the numerator, smoothness (beta) is added to the denominator."""

    alpha: float = 0.0
    beta: float = 0.0


NONE = Penalty()


def gram_sweep(h: np.ndarray, g: np.ndarray, f: np.ndarray, p: Penalty = NONE) -> np.ndarray:
    """Each component goes to its best non-negative value, seeing those already changed. A component whose Gram
    entry is zero stays as it is."""
    f = f.copy()
    for j in range(f.shape[1]):
        if g[j, j] <= EPS:
            continue
        free = h[:, j] - f @ g[:, j] + f[:, j] * g[j, j]
        f[:, j] = np.maximum(free - p.alpha, 0) / (g[j, j] + p.beta)
    return f


def multiplicative(h: np.ndarray, g: np.ndarray, f: np.ndarray, p: Penalty = NONE) -> np.ndarray:
    return f * np.maximum(h - p.alpha, 0) / (f @ g + p.beta * f + EPS)


def signed_multiplicative(h: np.ndarray, g: np.ndarray, f: np.ndarray, p: Penalty = NONE) -> np.ndarray:
    """For targets and Gram matrices of either sign: positive parts push up, negative parts push down."""
    h = h - p.alpha
    up = np.maximum(h, 0) + f @ np.maximum(-g, 0)
    down = np.maximum(-h, 0) + f @ np.maximum(g, 0) + p.beta * f
    return f * np.sqrt(up / (down + EPS))


def clipped_least_squares(h: np.ndarray, g: np.ndarray, f: np.ndarray, p: Penalty = NONE) -> np.ndarray:
    ridge = (1e-10 * np.trace(g) / len(g) + p.beta + EPS) * np.eye(len(g))
    return np.maximum(np.linalg.solve(g + ridge, (h - p.alpha).T).T, 0)


def projected_gradient(h: np.ndarray, g: np.ndarray, f: np.ndarray, p: Penalty = NONE, steps: int = 5) -> np.ndarray:
    """Gradient steps of the length that the largest eigenvalue allows, clipped at zero."""
    length = np.linalg.eigvalsh(g)[-1] + p.beta
    if length <= EPS:
        return f
    for _ in range(steps):
        f = np.maximum(f - (f @ g + p.beta * f - h + p.alpha) / length, 0)
    return f


def active_set(h: np.ndarray, g: np.ndarray, f: np.ndarray, p: Penalty = NONE) -> np.ndarray:
    """The exact non-negative least squares solution of every row: a variable that violates its condition most
    becomes free, and free ones that turn negative go back to zero."""
    k = len(g)
    g = g + (p.beta + 1e-12 * max(np.trace(g) / k, EPS)) * np.eye(k)
    h = h - p.alpha
    out = np.zeros_like(f)
    tol = 1e-9 * max(1.0, np.abs(h).max(initial=0))
    for r in range(len(h)):
        x, free = np.zeros(k), np.zeros(k, bool)
        for _ in range(6 * k + 20):
            slack = h[r] - g @ x
            slack[free] = -np.inf
            j = int(slack.argmax())
            if slack[j] <= tol:
                break
            free[j] = True
            while True:
                idx = np.flatnonzero(free)
                z = np.zeros(k)
                z[idx] = np.linalg.solve(g[np.ix_(idx, idx)], h[r][idx])
                if (z[idx] > 0).all():
                    x = z
                    break
                bad = idx[z[idx] <= 0]
                t = (x[bad] / np.maximum(x[bad] - z[bad], EPS)).min()
                x = x + t * (z - x)
                free &= x > 1e-14
                x[~free] = 0
        out[r] = x
    return out


KERNELS = {"mu": multiplicative, "gram_hals": gram_sweep, "als": clipped_least_squares, "pgd": projected_gradient, "anls": active_set, "cmu": signed_multiplicative, "cgram_hals": gram_sweep, "cals": clipped_least_squares, "cpgd": projected_gradient, "canls": active_set}
#: Methods that rebuild a residual for every component, a_j and b_j in turn.
RESIDUAL = ("hals", "chals")
METHODS = (*KERNELS, *RESIDUAL)
COMPRESSED = tuple(m for m in METHODS if m.startswith("c"))


def residual_component(x: np.ndarray, f: np.ndarray, other: np.ndarray, j: int, p: Penalty = NONE) -> np.ndarray:
    """One component from an explicit residual: rows of ``x`` minus the model of the other components. It is laid out in
    tiles, each used at once; a residual of many rows would go to memory and back for every component."""
    b = other[:, j]
    own = b @ b
    if own <= EPS:
        return f[:, j]
    up = np.zeros(len(x))
    width = min(x.shape[1], max(int(PART_CELLS**0.5), PART_CELLS // max(len(x), 1)))
    step = PART_CELLS // width
    for i in range(0, len(x), step):
        rows = slice(i, i + step)
        rest = f[rows].copy()
        rest[:, j] = 0
        for at in range(0, x.shape[1], width):
            cols = slice(at, at + width)
            part = x[rows, cols]
            left = np.empty_like(part, dtype=float)  # laid out as the part is
            np.matmul(rest, other[cols].T, out=left)
            np.subtract(part, left, out=left)
            up[rows] += left @ b[cols]
    return np.maximum(up - p.alpha, 0) / (own + p.beta)
