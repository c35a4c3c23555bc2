"""A small dense simplex: maximise c x subject to A x <= b, x >= 0, with b >= 0, so that the origin is a feasible start."""

from __future__ import annotations

import numpy as np

EPS = 1e-9


def maximise(c: np.ndarray, a: np.ndarray, b: np.ndarray, most: int = 100_000) -> tuple[float, np.ndarray, np.ndarray]:
    """Value, solution and dual values. Largest coefficient first, Bland's rule after a run of steps without progress."""
    m, n = a.shape
    if (b < -EPS).any():
        raise ValueError("right-hand sides must not be negative")
    t = np.zeros((m + 1, n + m + 1))
    t[:m, :n], t[:m, n : n + m], t[:m, -1], t[m, :n] = a, np.eye(m), b, -np.asarray(c, float)
    basis = list(range(n, n + m))
    stuck = 0
    for _ in range(most):
        row = t[m, :-1]
        able = np.flatnonzero(row < -EPS)
        if not len(able):
            break
        col = int(able[0]) if stuck > 20 else int(able[np.argmin(row[able])])
        up = np.flatnonzero(t[:m, col] > EPS)
        if not len(up):
            raise ValueError("unbounded")
        ratio = t[up, -1] / t[up, col]
        tied = up[ratio <= ratio.min() + EPS]
        r = int(min(tied, key=lambda i: basis[i]))
        before = t[m, -1]
        t[r] /= t[r, col]
        others = np.flatnonzero(np.abs(t[:, col]) > 0)
        others = others[others != r]
        t[others] -= np.outer(t[others, col], t[r])
        basis[r] = col
        stuck = 0 if t[m, -1] > before + EPS else stuck + 1
    else:
        raise ValueError("the simplex took too many steps")
    x = np.zeros(n + m)
    x[basis] = t[:m, -1]
    return float(t[m, -1]), x[:n], t[m, n : n + m].copy()
