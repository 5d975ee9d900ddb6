"""Leading singular triples, their orientation, and the closed-form step."""

from __future__ import annotations

import numpy as np

from featgreedy.session import ship


def orient(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Signs such that the largest entry of ``u`` (the first, if tied) is positive."""
    k = int(np.abs(u).argmax())
    return (-u, -v) if u[k] < 0 else (u, v)


def top_triple(c: np.ndarray, start: np.ndarray | None = None, sweeps: int = 200, tol: float = 1e-13) -> tuple[float, np.ndarray, np.ndarray]:
    """Largest singular value of ``c`` with its pair: exact for small sides, else power sweeps."""
    q, d = c.shape
    if not np.any(c):
        return 0.0, np.eye(q)[0], np.eye(d)[0]
    if q == 1 or d == 1:
        s = float(np.sqrt((c * c).sum()))
        u, v = (np.ones(1), c[0] / s) if q == 1 else (c[:, 0] / s, np.ones(1))
    elif min(q, d) <= 16:
        uu, ss, vv = np.linalg.svd(c, full_matrices=False)
        s, u, v = float(ss[0]), uu[:, 0], vv[0]
    else:
        v = start if start is not None else c[np.abs(c).sum(1).argmax()]
        v = v / np.sqrt(v @ v)
        s = 0.0
        for _ in range(sweeps):
            u = c @ v
            u /= max(np.sqrt(u @ u), 1e-300)
            v = c.T @ u
            new = float(np.sqrt(v @ v))
            v /= max(new, 1e-300)
            if abs(new - s) <= tol * new:
                s = new
                break
            s = new
        u = c @ v
        s = float(np.sqrt(u @ u))
        u = u / s
    return (s, *orient(u, v))


def top_scores(c: np.ndarray) -> np.ndarray:
    """Largest singular values of a stack of matrices ``(p, q, d)``."""
    p, q, d = c.shape
    if q == 1 or d == 1:
        return np.sqrt((c * c).sum((1, 2)))
    gram = c @ c.transpose(0, 2, 1) if q <= d else c.transpose(0, 2, 1) @ c
    return np.sqrt(np.maximum(np.linalg.eigvalsh(gram)[:, -1], 0))


def line_search(ua: float, ga: float, aa: float, yg: float, gg: float) -> float:
    """Best weight in [0, 1] of the atom against the present fit, from inner products.

    ``ua`` residual with atom, ``ga`` fit with atom, ``aa`` atom with itself, ``yg`` response with fit, ``gg`` fit
    with itself. An atom equal to the fit gives 0.
    """
    below = aa - 2 * ga + gg
    return float(min(1.0, max(0.0, (ua - (yg - gg)) / below))) if below > 0 else 0.0


def soft_singular(b: np.ndarray, level: float) -> np.ndarray:
    """Singular values lowered by ``level``, none below zero."""
    u, s, v = np.linalg.svd(b, full_matrices=False)
    return (u * np.maximum(s - level, 0)) @ v


def numeric_rank(b: np.ndarray, tol: float = 1e-9) -> int:
    s = np.linalg.svd(b, compute_uv=False)
    return int((s > tol * max(s.max(initial=0), 1e-300)).sum()) if np.any(b) else 0


ship(__name__)
