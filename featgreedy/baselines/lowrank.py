"""Low-rank and least-squares baselines on moments: oracle least squares, reduced rank, rank selection, vector
autoregressions, nuclear-norm splitting over views, sketches."""

from __future__ import annotations

import numpy as np

from featgreedy.operators.kernel import soft_singular
from featgreedy.operators.moments import GramMoments


def oracle_ls(moments: GramMoments, truth_ids) -> dict[int, np.ndarray]:
    """Least squares on the true blocks."""
    m = moments.only(truth_ids)
    b = np.linalg.lstsq(m.g, m.c0, rcond=None)[0]
    return {j: m.block(b, j) for j in m.ids}


def reduced_rank(g: np.ndarray, c: np.ndarray, yy: float, n: int, rank: int | str = "gcv") -> tuple[np.ndarray, int]:
    """Least squares cut to a rank, by the criterion residual / (1 - freedom)^2 if 'gcv'.

    Works on moments: fitted values' right singular vectors are those of ``c' g^-1 c``.
    """
    inv = np.linalg.pinv(g, hermitian=True)
    full = inv @ c
    w, v = np.linalg.eigh(c.T @ full)
    order = np.argsort(-w)
    w, v = np.maximum(w[order], 0), v[:, order]
    q, d = c.shape
    top = min(q, d)
    if rank == "gcv":
        q_eff = int(np.linalg.matrix_rank(g, hermitian=True))
        best = []
        for r in range(top + 1):
            df = r * (q_eff + d - r) / (n * d)
            rss = max(yy - w[:r].sum(), 0) / (n * d)
            best.append(rss / (1 - df) ** 2 if df < 1 else np.inf)
        rank = int(np.argmin(best))
    return full @ v[:, :rank] @ v[:, :rank].T, int(rank)


def rank_select(g: np.ndarray, c: np.ndarray, mu: float) -> int:
    """Number of squared singular values of the fitted values above ``mu``."""
    return int((np.linalg.eigvalsh(c.T @ np.linalg.pinv(g, hermitian=True) @ c) > mu).sum())


def multiview_admm(moments: GramMoments, levels, rho: float = 1.0, rounds: int = 400, tol: float = 1e-5):
    """Nuclear norms of all views' coefficients by splitting; warm starts over ``levels``. Yields (level, coefficients).

    Weights are ``s1(X_j) (sqrt(d) + sqrt(rank)) / n``. All inner products are decomposed once, as a matrix.
    """
    n, d = moments.n, moments.d
    s, c = moments.g / n, moments.c0 / n
    vals, vecs = np.linalg.eigh(s)
    weights = {}
    for j in moments.ids:
        e = np.linalg.eigvalsh(moments.gram(j))
        weights[j] = np.sqrt(max(e[-1], 0)) * (np.sqrt(d) + np.sqrt((e > 1e-9 * max(e[-1], 1e-300)).sum())) / n
    z = np.zeros_like(c)
    w = np.zeros_like(c)
    rho0 = rho * float(np.mean(vals))
    for level in levels:
        for _ in range(rounds):
            right = c + rho0 * (z - w)
            b = vecs @ ((vecs.T @ right) / (vals + rho0)[:, None])
            old = z.copy()
            for j in moments.ids:
                i, k = moments.range[j]
                z[i:k] = soft_singular(b[i:k] + w[i:k], level * weights[j] / rho0)
            w += b - z
            if np.abs(b - z).max() < tol and np.abs(z - old).max() < tol:
                break
        yield level, {j: moments.block(z, j).copy() for j in moments.ids if np.any(moments.block(z, j))}


def ridge_inverse(s: np.ndarray, c: float):
    """Solver of ``(S S' + c I) z = r``: by the smaller side of ``S``, so that no matrix of rows by rows is held where rows are many."""
    n, k = s.shape
    if k >= n:
        chol = np.linalg.cholesky(s @ s.T + c * np.eye(n))
        return lambda r: np.linalg.solve(chol.T, np.linalg.solve(chol, r))
    inner = np.linalg.inv(s.T @ s + c * np.eye(k))
    return lambda r: (r - s @ (inner @ (s.T @ r))) / c


def dual_sketch_ridge(x: np.ndarray | GramMoments, y: np.ndarray | None, lam: float, m: int, nodes: int = 4, iters: int = 20, seed: int = 3):
    """Nodes ship sketches of their columns once; the dual is then corrected with exact products.

    ``|y - Xb|^2 / 2 + n lam |b|^2 / 2``; returns coefficients and bytes sent. ``x`` may be moments of scalar columns and
    response (``y`` None): every vector of the dual is then held as ``X b + a y`` by ``b`` and ``a``, the sketches by their mixing.
    """
    held = isinstance(x, GramMoments)
    n, p = (x.n, len(x.c0)) if held else x.shape
    parts = [np.arange(p)[c::nodes] for c in range(nodes)]
    rng = np.random.default_rng(seed)
    found, sent = [], 0
    for i in parts:
        k = min(m, len(i))
        own = np.eye(p)[:, i] if held else x[:, i]
        found.append(own @ rng.standard_normal((len(i), k)) / np.sqrt(k) if k < len(i) else own)
        sent += n * k * 8
    if held:
        all_products = np.vstack([np.hstack([x.g, x.c0]), np.append(x.c0[:, 0], x.yy)])
        mix = np.hstack(found)
        inner = np.linalg.inv(mix.T @ x.g @ mix + n * lam * np.eye(mix.shape[1]))
        dot = lambda u, v: float(u @ (all_products @ v))
        products = lambda v: all_products[:p] @ v
        solve = lambda r: (r - np.append(mix @ (inner @ (mix.T @ products(r))), 0)) / (n * lam)
        kernel = lambda d: np.append(products(d), 0) + n * lam * d
        r = np.append(np.zeros(p), 1.0)
    else:
        dot, products = np.dot, lambda v: x.T @ v
        solve = ridge_inverse(np.hstack(found), n * lam)
        kernel = lambda d: sum(x[:, i] @ (x[:, i].T @ d) for i in parts) + n * lam * d
        r = y.copy()
    a = np.zeros(len(r))
    d = z = solve(r)
    rz = dot(r, z)
    for _ in range(iters):  # conjugate gradients with the sketched kernel as preconditioner
        kd = kernel(d)
        sent += 2 * nodes * n * 8
        step = rz / max(dot(d, kd), 1e-300)
        a = a + step * d
        r = r - step * kd
        z = solve(r)
        new = dot(r, z)
        if new < 1e-20:
            break
        d, rz = z + new / rz * d, new
    return products(a), sent


def hessian_sketch(x: np.ndarray, y: np.ndarray, m: int, iters: int = 12, seed: int = 9) -> np.ndarray:
    """Least squares by fresh sketches of the second moment at every step."""
    n, p = x.shape
    b = np.zeros(p)
    rng = np.random.default_rng(seed)
    m = min(max(m, 4 * p), 8 * n)
    for _ in range(iters):
        s = rng.standard_normal((m, n)) @ x / np.sqrt(m)
        b = b + np.linalg.lstsq(s.T @ s, x.T @ (y - x @ b), rcond=None)[0]
    return b


def feature_sgd(x: np.ndarray, y: np.ndarray, lam: float = 0.0, batch: int = 64, epochs: int = 30, rate: float = 0.5, seed: int = 4) -> np.ndarray:
    """Synchronous mini-batches over rows on one array; :func:`featgreedy.baselines.spread.row_sgd` is the distributed form."""
    n, p = x.shape
    b, rng = np.zeros(p), np.random.default_rng(seed)
    top = float((x * x).sum(1).max())
    for e in range(epochs):
        for i in np.array_split(rng.permutation(n), max(1, n // batch)):
            b = b - rate / (1 + e) / top * (x[i].T @ (x[i] @ b - y[i]) / 1 + lam * b)
    return b
