"""Independent direct forms: residual matrices and full decompositions, no recursions."""

import numpy as np


def direct_rga(blocks, y, radius, steps):
    g, out = np.zeros_like(y), []
    for _ in range(steps):
        best = None
        for j, x in enumerate(blocks):
            u, s, vt = np.linalg.svd(x.T @ (y - g), full_matrices=False)
            if best is None or s[0] > best[0] * (1 + 1e-12):
                best = (s[0], j, radius * np.outer(x @ u[:, 0], vt[0]))
        _, j, a = best
        diff = a - g
        lam = min(1.0, max(0.0, ((y - g) * diff).sum() / (diff * diff).sum()))
        g = g + lam * diff
        out.append((j, lam, ((y - g) ** 2).mean(), g.copy()))
    return out


def direct_refit(blocks, y, ranks, radius, steps):
    n, total = len(y), sum(ranks.values())
    maps = {}
    for j in ranks:
        x = blocks[j]
        inv = np.linalg.inv(x.T @ x / n)
        u, _, vt = np.linalg.svd(x.T @ y, full_matrices=False)
        k = total if min(x.shape[1], y.shape[1]) > total else min(x.shape[1], y.shape[1])
        maps[j] = (inv @ u[:, :k], vt[:k].T) if k == total and min(x.shape[1], y.shape[1]) > total else (inv, np.eye(y.shape[1]))
    g, out = np.zeros_like(y), []
    for _ in range(steps):
        best = None
        for j in sorted(ranks):
            t, v = maps[j]
            a, s, bt = np.linalg.svd(t.T @ blocks[j].T @ (y - g) @ v, full_matrices=False)
            if best is None or s[0] > best[0] * (1 + 1e-12):
                best = (s[0], j, radius * np.outer(blocks[j] @ t @ a[:, 0], v @ bt[0]))
        _, j, a = best
        diff = a - g
        lam = min(1.0, max(0.0, ((y - g) * diff).sum() / (diff * diff).sum()))
        g = g + lam * diff
        out.append((j, lam, ((y - g) ** 2).mean()))
    return out
