"""Phase one: the relaxed greedy loop over blocks with nuclear-ball atoms, and its plateau stop."""

from __future__ import annotations

import math
import time
from dataclasses import dataclass, field

import numpy as np

from featgreedy.operators.kernel import line_search, numeric_rank

#: The threshold grid as printed (its second entry, 0.07, stands where 0.69 continues the logarithms).
GRID_PRINTED = (0.01, 0.07, 1.10, 1.39, 1.61, 1.79, 1.95, 2.08, 2.20, 2.30)
#: The tenths over log n of the panel study.
GRID_PANEL = tuple(k / 10 for k in range(1, 11))


def default_threshold(n: int) -> float:
    """One tenth over log n; needs two rows at least."""
    if n < 2:
        raise ValueError("the default threshold needs at least two rows")
    return 1 / (10 * math.log(n))


class PlateauStop:
    """Stop at the first step whose loss is at least ``1 - t`` of the one before."""

    def __init__(self, t: float):
        self.t = t

    def done(self, before: float, now: float) -> bool:
        return before <= 0 or now / before >= 1 - self.t


class RelativePlateauStop:
    """Stop when the loss changes by less than the share ``t``; near zero, by the absolute change."""

    def __init__(self, t: float):
        self.t = t

    def done(self, before: float, now: float) -> bool:
        return abs(now - before) < self.t * abs(before) if abs(before) > 1e-8 else abs(now - before) < self.t


@dataclass
class Fit:
    """Coefficients by block as weighted rank-one terms, the path, and its losses."""

    d: int
    widths: dict[int, int]
    terms: list[tuple[int, float, np.ndarray, np.ndarray]] = field(default_factory=list)
    trace: list[dict] = field(default_factory=list)
    loss0: float = 0.0
    stop_index: int = 0
    passes: int = 0

    def coef(self, upto: int | None = None) -> dict[int, np.ndarray]:
        """Coefficient matrices after ``upto`` steps (all if None): earlier terms shrink with each later step."""
        out: dict[int, np.ndarray] = {}
        weight = 1.0
        steps = self.terms[: self.stop_index if upto is None else upto]
        lams = [t["lam"] for t in self.trace[: len(steps)]]
        for (j, radius, u, v), lam in zip(reversed(steps), reversed(lams), strict=True):
            b = out.setdefault(j, np.zeros((self.widths[j], self.d)))
            b += weight * lam * radius * np.outer(u, v)
            weight *= 1 - lam
        return {j: b for j, b in sorted(out.items()) if np.any(b)}

    def screened(self, upto: int | None = None, tol: float = 1e-9) -> dict[int, int]:
        """Selected blocks and the ranks of their coefficients."""
        return {j: r for j, b in self.coef(upto).items() if (r := numeric_rank(b, tol))}

    def stop_for(self, t: float) -> int:
        """The stop index that threshold ``t`` would give on this path; indices are nested in ``t``."""
        before, rule = self.loss0, PlateauStop(t)
        for row in self.trace:
            if rule.done(before, row["loss"]):
                return row["k"]
            before = row["loss"]
        return len(self.trace)


def rga(moments, radius: float, cap: int = 200, stop=None, ledger=None, wire: str = "eager", node_of=None) -> Fit:
    """Relaxed greedy steps until ``stop`` or ``cap``.

    Each step takes the block whose residual product has the largest singular value, and moves the fit towards the
    rank-one atom of nuclear norm ``radius`` by the exact line search. Only inner products are read: of residual,
    fit and atom, all carried on by scalars, and of the winner's column space, from ``moments``.
    """
    n, d = moments.n, moments.d
    fit = Fit(d, {})
    yg = gg = 0.0
    yy = moments.yy
    fit.loss0 = before = yy / (n * d)
    for k in range(1, cap + 1):
        began = time.perf_counter()
        if yy <= 0:
            break
        j, s, u, v = moments.best()
        ua, ya, aa = radius * s, radius * moments.with_response(j, u, v), radius * radius * moments.fit_norm(j, u)
        ga = ya - ua
        lam = line_search(ua, ga, aa, yg, gg)
        moments.advance(j, u, v, lam, radius)
        gg = (1 - lam) ** 2 * gg + 2 * lam * (1 - lam) * ga + lam * lam * aa
        yg = (1 - lam) * yg + lam * ya
        loss = max(0.0, (yy - 2 * yg + gg) / (n * d))
        fit.widths[j] = len(u)
        fit.terms.append((j, radius, u, v))
        fit.trace.append({"k": k, "j": j, "lam": lam, "score": s, "loss": loss, "ratio": loss / before if before > 0 else 1.0, "secs": time.perf_counter() - began})
        if ledger is not None:
            winner = (node_of or (lambda j: j % ledger.nodes))(j)
            ledger.lazy(1, k, n, d, winner) if wire == "lazy" else ledger.eager(1, k, n, d)
        fit.stop_index = k
        if stop is not None and stop.done(before, loss):
            break
        before = loss
    if ledger is not None and fit.stop_index:
        ledger.flush(1, fit.stop_index, n, d)
    fit.passes = getattr(moments, "passes", 0)
    return fit


def rga_rank_k(moments, radius: float, cap: int, k: int) -> list[float]:
    """Losses of the comparator whose atoms have rank ``k``: the leading ``k`` pairs of the winner share the radius in
    proportion to their singular values. It needs ``k`` pairs a step and ships ``k`` times the vectors."""
    n, d = moments.n, moments.d
    yg = gg = 0.0
    losses = []
    for _ in range(cap):
        j, _, _, _ = moments.best()
        c = moments.block(moments.c, j)
        u, s, vt = np.linalg.svd(c, full_matrices=False)
        r = min(k, int((s > 1e-12 * s[0]).sum()))
        b = radius * (u[:, :r] * (s[:r] / s[:r].sum())) @ vt[:r]
        ua, ya = float((b * c).sum()), float((b * moments.block(moments.c0, j)).sum())
        aa, ga = float((b * (moments.gram(j) @ b)).sum()), ya - ua
        lam = line_search(ua, ga, aa, yg, gg)
        i, e = moments.range[j]
        moments.c *= 1 - lam
        moments.c += lam * (moments.c0 - moments.g[:, i:e] @ b)
        gg = (1 - lam) ** 2 * gg + 2 * lam * (1 - lam) * ga + lam * lam * aa
        yg = (1 - lam) * yg + lam * ya
        losses.append(max(0.0, (moments.yy - 2 * yg + gg) / (n * d)))
    return losses
