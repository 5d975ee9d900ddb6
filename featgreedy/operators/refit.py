"""Phase two: coefficients of the screened blocks from zero, inside frozen singular subspaces.

A block whose smaller side exceeds the total rank ``R`` keeps its coefficient in ``S_j^-1 U_j S V_j'`` with the leading
``R`` singular vectors of its product with the response; a smaller block is only preconditioned by ``S_j^-1``.
``S_j`` is the block's inner product over the total row count, in one segment or many.
"""

from __future__ import annotations

import math
import time

import numpy as np
import pyarrow as pa

from featgreedy.operators.greedy import Fit
from featgreedy.operators.kernel import line_search, top_triple
from featgreedy.operators.moments import arrays, pick_winner, score_blocks
from featgreedy.session import ship


def inverse(s: np.ndarray) -> np.ndarray:
    """Inverse of a block's second moment; pseudo-inverse where columns are collinear."""
    return np.linalg.pinv(s, rcond=1e-10, hermitian=True)


class Subspace:
    """Left map ``t`` (q by r) and right map ``v`` (d by r) of a block; ``large`` tells whether ranks are bounded."""

    def __init__(self, gram: np.ndarray, cross: np.ndarray, n: int, total_rank: float):
        q, d = cross.shape
        inv = inverse(gram / n)
        self.large = min(q, d) > total_rank
        if self.large:
            u, _, vt = np.linalg.svd(cross, full_matrices=False)
            self.t, self.v = inv @ u[:, : int(total_rank)], vt[: int(total_rank)].T
        else:
            self.t, self.v = inv, np.eye(d)

    def project(self, c: np.ndarray) -> np.ndarray:
        return self.t.T @ c @ self.v


def refit(moments, ranks: dict[int, int] | None, radius: float, iters: int = 500, tol: float = 1e-10, ledger=None, total_rank: float | None = None) -> Fit:
    """The second loop on moments of the screened blocks alone (see :meth:`GramMoments.only`); with ``tol`` 0, all ``iters`` steps."""
    n, d = moments.n, moments.d
    total = total_rank if total_rank is not None else float(sum(ranks.values()))
    spaces = {j: Subspace(moments.gram(j), moments.block(moments.c0, j), n, total) for j in moments.ids}
    moments.reset()
    fit = Fit(d, {j: moments.range[j][1] - moments.range[j][0] for j in moments.ids})
    yg = gg = 0.0
    yy = moments.yy
    fit.loss0 = before = yy / (n * d)
    for k in range(1, iters + 1):
        began = time.perf_counter()
        best = None
        for j in moments.ids:
            s, a, b = top_triple(spaces[j].project(moments.block(moments.c, j)))
            if best is None or s > best[1] * (1 + 1e-12):
                best = (j, s, a, b)
        if best is None or best[1] <= 0:
            break
        j, s, a, b = best
        u, v = spaces[j].t @ a, spaces[j].v @ b
        ua, ya, aa = radius * s, radius * moments.with_response(j, u, v), radius * radius * moments.fit_norm(j, u) * float(v @ v)
        ga = ya - ua
        lam = line_search(ua, ga, aa, yg, gg)
        moments.advance(j, u, v, lam, radius)
        gg = (1 - lam) ** 2 * gg + 2 * lam * (1 - lam) * ga + lam * lam * aa
        yg = (1 - lam) * yg + lam * ya
        loss = max(0.0, (yy - 2 * yg + gg) / (n * d))
        fit.terms.append((j, radius, u, v))
        fit.trace.append({"k": k, "j": j, "lam": lam, "score": s, "loss": loss, "ratio": loss / before if before > 0 else 1.0, "secs": time.perf_counter() - began})
        fit.stop_index = k
        if ledger is not None:
            ledger.eager(2, k, n, d)
        if tol > 0 and before - loss <= tol * before and k > 1:
            break
        before = loss
    fit.passes = 1
    fit.spaces = spaces
    return fit


def refit_state(state, ranks: dict[int, int], radius: float, iters: int = 500, tol: float = 1e-10, ledger=None, total_rank: float | None = None) -> Fit:
    """The second loop where the screened blocks' inner products stay in Spark, one row a block.

    ``state`` is a :class:`~featgreedy.operators.moments.StateMoments` that has met the blocks of ``ranks``. A step maps
    each row's residual product into the block's frozen subspace and brings the best pair, in the block's coordinates.
    """
    n, d, total = state.n, state.d, total_rank if total_rank is not None else float(sum(ranks.values()))
    state.meet(*ranks)
    state.reset()
    ids = sorted(ranks)
    spaces = {j: Subspace(state.own[j], state.start[j], n, total) for j in ids}
    shapes = {j: (s.t, s.v) for j, s in spaces.items()}  # of one block each, as large as its coefficient
    fit = Fit(d, {j: state.own[j].shape[0] for j in ids})
    yg = gg = 0.0
    fit.loss0 = before = state.yy / (n * d)

    def project(batches):
        for batch in batches:
            out, size = [], []
            for j, q, c in zip(batch.column("j").to_pylist(), batch.column("q").to_pylist(), arrays(batch.column("c")), strict=True):
                t, v = shapes[j]
                out.append((t.T @ c.reshape(q, -1) @ v).ravel())
                size.append((t.shape[1], v.shape[1]))
            yield pa.RecordBatch.from_arrays([batch.column("j"), pa.array([a for a, _ in size], pa.int32()), pa.array([b for _, b in size], pa.int32()), pa.array(out, pa.list_(pa.float64()))], ["j", "q", "k", "c"])

    for k in range(1, iters + 1):
        began = time.perf_counter()
        w = pick_winner(score_blocks(state.residual_rows(ids).mapInArrow(project, "j int, q int, k int, c array<double>")))
        if w is None or not w["s1"] > 0:
            break
        j, s = w["j"], w["s1"]
        u, v = spaces[j].t @ np.array(w["u"]), spaces[j].v @ np.array(w["v"])
        ua, ya, aa = radius * s, radius * state.with_response(j, u, v), radius * radius * state.fit_norm(j, u) * float(v @ v)
        ga = ya - ua
        lam = line_search(ua, ga, aa, yg, gg)
        state.advance(j, u, v, lam, radius)
        gg = (1 - lam) ** 2 * gg + 2 * lam * (1 - lam) * ga + lam * lam * aa
        yg = (1 - lam) * yg + lam * ya
        loss = max(0.0, (state.yy - 2 * yg + gg) / (n * d))
        fit.terms.append((j, radius, u, v))
        fit.trace.append({"k": k, "j": j, "lam": lam, "score": s, "loss": loss, "ratio": loss / before if before > 0 else 1.0, "secs": time.perf_counter() - began})
        fit.stop_index = k
        if ledger is not None:
            ledger.eager(2, k, n, d)
        if tol > 0 and before - loss <= tol * before and k > 1:
            break
        before = loss
    fit.passes, fit.spaces = state.passes, spaces
    return fit


def required_iters(widths: dict[int, int], d: int, total_rank: int, xi: float, n: int, mu: float = 1.0, tau: float = 1.0) -> int:
    """Steps that reach the noise floor: a multiple of kappa times the log of ``n^2 d / xi^2``.

    kappa is the number of blocks times the larger of the widest small block and, if any block is large, the rank.
    """
    small = [min(q, d) for q in widths.values() if min(q, d) <= total_rank]
    large = any(min(q, d) > total_rank for q in widths.values())
    kappa = len(widths) * max([*small, total_rank if large else 0, 1])
    return max(1, math.ceil(tau * kappa / mu * math.log(max(n * n * d / max(xi, 1e-300) ** 2, math.e))))


ship(__name__)
