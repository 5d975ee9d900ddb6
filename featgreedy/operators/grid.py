"""Row-and-column partition: screening on row segments, a vote, pooled moments, and a joint second phase.

Every segment's moments stay apart; a step sums small projected matrices over segments, and the line search needs
two numbers of each. With second moments over the total row count the path equals that of one segment.
"""

from __future__ import annotations

from collections import Counter


from featgreedy.operators.greedy import Fit, PlateauStop, default_threshold, rga
from featgreedy.operators.kernel import top_triple
from featgreedy.operators.refit import Subspace


def screen(by_segment: dict, radius: float, cap: int = 200, t: float | None = None, segments=None, vote: str = "intersect"):
    """Selected blocks and ranks from one or several segments.

    ``intersect`` keeps blocks of every segment with their smallest rank, ``union`` those of any with the largest,
    ``majority`` those of more than half with the smallest among them.
    """
    picks = []
    for h in segments if segments is not None else sorted(by_segment):
        m = by_segment[h]
        m.reset()
        picks.append(rga(m, radius, cap, PlateauStop(default_threshold(m.n) if t is None else t)).screened())
    return tally(picks, vote)


def tally(picks: list[dict[int, int]], vote: str) -> dict[int, int]:
    count = Counter(j for p in picks for j in p)
    need = {"intersect": len(picks), "union": 1, "majority": len(picks) // 2 + 1}[vote]
    fold = max if vote == "union" else min
    return {j: fold(p[j] for p in picks if j in p) for j in sorted(count) if count[j] >= need}


def grid_refit(by_segment: dict, ranks: dict[int, int], radius: float, iters: int = 500, tol: float = 1e-10, ledger=None, total_rank: float | None = None) -> Fit:
    """Phase two over segments; ``by_segment`` maps a segment to moments that hold the blocks of ``ranks``."""
    parts = {h: m.only(ranks) for h, m in sorted(by_segment.items())}
    some = next(iter(parts.values()))
    n, d, ids = sum(m.n for m in parts.values()), some.d, some.ids
    total = total_rank if total_rank is not None else float(sum(ranks.values()))
    yy = sum(m.yy for m in parts.values())
    spaces = {j: Subspace(sum(m.gram(j) for m in parts.values()), sum(m.block(m.c0, j) for m in parts.values()), n, total) for j in ids}
    widths = {j: some.range[j][1] - some.range[j][0] for j in ids}
    if ledger is not None:
        for h in parts:
            for j in ids:
                r = int(total) if spaces[j].large else 0
                ledger.send(2, 0, f"seg{h}", "coordinator", "moments", widths[j] ** 2 + widths[j] * d)
                ledger.send(2, 0, "coordinator", f"seg{h}", "subspace", widths[j] ** 2 + r * (widths[j] + d))
    for m in parts.values():
        m.reset()
    fit = Fit(d, widths)
    fit.loss0 = before = yy / (n * d)
    gg = dict.fromkeys(parts, 0.0)  # squared fit of each segment
    yg = dict.fromkeys(parts, 0.0)
    for k in range(1, iters + 1):
        best = None
        for j in ids:
            p = sum(spaces[j].project(m.block(m.c, j)) for m in parts.values())
            s, a, b = top_triple(p)
            if best is None or s > best[1] * (1 + 1e-12):
                best = (j, s, a, b)
        if best is None or best[1] <= 0:
            break
        j, s, a, b = best
        u, v = spaces[j].t @ a, spaces[j].v @ b
        # each segment: residual with (atom - fit), and squared length of (atom - fit)
        up = down = 0.0
        held = {}
        for h, m in parts.items():
            ua = radius * float(u @ m.block(m.c, j) @ v)
            ya = radius * m.with_response(j, u, v)
            aa = radius * radius * m.fit_norm(j, u) * float(v @ v)
            ga = ya - ua
            up += ua - (yg[h] - gg[h])
            down += aa - 2 * ga + gg[h]
            held[h] = (ya, ga, aa)
        lam = float(min(1.0, max(0.0, up / down))) if down > 0 else 0.0
        for h, m in parts.items():
            ya, ga, aa = held[h]
            m.advance(j, u, v, lam, radius)
            gg[h] = (1 - lam) ** 2 * gg[h] + 2 * lam * (1 - lam) * ga + lam * lam * aa
            yg[h] = (1 - lam) * yg[h] + lam * ya
        loss = max(0.0, (yy - 2 * sum(yg.values()) + sum(gg.values())) / (n * d))
        fit.terms.append((j, radius, u, v))
        fit.trace.append({"k": k, "j": j, "lam": lam, "score": s, "loss": loss, "ratio": loss / before if before > 0 else 1.0, "secs": 0.0})
        fit.stop_index = k
        if ledger is not None:
            for h, m in parts.items():
                for i in ids:
                    ledger.send(2, k, f"seg{h}", "coordinator", "projected", spaces[i].t.shape[1] * spaces[i].v.shape[1])
                ledger.send(2, k, f"seg{h}", "coordinator", "search", 2)
                ledger.send(2, k, f"seg{h}", f"seg{h}", "fit", m.n + d)
        if tol > 0 and before - loss <= tol * before and k > 1:
            break
        before = loss
    fit.spaces = spaces
    return fit


def complexity(n1: int, s: int, d: int, a: float, log: float, printed: bool = True) -> float:
    """Order of doubles per grid node, as printed, or with the logarithm kept on every term as the derivation has it."""
    lead = float(n1) ** max(2 * a, 1) * s**2
    if printed:
        return lead + (s**2 * float(n1) ** a * d + n1) * log + s**10 * log + d * s**8 * log**2
    return lead + s**4 * log * (s**6 + s**2 * float(n1) ** a * d + n1)


def pooled(by_segment: dict):
    total = None
    for _, m in sorted(by_segment.items()):
        total = m if total is None else total + m
    return total


