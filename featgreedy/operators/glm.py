"""The greedy loop for exponential families with scalar response, on segments that never leave Spark.

State per row segment: response, fit. A step takes the scaled residual's products with every column, the largest in
absolute value wins, and a one-dimensional search on [0, 1] over grids of 32 weights, each grid one aggregate,
moves the fit towards ``+-radius`` times the winner's column.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from featgreedy.functions.families import Family
from featgreedy.operators.greedy import RelativePlateauStop
from featgreedy.operators.moments import arrays, cross
from featgreedy.session import ship, stored

STATE = "h int, n_h int, y array<double>, g array<double>"


def _each(fn, *names):
    def run(batches):
        for batch in batches:
            yield fn(batch, *[arrays(batch.column(c)) for c in names])

    return run


def residuals(state: DataFrame, family: Family, n: int) -> DataFrame:
    """Segments of ``(y - mean(fit)) / n`` as one-column matrices for :func:`cross`."""

    def fn(batch, y, g):
        out = [(a - family.mean(b)) / n for a, b in zip(y, g, strict=True)]
        return pa.RecordBatch.from_arrays([batch.column("h"), pa.array([1] * len(out), pa.int32()), pa.array(out, pa.list_(pa.float64()))], ["h", "k", "a"])

    return state.mapInArrow(_each(fn, "y", "g"), "h int, k int, a array<double>")


def glm_line_search(state_z: DataFrame, family: Family, n: int, rounds: int = 3, points: int = 32) -> tuple[float, float]:
    """Best weight and its mean loss; ``state_z`` has ``y, g, z`` with ``z`` the atom's fit."""
    lo, hi, best = 0.0, 1.0, (0.0, None)
    for _ in range(rounds):
        lams = np.linspace(lo, hi, points)

        def run(batches, lams=lams):
            total = np.zeros(len(lams))
            for batch in batches:
                for y, g, z in zip(*[arrays(batch.column(c)) for c in ("y", "g", "z")], strict=True):
                    total += [float(family.loss(y, (1 - m) * g + m * z).sum()) for m in lams]
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(lams)), pa.int32()), pa.array(total)], ["i", "s"])

        got = state_z.select("y", "g", "z").mapInArrow(run, "i int, s double").groupBy("i").agg(F.sum("s").alias("s")).orderBy("i").collect()
        s = np.array([r["s"] for r in got]) / n
        k = int(s.argmin())
        best = (float(lams[k]), float(s[k]))
        lo, hi = float(lams[max(k - 1, 0)]), float(lams[min(k + 1, points - 1)])
    return best


def glm_rga(blocks: DataFrame, segments: DataFrame, family: Family, radius: float, cap: int = 50, t: float = 0.01, only=None) -> dict:
    """Coefficients by (block, column), path and losses. ``only``: the blocks of a second phase, read by a pruned scan."""
    some = blocks if only is None else blocks.filter(F.col("j").isin([int(j) for j in only]))
    zero = F.transform("y", lambda x: x * 0)
    state = stored(segments.select("h", "n_h", "y", zero.alias("g")), "glm")
    n = int(segments.agg(F.sum("n_h")).first()[0])
    before = float(family.cumulant(np.zeros(1))[0])
    coef: dict[tuple[int, int], float] = {}
    trace, rule = [], RelativePlateauStop(t)
    for k in range(1, cap + 1):
        scores = cross(some, residuals(state, family, n)).select("j", F.posexplode("c").alias("l", "s"))
        w = scores.agg(F.max(F.struct(F.abs("s").alias("a"), (-F.col("j")).alias("mj"), (-F.col("l")).alias("ml"), "j", "l", "s")).alias("w")).select("w.*").first()
        sign = 1.0 if w["s"] >= 0 else -1.0
        column = some.filter(F.col("j") == w["j"]).select("h", F.transform(F.slice("x", F.lit(w["l"]) * F.col("n_h") + 1, F.col("n_h")), lambda x: x * (sign * radius)).alias("z"))
        with_z = stored(state.join(column, "h"), "glmz")
        lam, loss = glm_line_search(with_z, family, n)
        state = stored(with_z.select("h", "n_h", "y", F.zip_with("g", "z", lambda a, b: (1 - lam) * a + lam * b).alias("g")), "glm")
        coef = {c: (1 - lam) * v for c, v in coef.items()}
        c = (w["j"], w["l"])
        coef[c] = coef.get(c, 0.0) + lam * sign * radius
        trace.append({"k": k, "j": w["j"], "l": w["l"], "score": w["s"], "lam": lam, "loss": loss})
        if rule.done(before, loss):
            break
        before = loss
    return {"coef": {c: v for c, v in coef.items() if v}, "trace": trace, "stop_index": len(trace)}


def glm_srg(blocks: DataFrame, segments: DataFrame, family: Family, radius: float, cap: int = 50, t: float = 0.01, refit_cap: int = 60, refit_t: float = 1e-5) -> dict:
    """Both phases: the loop with its stop, then the loop on the selected columns' blocks from zero."""
    one = glm_rga(blocks, segments, family, radius, cap, t)
    two = glm_rga(blocks, segments, family, radius, refit_cap, refit_t, only={j for j, _ in one["coef"]})
    return {"support": sorted(one["coef"]), "coef": two["coef"], "phase1": one, "phase2": two}


# the same on arrays that the driver holds, for replications of simulations


def glm_local(x: np.ndarray, y: np.ndarray, family: Family, radius: float, cap: int, t: float, only=None) -> dict:
    """Array version of :func:`glm_rga` with a Newton search, for many small fits."""
    cols = np.arange(x.shape[1]) if only is None else np.array(sorted(only))
    g, n, b = np.zeros(len(y)), len(y), np.zeros(x.shape[1])
    before, rule, trace = float(family.cumulant(np.zeros(1))[0]), RelativePlateauStop(t), []
    for k in range(1, cap + 1):
        s = x[:, cols].T @ (y - family.mean(g)) / n
        i = int(np.abs(s).argmax())
        j, sign = int(cols[i]), 1.0 if s[i] >= 0 else -1.0
        step = sign * radius * x[:, j] - g
        lo, hi, lam = 0.0, 1.0, 0.0
        for _ in range(60):
            fit = g + lam * step
            slope = float(step @ (family.mean(fit) - y))
            lo, hi = (lam, hi) if slope < 0 else (lo, lam)
            curve = float(step @ (family.variance(fit) * step))
            new = lam - slope / curve if curve > 0 else (lo + hi) / 2
            new = new if lo < new < hi else (lo + hi) / 2
            if abs(new - lam) < 1e-12:
                break
            lam = new
        g = g + lam * step
        b *= 1 - lam
        b[j] += lam * sign * radius
        loss = float(family.loss(y, g).mean())
        trace.append({"k": k, "j": j, "lam": lam, "loss": loss})
        if rule.done(before, loss):
            break
        before = loss
    return {"coef": b, "support": np.flatnonzero(b), "trace": trace, "stop_index": len(trace)}


def glm_srg_local(x, y, family: Family, radius: float, t: float, cap: int = 100, refit_cap: int = 400, refit_t: float = 1e-7) -> dict:
    one = glm_local(x, y, family, radius, cap, t)
    two = glm_local(x, y, family, radius, refit_cap, refit_t, only=one["support"])
    return {"support": one["support"], "coef": two["coef"], "phase1": one, "phase2": two}


ship(__name__)
