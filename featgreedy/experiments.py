"""The experiment workloads on planted fixtures: each returns a long table of method, setting and measure.

Replications are rows: seeds are dealt to tasks, each task fits on the broadcast predictors, whose bytes are checked.
"""

from __future__ import annotations

import math
import time

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession

from featgreedy.baselines import lowrank, sparse
from featgreedy.functions.families import LOGIT, POISSON
from featgreedy.operators import glm, measures
from featgreedy.operators.greedy import GRID_PRINTED, PlateauStop, default_threshold, rga
from featgreedy.operators.ledger import Ledger
from featgreedy.operators.model import SRGConfig, from_moments, rmse_moments, tune
from featgreedy.operators.refit import refit
from featgreedy.session import BROADCAST_BYTES, ship
from featgreedy.sources import planted as pl

PATH = "seed int, shape string, method string, k int, value double, test double, secs double"
SCORE = "seed int, shape string, method string, measure string, value double"
#: The published shapes (rows, columns) and (rows, responses, width, blocks, true blocks, ranks).
SCALAR_SHAPES = ((800, 1200), (1200, 2000), (1500, 3000))
VIEW_SHAPES = ((200, 10, 12, 20, 1, 2), (400, 15, 18, 50, 2, 2), (600, 20, 25, 400, 3, 2), (1200, 40, 45, 800, 3, 3))
GLM_SHAPES = ((800, 1200), (1200, 2000))
#: Shapes on which the published study runs the splitting baseline.
SPLIT_SHAPES = VIEW_SHAPES[:2]


def held(shapes, rows: int) -> list:
    """The shapes whose training rows a table of ``rows`` holds beside its test quarter; if none, its own rows with twice the columns."""
    train = rows - rows // 4
    return [s for s in shapes if s[0] <= train] or [(train, 2 * train)]


def replicate(spark: SparkSession, base: np.ndarray, fn, cases, schema: str) -> DataFrame:
    """``fn(base, case, seed)`` gives rows; a case and seed are one unit of work, spread over the executors."""
    if base.nbytes > BROADCAST_BYTES:
        raise MemoryError("the base columns exceed the broadcast bound")
    shared = spark.sparkContext.broadcast(base)
    names = [c.split()[0] for c in schema.split(", ")]
    cases = list(cases)

    def run(batches):
        for pdf in batches:
            for i in pdf["i"]:
                case, seed = cases[i]
                yield pd.DataFrame(fn(shared.value, case, seed), columns=names)

    units = spark.createDataFrame([(i,) for i in range(len(cases))], "i int")
    return units.repartitionByRange(len(cases), "i").mapInPandas(run, schema)


def _path(fit, f: pl.Planted, test, spent: float = 0.0):
    """Squared coefficient error, test error (from the test rows' moments) and seconds after every step, carried on term by term."""
    coef = {j: np.zeros_like(b) for j, b in f.truth.items()}
    out = []
    for (j, radius, u, v), row in zip(fit.terms, fit.trace, strict=True):
        for i in coef:
            coef[i] *= 1 - row["lam"]
        coef[j] = coef.get(j, 0) + row["lam"] * radius * np.outer(u, v)
        spent += row["secs"]
        ids = sorted(coef)
        out.append((measures.err_sq(coef, f.truth), _test_rmse(test, ids, np.array([coef[i][0, 0] for i in ids])), spent))
    return out


def _test_rmse(test, at, b) -> float:
    """Error of coefficients ``b`` of the columns ``at`` (single-column blocks, one response)."""
    c, g = test.c0[at, 0], test.g[np.ix_(at, at)]
    return math.sqrt(max(test.yy - 2 * float(b @ c) + float(b @ (g @ b)), 0.0) / test.n)


def _errors(fit, truth):
    """Squared coefficient error after every step."""
    coef = {j: np.zeros_like(b) for j, b in truth.items()}
    out = []
    for (j, radius, u, v), row in zip(fit.terms, fit.trace, strict=True):
        for i in coef:
            coef[i] *= 1 - row["lam"]
        coef[j] = coef.get(j, 0) + row["lam"] * radius * np.outer(u, v)
        out.append(measures.err_sq(coef, truth))
    return out


def scalar_paths(correlated: bool, rounds: int = 120):
    """Error, test error and seconds by step of the two-phase fit, phase one alone with two radii, the lasso and coordinate descent."""

    def fn(base, shape, seed):
        n, p = shape
        f = pl.plant_scalar(pl.Columns(base, p), f"scalar{int(correlated)}|{seed}", correlated, n)
        m, n, name = f.moments(), len(f.y), f"{n}x{p}"
        rows, truth, seen = [], f.truth, f.test_moments()

        def add(method, path):
            rows.extend((seed, name, method, k, float(e), float(t), float(s)) for k, (e, t, s) in enumerate(path, 1))

        one = rga(m, 500.0, rounds, PlateauStop(default_threshold(n)))
        ranks = one.screened()
        two = refit(m.only(ranks), ranks, 500.0, max(rounds - one.stop_index, 1), 0.0)
        first = _path(one, f, seen)
        add("two_phase", first + _path(two, f, seen, first[-1][2]))
        for method, radius in (("one_phase_500", 500.0), ("one_phase_oracle", float(sum(np.abs(b).sum() for b in truth.values())))):
            m.reset()
            add(method, _path(rga(m, radius, rounds), f, seen))
        y, beta = f.y[:, 0], f.beta[:, 0]
        test = lambda b: _test_rmse(seen, np.flatnonzero(b), b[np.flatnonzero(b)])
        t0 = time.perf_counter()
        b, level = sparse.lasso_cv(f.x, y, count=25)
        add("lasso_cv", [(((b - beta) ** 2).sum(), test(b), time.perf_counter() - t0)])
        for method, frac, accel in (("coordinate_25", 0.25, False), ("coordinate_50", 0.5, False), ("coordinate_50_fast", 0.5, True)):
            got = sparse.coord_descent(f.x, y, level, frac, rounds=rounds, accel=accel, truth=beta, damp=None if not accel else 16.0, watch=test)
            if got:
                add(method, zip(got[1], got[2].seen, got[2].secs, strict=True))
        return rows

    return fn


def view_scores(correlated: bool, radius: float = 1e5):
    """Estimation and prediction errors of the tuned two-phase fit, the splitting baseline and oracle least squares.

    The splitting baseline's level is chosen on 500 validation rows of their own where the table has them beside the
    training and test rows, else on the training rows' held third, as the threshold is.
    """

    def fn(base, shape, seed):
        n, d, q, p, a, r = shape
        name = "x".join(map(str, shape))
        f = pl.plant_views(pl.Columns(base, p * q), f"view{int(correlated)}|{name}|{seed}", d, q, a, r, correlated, train=n, spare=500 if shape in SPLIT_SHAPES else 0)
        m = f.moments()
        rows = []
        fit_rows, held_rows = pl.split_rows(len(f.y), len(f.y) // 3)
        t, _ = tune(f.moments(fit_rows), f.moments(held_rows), SRGConfig(radius=radius, cap=60, refit_iters=300), GRID_PRINTED)
        model = from_moments(m, SRGConfig(radius=radius, cap=60, refit_iters=500), t)
        found = [("two_phase", model.coef), ("oracle_ls", lowrank.oracle_ls(m, f.truth))]
        if shape in SPLIT_SHAPES:
            train, judge = (m, f.spare_moments()) if f.spare() >= 500 else (f.moments(fit_rows), f.moments(held_rows))
            top = max(np.linalg.norm(m.block(m.c0, j), 2) for j in m.ids) / m.n
            levels = top * 0.6 ** np.arange(12)
            scored = [(rmse_moments(judge, coef), level) for level, coef in lowrank.multiview_admm(train, levels, rounds=300, tol=1e-4)]
            best = min(scored)[1]
            *_, (_, coef) = lowrank.multiview_admm(m, [lv for lv in levels if lv >= best], rounds=300, tol=1e-4)
            found.append(("splitting", coef))
        test = f.test_moments({j for _, coef in found for j in coef})
        for method, coef in found:
            rows += [(seed, name, method, "estimation", measures.err_root(coef, f.truth)), (seed, name, method, "prediction", rmse_moments(test, coef))]
        fp, fn_ = measures.fp_fn(model.coef, f.truth)
        rows += [(seed, name, "two_phase", k, float(v)) for k, v in (("false_positives", fp), ("false_negatives", fn_), ("stop_index", model.stop_index), ("screening_ok", measures.screening_ok(model.ranks, f.truth)), ("estimation_per_response", measures.err_norm(model.coef, f.truth, d)))]
        return rows

    return fn


def glm_scores(family_name: str, radius: float, grid):
    """Coefficient error, false selections and test error of the greedy and the penalised generalized linear fits."""
    family = LOGIT if family_name == "logit" else POISSON

    def fn(base, shape, seed):
        x = pl.replicas(base, shape[1])
        f = pl.plant_glm(x, f"{family_name}|{seed}", family_name, shape[0])
        y, beta, n = f.y[:, 0], f.beta[:, 0], len(f.y)
        keep, held = pl.split_rows(n, n // 3)
        best = None
        for g in grid:
            fit = glm.glm_srg_local(f.x[keep], y[keep], family, radius, g / math.log(n), cap=60)
            loss = float(family.loss(y[held], f.x[held] @ fit["coef"]).mean())
            best = (loss, g) if best is None or loss < best[0] else best
        fit = glm.glm_srg_local(f.x, y, family, radius, best[1] / math.log(n), cap=60)
        found = [("two_phase", fit["coef"]), ("l1", sparse.l1_glm_cv(f.x, y, family, count=12)[0])]
        rows = []
        for method, b in found:
            fp, fn_ = measures.fp_fn(np.flatnonzero(np.abs(b) > 1e-8), np.flatnonzero(beta))
            g = f.x_test @ b
            test = measures.accuracy((g > 0).astype(float), f.y_test[:, 0]) if family_name == "logit" else measures.rmse(family.mean(g), f.y_test[:, 0])
            for k, v in (("l2_error", float(np.sqrt(((b - beta) ** 2).sum()))), ("false_positives", fp), ("false_negatives", fn_), ("test", test)):
                rows.append((seed, f"{n}x{x.shape[1]}", method, k, float(v)))
        return rows

    return fn


def communication(fits: dict, nodes: int = 4, rounds: int = 400) -> list[tuple]:
    """Bytes that each protocol sends while the number of columns grows and the rows stay, from the moments ``fits`` by number of columns."""
    rows = []
    for p, m in fits.items():
        for wire in ("eager", "lazy"):
            led = Ledger(wire, nodes)
            m.reset()
            one = rga(m, 500.0, 200, PlateauStop(default_threshold(m.n)), led, wire)
            ranks = one.screened()
            refit(m.only(ranks), ranks, 500.0, 200, 1e-8, led)
            rows.append((p, f"two_phase_{wire}", led.total()))
        rows.append((p, "two_phase_state", len({t[0] for t in one.terms}) * m.n * 8 * nodes))
        # rounds that update 64 columns each, until the error is within a tenth of where it settles
        level = 2 * math.sqrt(math.log(p) / m.n)
        _, errs, led = sparse.coord_descent(m, None, level, 64 / p, nodes, rounds, damp=2.0)
        need = measures.iters_to(errs, 1.1 * min(errs))
        rows.append((p, "coordinate", sum(r[-1] for r in led.rows if r[2] <= need)))
        rows.append((p, "sketch", lowrank.dual_sketch_ridge(m, None, 0.1, 64, nodes)[1]))
    return rows


ship(__name__)
