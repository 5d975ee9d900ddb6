"""The two-phase fit end to end: configuration, model, tuning by holdout, pruning, prediction, saving."""

from __future__ import annotations

import json
import math
import time
from dataclasses import asdict, dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from featgreedy.operators import moments
from featgreedy.operators.greedy import GRID_PRINTED, Fit, PlateauStop, default_threshold, rga
from featgreedy.operators.kernel import numeric_rank
from featgreedy.operators.ledger import Ledger
from featgreedy.operators.moments import ArrayMoments, GramMoments, StateMoments, arrays, gram_moments, matrix
from featgreedy.operators.refit import refit, refit_state
from featgreedy.session import ship


@dataclass
class SRGConfig:
    """``radius`` a number or 'auto'; ``threshold`` a number, 'default' or a grid in units of one over log n."""

    radius: float | str = 500.0
    threshold: object = "default"
    cap: int = 200
    refit_iters: int = 500
    refit_tol: float = 1e-10
    mode: str = "auto"  # 'gram', 'state' or 'auto'
    wire: str = "eager"
    nodes: int = 4
    center: bool = False
    holdout: float = 1 / 3
    prune_tau: float = 0.0
    rank_tol: float = 1e-9
    total_rank: float | None = None  # of phase two; None: the screened ranks' sum


@dataclass
class SRGModel:
    coef: dict[int, np.ndarray]
    phase1: Fit
    phase2: Fit
    ranks: dict[int, int]
    ledger: Ledger
    intercept: np.ndarray
    threshold: float
    secs: float = 0.0
    tuning: list[dict] = field(default_factory=list)

    @property
    def support(self) -> list[int]:
        return sorted(self.coef)

    @property
    def stop_index(self) -> int:
        return self.phase1.stop_index

    def coef_frame(self, spark: SparkSession) -> DataFrame:
        rows = [(int(j), b.shape[0], b.shape[1], [float(x) for x in b.ravel()], numeric_rank(b), self.ranks.get(j, 0), float(np.sqrt((b * b).sum()))) for j, b in self.coef.items()]
        return spark.createDataFrame(rows, "j int, q int, d int, b array<double>, rank int, rank_bound int, norm_f double")

    def trace_frame(self, spark: SparkSession) -> DataFrame:
        rows = [(p, r["k"], int(r["j"]), float(r["lam"]), float(r["score"]), float(r["loss"]), float(r["ratio"]), float(r["secs"])) for p, f in ((1, self.phase1), (2, self.phase2)) for r in f.trace]
        return spark.createDataFrame(rows, "phase int, k int, j int, lam double, score double, loss double, ratio double, secs double")

    def summary(self) -> dict:
        return {"stop_index": self.stop_index, "support": self.support, "ranks": {j: numeric_rank(b) for j, b in self.coef.items()}, "rank_bounds": self.ranks, "bytes": self.ledger.total(), "threshold": self.threshold}

    def save(self, spark: SparkSession, path: str) -> None:
        """Coefficients, trace and ledger as Parquet tables under ``path``."""
        self.coef_frame(spark).write.mode("overwrite").parquet(f"{path}/coef")
        self.trace_frame(spark).write.mode("overwrite").parquet(f"{path}/trace")
        self.ledger.frame(spark).write.mode("overwrite").parquet(f"{path}/ledger")
        meta = json.dumps({"intercept": self.intercept.tolist(), "threshold": self.threshold})
        spark.createDataFrame([(meta,)], "meta string").write.mode("overwrite").parquet(f"{path}/meta")


def load_coef(spark: SparkSession, path: str) -> tuple[dict[int, np.ndarray], np.ndarray]:
    coef = {r["j"]: np.array(r["b"]).reshape(r["q"], r["d"]) for r in spark.read.parquet(f"{path}/coef").collect()}
    return coef, np.array(json.loads(spark.read.parquet(f"{path}/meta").first()["meta"])["intercept"])


def auto_radius(held: GramMoments) -> float:
    """Ten times the nuclear norms of blockwise ridge fits: wide enough not to bind."""
    total = 0.0
    for j in held.ids:
        g = held.gram(j)
        b = np.linalg.solve(g + 1e-3 * np.trace(g) / max(len(g), 1) * np.eye(len(g)) + 1e-12 * np.eye(len(g)), held.block(held.c0, j))
        total += np.linalg.svd(b, compute_uv=False).sum()
    return 10 * total


def from_moments(held: GramMoments, config: SRGConfig, threshold: float | None = None, run: str = "srg") -> SRGModel:
    """Both phases on moments that the driver holds."""
    began = time.perf_counter()
    source = held.centred() if config.center else held
    source.reset()
    radius = auto_radius(source) if config.radius == "auto" else float(config.radius)
    t = threshold if threshold is not None else default_threshold(source.n) if config.threshold == "default" else float(config.threshold)
    ledger = Ledger(run, config.nodes)
    one = rga(source, radius, config.cap, PlateauStop(t), ledger, config.wire)
    return second_phase(one, source, config, radius, t, ledger, began)


def second_phase(one: Fit, source: GramMoments, config: SRGConfig, radius: float, t: float, ledger: Ledger, began: float, upto: int | None = None) -> SRGModel:
    ranks = one.screened(upto, config.rank_tol)
    zero = np.zeros(source.d)
    if not ranks:
        return SRGModel({}, one, Fit(source.d, {}), {}, ledger, zero, t)
    two = refit(source.only(ranks), ranks, radius, config.refit_iters, config.refit_tol, ledger, config.total_rank)
    coef = two.coef()
    if config.prune_tau:
        keep = {j: ranks[j] for j, b in coef.items() if np.sqrt((b * b).sum()) >= config.prune_tau}
        if keep and len(keep) < len(coef):
            two = refit(source.only(keep), keep, radius, config.refit_iters, config.refit_tol, ledger, config.total_rank)
            coef, ranks = two.coef(), keep
    intercept = zero
    if hasattr(source, "means"):
        intercept = source.y_mean - sum((source.means[slice(*source.range[j])] @ b for j, b in coef.items()), zero)
    return SRGModel(coef, one, two, ranks, ledger, intercept, t, time.perf_counter() - began)


def fit(blocks: DataFrame, segments: DataFrame, config: SRGConfig) -> SRGModel:
    """Fit from Spark: inner products on the driver while they are within ``GRAM_BYTES``, else phase one by per-block
    rows in Spark, and phase two on the moments of the screened blocks, read with a pruned scan, or again by rows."""
    size = blocks.select("j", "q").distinct().agg(F.sum("q").alias("q")).first()["q"] or 0
    within = lambda q: (q + 1) ** 2 * 8 <= moments.GRAM_BYTES
    if config.mode == "gram" or config.mode == "auto" and within(size):
        return from_moments(gram_moments(blocks, segments), config)
    began = time.perf_counter()
    state = StateMoments(blocks, segments)
    radius = float(config.radius)
    t = default_threshold(state.n) if config.threshold == "default" else float(config.threshold)
    ledger = Ledger("srg", config.nodes)
    one = rga(state, radius, config.cap, PlateauStop(t), ledger, config.wire)
    ranks = one.screened(tol=config.rank_tol)
    if not ranks or within(sum(one.widths[j] for j in ranks) + state.d):
        return second_phase(one, gram_moments(blocks, segments, list(ranks)) if ranks else state, config, radius, t, ledger, began)
    two = refit_state(state, ranks, radius, config.refit_iters, config.refit_tol, ledger, config.total_rank)
    coef = two.coef()
    if config.prune_tau:
        keep = {j: ranks[j] for j, b in coef.items() if np.sqrt((b * b).sum()) >= config.prune_tau}
        if keep and len(keep) < len(coef):
            two, ranks = refit_state(state, keep, radius, config.refit_iters, config.refit_tol, ledger, config.total_rank), keep
            coef = two.coef()
    return SRGModel(coef, one, two, ranks, ledger, np.zeros(state.d), t, time.perf_counter() - began)


def wired(blocks: DataFrame, segments: DataFrame, radius: float, cap: int, nodes: int = 4, lazy: bool = False):
    """Phase one as the message protocol itself: nodes hold columns and the residual, the driver coordinates.

    For one row segment. Each round the nodes' best atoms (eager) or scores (lazy) travel; kept as a reference for
    the other modes and the ledger, since it ships row-length vectors.
    """
    from featgreedy.operators.kernel import line_search, top_triple

    seg = segments.first()
    n, d = seg["n_h"], seg["d"]
    y = np.array(seg["y"]).reshape(n, d)
    g = np.zeros_like(y)
    sc = blocks.sparkSession.sparkContext
    out, ledger = [], Ledger("wire", nodes)
    for k in range(1, cap + 1):
        shared = sc.broadcast(y - g)

        def best(batches, shared=shared, lazy=lazy):
            top: dict[int, tuple] = {}
            for batch in batches:
                for j, q, x in zip(batch.column("j").to_pylist(), batch.column("q").to_pylist(), arrays(batch.column("x")), strict=True):
                    m = matrix(x, n, q)
                    s, u, v = top_triple(m.T @ shared.value)
                    c = j % nodes
                    if c not in top or (s, -j) > (top[c][0], -top[c][1]):
                        top[c] = (s, j, u, v, m @ u)
            for c, (s, j, u, v, xu) in top.items():
                empty = np.zeros(0)
                yield pa.RecordBatch.from_arrays([pa.array([c], pa.int32()), pa.array([s]), pa.array([j], pa.int32())] + [pa.array([empty if lazy and i else z], pa.list_(pa.float64())) for i, z in enumerate((u, v, xu))], ["c", "s", "j", "u", "v", "xu"])

        rows = blocks.mapInArrow(best, "c int, s double, j int, u array<double>, v array<double>, xu array<double>").collect()  # one row a node and task
        w = max(rows, key=lambda r: (r["s"], -r["j"]))
        if lazy:
            (ledger.lazy)(1, k, n, d, w["c"])
            x = blocks.filter(F.col("j") == w["j"]).first()
            m = matrix(x["x"], n, x["q"])
            _, u, v = top_triple(m.T @ (y - g))
            xu = m @ u
        else:
            ledger.eager(1, k, n, d)
            u, v, xu = np.array(w["u"]), np.array(w["v"]), np.array(w["xu"])
        shared.unpersist()
        a = radius * np.outer(xu, v)
        lam = line_search(float(((y - g) * a).sum()), float((g * a).sum()), float((a * a).sum()), float((y * g).sum()), float((g * g).sum()))
        g = (1 - lam) * g + lam * a
        out.append((w["j"], lam, float(((y - g) ** 2).sum() / (n * d))))
    ledger.flush(1, cap, n, d)
    return out, ledger


def tune(train: GramMoments, held: GramMoments, config: SRGConfig, grid=GRID_PRINTED) -> tuple[float, list[dict]]:
    """Threshold from a grid over log n by the error on held-out rows.

    One phase-one path with the smallest threshold serves all: stop indices are nested, so larger thresholds are read
    off the trace and phase two runs once per distinct stop index.
    """
    n = train.n
    source = train.centred() if config.center else train
    source.reset()
    radius = auto_radius(source) if config.radius == "auto" else float(config.radius)
    one = rga(source, radius, config.cap, PlateauStop(min(grid) / math.log(n)))
    table, seen = [], {}
    for g in grid:
        t = g / math.log(n)
        k = one.stop_for(t)
        if k not in seen:
            model = second_phase(one, source, config, radius, t, Ledger("tune", config.nodes), time.perf_counter(), upto=k)
            seen[k] = rmse_moments(held, model.coef, model.intercept)
        table.append({"grid": g, "threshold": t, "stop_index": k, "rmse": seen[k]})
    best = min(table, key=lambda r: (r["rmse"], -r["threshold"]))
    return best["threshold"], table


def rmse_moments(m: GramMoments, coef: dict[int, np.ndarray], intercept: np.ndarray | None = None) -> float:
    """Root mean square error of a coefficient set, from moments of the rows it is measured on."""
    if isinstance(m, ArrayMoments):
        m = m.only(coef)
    b = np.zeros_like(m.c0)
    for j, x in coef.items():
        b[slice(*m.range[j])] = x
    loss = m.yy - 2 * float((b * m.c0).sum()) + float((b * (m.g @ b)).sum())
    if intercept is not None and np.any(intercept):
        loss += m.n * intercept @ intercept - 2 * intercept @ m.y_sum + 2 * (m.sums @ b) @ intercept
    return math.sqrt(max(loss, 0.0) / (m.n * m.d))


def predict(blocks: DataFrame, coef: dict[int, np.ndarray], d: int, intercept: np.ndarray | None = None) -> DataFrame:
    """``h, t0, n_h, yhat`` (row-major): a pruned scan of the selected blocks, then sums by segment."""
    held = blocks.sparkSession.sparkContext.broadcast(coef)
    base = np.zeros(d) if intercept is None else np.asarray(intercept, float)

    def run(batches):
        for batch in batches:
            out = []
            for j, n, q, x in zip(batch.column("j").to_pylist(), batch.column("n_h").to_pylist(), batch.column("q").to_pylist(), arrays(batch.column("x")), strict=True):
                out.append((matrix(x, n, q) @ held.value[j]).ravel())
            yield pa.RecordBatch.from_arrays([batch.column("h"), batch.column("t0"), batch.column("n_h"), pa.array(out, pa.list_(pa.float64()))], ["h", "t0", "n_h", "yhat"])

    def total(key, table):
        s = sum(arrays(table.column("yhat"))).reshape(-1, d) + base
        return pa.table({"h": table.column("h")[:1], "t0": table.column("t0")[:1], "n_h": table.column("n_h")[:1], "yhat": pa.array([s.ravel()], pa.list_(pa.float64()))})

    some = blocks.filter(F.col("j").isin([int(j) for j in coef])).select("j", "h", "t0", "n_h", "q", "x")
    parts = some.mapInArrow(run, "h int, t0 long, n_h int, yhat array<double>")
    return parts.groupBy("h").applyInArrow(total, "h int, t0 long, n_h int, yhat array<double>")


def describe(config: SRGConfig) -> dict:
    return asdict(config)


ship(__name__)
