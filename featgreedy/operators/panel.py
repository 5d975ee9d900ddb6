"""The panel workload: monthly measures by entity from daily sales, their twelve-vectors by year, lagged designs, and
one-year-ahead forecasts by the two-phase fit and its comparators."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from featgreedy.baselines import lowrank, sparse
from featgreedy.operators import measures
from featgreedy.operators.greedy import GRID_PANEL
from featgreedy.operators.model import SRGConfig, from_moments, tune
from featgreedy.operators.moments import GramMoments
from featgreedy.sources.tables import table

MEASURES = ("v", "m", "b", "r")


def daily(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``entity, dt, rev, qty``: sales of (supplier's nation, return flag) by ship date, as decimals."""
    li = table(spark, sf_dir, "lineitem").select("l_suppkey", "l_returnflag", F.to_date("l_shipdate").alias("dt"), "l_extendedprice", "l_quantity")
    su = table(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey")
    g = li.join(su, li.l_suppkey == su.s_suppkey).withColumn("entity", F.concat_ws("-", F.col("s_nationkey").cast("string"), "l_returnflag"))
    return g.groupBy("entity", "dt").agg(F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).alias("rev"), F.sum(F.col("l_quantity").cast("decimal(18,2)")).alias("qty"))


def monthly(days: DataFrame) -> DataFrame:
    """``entity, year, month, v, b, m``: log variance of log sales, slope on the market, log volume."""
    market = days.groupBy("dt").agg(F.sum("rev").alias("market"))
    j = days.join(market, "dt").select("entity", F.year("dt").alias("year"), F.month("dt").alias("month"), F.ln(F.col("rev").cast("double")).alias("lr"), F.ln(F.col("market").cast("double")).alias("lm"), "qty")
    g = j.groupBy("entity", "year", "month").agg(F.count("*").alias("days"), F.var_samp("lr").alias("var"), F.regr_slope("lr", "lm").alias("slope"), F.avg("lr").alias("level"), F.sum("qty").alias("qty"))
    ok = F.col("days") >= 2
    return g.select("entity", "year", "month", "days", F.when(ok & (F.col("var") > 0), F.ln("var")).alias("v"), F.when(ok, F.col("slope")).alias("b"), "level", F.ln(F.col("qty").cast("double")).alias("volume"))


def measures_by_month(months: DataFrame) -> DataFrame:
    """Adds ``r`` (level less the month before) and ``m`` (volume less the same month a year before)."""
    w = Window.partitionBy("entity").orderBy("year", "month")
    prior = months.select("entity", (F.col("year") + 1).alias("year"), "month", F.col("volume").alias("volume_before"))
    out = months.withColumn("r", F.col("level") - F.lag("level").over(w)).join(prior, ["entity", "year", "month"], "left")
    return out.withColumn("m", F.col("volume") - F.col("volume_before")).drop("volume_before")


def vectors(panel: DataFrame, first: int, last: int) -> DataFrame:
    """``entity, year, v, m, b, r``: twelve-vectors; gaps take the entity-year mean, else zero."""
    years = panel.filter(F.col("year").between(first, last))
    month = F.sequence(F.lit(1), F.lit(12))
    agg = []
    for c in MEASURES:
        agg += [F.map_from_entries(F.collect_list(F.struct("month", F.col(c)))).alias(c), F.avg(c).alias(f"{c}_mean")]
    g = years.groupBy("entity", "year").agg(*agg)
    pick = lambda c: F.transform(month, lambda i: F.coalesce(F.try_element_at(F.col(c), i), F.col(f"{c}_mean"), F.lit(0.0)))
    return g.select("entity", "year", *[pick(c).alias(c) for c in MEASURES])


def fences(panel: DataFrame, width: float = 5.0) -> DataFrame:
    """Entities with no value outside median +- ``width`` interquartile ranges (own rule)."""
    out = None
    for c in MEASURES:
        q = panel.agg(F.percentile(c, [0.25, 0.5, 0.75]).alias("q"))
        bad = panel.join(F.broadcast(q)).filter((F.col(c) < F.col("q")[1] - width * (F.col("q")[2] - F.col("q")[0])) | (F.col(c) > F.col("q")[1] + width * (F.col("q")[2] - F.col("q")[0]))).select("entity")
        out = bad if out is None else out.union(bad)
    return panel.select("entity").distinct().join(out.distinct(), "entity", "left_anti")


def lagged(vec: DataFrame) -> DataFrame:
    """This year's vectors with last year's, by a join on (entity, year - 1)."""
    before = vec.select("entity", (F.col("year") + 1).alias("year"), *[F.col(c).alias(f"lag_{c}") for c in MEASURES])
    return vec.join(before, ["entity", "year"])


def text_blocks(scores: DataFrame, entities: DataFrame, first: int, years: int) -> DataFrame:
    """``entity, year, text``: mean score of the documents dealt to each (entity, year) by id."""
    w = Window.orderBy("entity")
    e = entities.select("entity").distinct().withColumn("e", F.row_number().over(w) - 1)
    n = e.count()
    s = scores.select((F.col("doc") % n).alias("e"), (F.floor(F.col("doc") / n) % years + first).cast("int").alias("year"), F.posexplode("x").alias("i", "x"))
    g = s.groupBy("e", "year", "i").agg(F.avg("x").alias("x")).groupBy("e", "year").agg(F.sort_array(F.collect_list(F.struct("i", "x"))).alias("p"))
    return g.join(F.broadcast(e), "e").select("entity", "year", F.col("p.x").alias("text"))


def _moments(parts: list[np.ndarray], y: np.ndarray) -> GramMoments:
    x = np.hstack(parts)
    return GramMoments(range(len(parts)), [p.shape[1] for p in parts], x.T @ x, x.T @ y, (y * y).sum(), len(y), x.sum(0), y.sum(0))


def forecast(design, target: str, k: int | None) -> list[tuple[str, float]]:
    """Errors on the last year of all methods; ``design`` is a bounded pandas table of the lagged panel."""
    last = design["year"].max()
    train, test = design[design["year"] < last], design[design["year"] == last]
    stack = lambda d, c: np.stack(d[c].map(np.asarray).to_numpy()).astype(float)
    names = [f"lag_{c}" for c in MEASURES]
    y, yt = stack(train, target), stack(test, target)
    xs, xt = [stack(train, c) for c in names], [stack(test, c) for c in names]
    if k:
        xs.append(stack(train, "text")[:, :k])
        xt.append(stack(test, "text")[:, :k])
    out = []
    mean_x, mean_y = [x.mean(0) for x in xs], y.mean(0)
    sd = [np.maximum(x.std(0), 1e-9) for x in xs]
    zs, zt = [(x - m) / s for x, m, s in zip(xs, mean_x, sd, strict=True)], [(x - m) / s for x, m, s in zip(xt, mean_x, sd, strict=True)]
    yc = y - mean_y
    if not k:
        ridge = lambda a, b: np.linalg.lstsq(a, b, rcond=None)[0]
        own = MEASURES.index(target)
        allx, allt = np.hstack(xs[:4]), np.hstack(xt[:4])
        full_y = np.hstack([stack(train, c) for c in MEASURES])
        out.append(("var", measures.rmse((allt @ ridge(allx, full_y))[:, own * 12 : own * 12 + 12], yt)))
        out.append(("gvar", measures.rmse(xt[own] @ ridge(xs[own], y), yt)))
        m = _moments([np.hstack(zs[:4])], yc)
        b, _ = lowrank.reduced_rank(m.g, m.c0, m.yy, m.n)
        out.append(("reduced_rank", measures.rmse(np.hstack(zt[:4]) @ b + mean_y, yt)))
    m = _moments(zs, yc)
    rng = np.random.default_rng(3).permutation(len(yc))
    held, keep = rng[: len(rng) // 3], rng[len(rng) // 3 :]
    cut = lambda rows: _moments([z[rows] for z in zs], yc[rows])
    z, ztest = np.hstack(zs), np.hstack(zt)
    g, c = z.T @ z, z.T @ yc
    pred = np.empty_like(yt)
    zk, ck = z[keep].T @ z[keep], z[keep].T @ yc[keep]
    for i in range(12):
        levels, b, best = sparse.level_grid(c[:, i], len(yc), 8), None, None
        for lv in levels:
            b = sparse.lasso_gram(zk, ck[:, i], len(keep), lv, b, tol=1e-4)
            e = float(((yc[held, i] - z[held] @ b) ** 2).sum())
            best = (e, lv) if best is None or e < best[0] else best
        pred[:, i] = ztest @ sparse.lasso_gram(g, c[:, i], len(yc), best[1], tol=1e-4) + mean_y[i]
    out.append(("lasso", measures.rmse(pred, yt)))
    tm = _moments(zt, yt - mean_y)
    from featgreedy.operators.model import rmse_moments

    top = max(np.linalg.norm(m.block(m.c0, j), 2) for j in m.ids) / m.n
    grid = top * 0.5 ** np.arange(7)
    scored = [(rmse_moments(cut(held), coef), lv) for lv, coef in lowrank.multiview_admm(cut(keep), grid, rounds=100, tol=1e-3)]
    *_, (_, coef) = lowrank.multiview_admm(m, [lv for lv in grid if lv >= min(scored)[1]], rounds=100, tol=1e-3)
    out.append(("splitting", rmse_moments(tm, coef)))
    config = SRGConfig(radius="auto", cap=60, refit_iters=150)
    t, _ = tune(cut(keep), cut(held), config, GRID_PANEL)
    out.append(("two_phase", rmse_moments(tm, from_moments(m, config, t).coef)))
    return out
