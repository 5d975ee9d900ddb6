"""The methods, their measures and small exact instances, with SQL where SQL can express them."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Window
from pyspark.sql import functions as F

from featgreedy.baselines import lowrank, sparse
from featgreedy.functions import draws
from featgreedy.functions.arrays import doubles
from featgreedy.functions.families import LOGIT, POISSON
from featgreedy.operators import grid, layout, measures
from featgreedy.operators.greedy import rga
from featgreedy.operators.ledger import Ledger, summary
from featgreedy.operators.model import SRGConfig, from_moments, tune
from featgreedy.operators.moments import GramMoments, StateMoments, gram_moments
from featgreedy.operators.refit import refit
from featgreedy.queries.registry import query, t
from featgreedy.sources import planted

# the scalar instance: 64 standardised columns, response = label less its mean

_SCALAR = """b AS (SELECT vec_id, label::DOUBLE AS y, unnest(embedding)::DOUBLE AS v, unnest(range(64)) AS i FROM embeddings),
s AS (SELECT i, avg(v) AS m, stddev_pop(v) AS sd FROM b GROUP BY i),
z AS (SELECT b.vec_id, b.i, (b.v - s.m) / s.sd AS x, b.y - (SELECT avg(label) FROM embeddings) AS y FROM b JOIN s ON b.i = s.i),
cv AS (SELECT i, sum(x * y) AS c FROM z GROUP BY i)"""

_LOOP = (
    "WITH RECURSIVE "
    + _SCALAR
    + """,
c0 AS (SELECT list(c ORDER BY i) AS c0 FROM cv),
gm AS (SELECT list(r ORDER BY i) AS g FROM (SELECT i, list(g ORDER BY k) AS r FROM (SELECT a.i, q.i AS k, sum(a.x * q.x) AS g FROM z a JOIN z q ON a.vec_id = q.vec_id GROUP BY 1, 2) GROUP BY i)),
tot AS (SELECT sum(y * y) AS yy, count(*)::DOUBLE AS n FROM z WHERE i = 0),
r(k, c, yg, gg, j, lam, loss) AS (
 SELECT 0, c0, 0.0::DOUBLE, 0.0::DOUBLE, -1, 0.0::DOUBLE, yy / n FROM c0, tot
 UNION ALL
 SELECT k + 1, list_transform(list_zip(c, list_zip(c0, g[j])), lambda w: (1 - lam) * w[1] + lam * (w[2][1] - {L} * sg * w[2][2])),
        (1 - lam) * yg + lam * ya, (1 - lam) * (1 - lam) * gg + 2 * lam * (1 - lam) * ga + lam * lam * aa, (j - 1)::INT, lam,
        (yy - 2 * ((1 - lam) * yg + lam * ya) + (1 - lam) * (1 - lam) * gg + 2 * lam * (1 - lam) * ga + lam * lam * aa) / n
 FROM (SELECT *, greatest(0.0, least(1.0, (ua - (yg - gg)) / (aa - 2 * ga + gg))) AS lam FROM
  (SELECT *, ya - ua AS ga FROM
   (SELECT *, {L} * s1 AS ua, {L} * sg * c0[j] AS ya, {L} * {L} * g[j][j] AS aa FROM
    (SELECT *, CASE WHEN c[j] < 0 THEN -1.0 ELSE 1.0 END AS sg, abs(c[j]) AS s1 FROM
     (SELECT r.*, c0.c0, gm.g, tot.yy, tot.n, list_position(list_transform(c, lambda w: abs(w)), list_max(list_transform(c, lambda w: abs(w)))) AS j FROM
       (SELECT k, c, yg, gg FROM r WHERE k < {K}) r, c0, gm, tot))))))
"""
)


def _loop(select: str, radius: float, steps: int) -> str:
    return _LOOP.replace("{L}", f"{float(radius)}").replace("{K}", str(steps)) + select


def scalar_wide(spark, d):
    """``t, f, y`` of the scalar instance."""
    base = planted.base(spark, d)
    e = layout.numbered(t(spark, d, "embeddings").select("vec_id", "label"), "vec_id")
    m = t(spark, d, "embeddings").agg(F.avg("label").alias("m"))
    y = e.join(F.broadcast(m)).select("t", F.array(F.col("label") - F.col("m")).alias("y"))
    return base.join(y, "t")


def scalar_moments(spark, d) -> GramMoments:
    w = scalar_wide(spark, d)
    return gram_moments(layout.to_blocks(w, [1] * 64), layout.to_segments(w))


def label_wide(spark, d, centred: bool = True):
    """``t, f, y``: raw embedding and label indicators, less their means."""
    e = layout.numbered(t(spark, d, "embeddings").select("vec_id", "embedding", "label"), "vec_id")
    y = F.transform(F.sequence(F.lit(0), F.lit(9)), lambda k: (F.col("label") == k).cast("double"))
    w = e.select("t", doubles(F.col("embedding")).alias("f"), y.alias("y"))
    if not centred:
        return w
    m = w.select(F.posexplode("y").alias("i", "v")).groupBy("i").agg(F.avg("v").alias("m")).agg(F.sort_array(F.collect_list(F.struct("i", "m"))).alias("m"))
    return w.join(F.broadcast(m)).select("t", "f", F.zip_with("y", "m", lambda a, b: a - b["m"]).alias("y"))


def label_blocks(spark, d, seg: int | None = None):
    w = label_wide(spark, d)
    return layout.to_blocks(w, [8] * 8, seg), layout.to_segments(w, seg)


@query("WITH " + _SCALAR + " SELECT i::INT AS j, round(abs(c), 6) AS score FROM cv")
def rga_scalar_scores(spark, d):
    cells = scalar_wide(spark, d).select("t", F.posexplode("f").alias("j", "v"), F.col("y")[0].alias("y"))
    return cells.groupBy("j").agg(F.round(F.abs(F.sum(F.col("v") * F.col("y"))), 6).alias("score"))


@query("WITH " + _SCALAR + " SELECT i::INT AS j, round(abs(c), 6) AS score FROM cv ORDER BY abs(c) DESC, i LIMIT 1")
def rga_scalar_first_pick(spark, d):
    cells = scalar_wide(spark, d).select(F.posexplode("f").alias("j", "v"), F.col("y")[0].alias("y"))
    s = cells.groupBy("j").agg(F.abs(F.sum(F.col("v") * F.col("y"))).alias("s"))
    return s.agg(F.max(F.struct("s", (-F.col("j")).alias("m"))).alias("w")).select((-F.col("w.m")).alias("j"), F.round("w.s", 6).alias("score"))


@query("WITH " + _SCALAR + " SELECT i::INT AS j, round(c, 6) AS c FROM cv ORDER BY abs(c) DESC, i LIMIT 10")
def marginal_screen_top10(spark, d):
    cells = scalar_wide(spark, d).select(F.posexplode("f").alias("j", "v"), F.col("y")[0].alias("y"))
    g = cells.groupBy("j").agg(F.sum(F.col("v") * F.col("y")).alias("c"))
    return g.orderBy(F.abs("c").desc(), "j").limit(10).select("j", F.round("c", 6).alias("c"))


def _path_rows(spark, f):
    return spark.createDataFrame([(r["k"], int(r["j"]), round(float(r["lam"]), 6), round(float(r["loss"]), 6)) for r in f.trace], "k int, j int, lam double, loss double")


@query(_loop("SELECT k, j::INT AS j, round(lam, 6) AS lam, round(loss, 6) AS loss FROM r WHERE k > 0", 50, 10))
def rga_scalar_path_10(spark, d):
    """Ten steps of phase one with radius 50 and no stop."""
    return _path_rows(spark, rga(scalar_moments(spark, d), 50.0, 10))


@query(_loop("SELECT k, j::INT AS j, round(lam, 6) AS lam, round(loss, 6) AS loss FROM r WHERE k > 0", 50, 10))
def rga_scalar_path_recursive_sql(spark, d):
    """The same path as one recursive query: the state is one row of arrays, joined to the moment rows."""
    cells = scalar_wide(spark, d).select("t", "f", F.col("y")[0].alias("y"))
    c = cells.select(F.posexplode("f").alias("i", "x"), "y").groupBy("i").agg(F.sum(F.col("x") * F.col("y")).alias("c")).agg(F.sort_array(F.collect_list(F.struct("i", "c"))).alias("c")).select(F.col("c.c").alias("c0"))
    g = cells.select(F.posexplode("f").alias("i", "x"), "f").select("i", "x", F.posexplode("f").alias("k", "z")).groupBy("i", "k").agg(F.sum(F.col("x") * F.col("z")).alias("g"))
    g = g.groupBy("i").agg(F.sort_array(F.collect_list(F.struct("k", "g"))).alias("r")).select("i", F.col("r.g").alias("r")).agg(F.sort_array(F.collect_list(F.struct("i", "r"))).alias("g")).select(F.col("g.r").alias("g"))
    y = cells.agg(F.sum(F.col("y") * F.col("y")).alias("yy"), F.count("*").cast("double").alias("n"))
    from featgreedy.session import stored

    stored(c.join(g).join(y), "moments").createOrReplaceTempView("fg_moments")
    return spark.sql("""
        WITH RECURSIVE r(k, c, yg, gg, j, lam, loss) AS (
          SELECT 0, c0, 0.0D, 0.0D, -1, 0.0D, yy / n FROM fg_moments
          UNION ALL
          SELECT k + 1, zip_with(c, zip_with(c0, g[j - 1], (a, b) -> a - 50.0D * sg * b), (a, b) -> (1 - lam) * a + lam * b),
                 (1 - lam) * yg + lam * ya, (1 - lam) * (1 - lam) * gg + 2 * lam * (1 - lam) * ga + lam * lam * aa, CAST(j - 1 AS INT), lam,
                 (yy - 2 * ((1 - lam) * yg + lam * ya) + (1 - lam) * (1 - lam) * gg + 2 * lam * (1 - lam) * ga + lam * lam * aa) / n
          FROM (SELECT *, greatest(0.0D, least(1.0D, (ua - (yg - gg)) / (aa - 2 * ga + gg))) AS lam FROM
               (SELECT *, ya - ua AS ga FROM
               (SELECT *, 50.0D * abs(c[j - 1]) AS ua, 50.0D * sg * c0[j - 1] AS ya, 2500.0D * g[j - 1][j - 1] AS aa FROM
               (SELECT *, CASE WHEN c[j - 1] < 0 THEN -1.0D ELSE 1.0D END AS sg FROM
               (SELECT r.k, r.c, r.yg, r.gg, m.c0, m.g, m.yy, m.n, CAST(array_position(transform(r.c, a -> abs(a)), array_max(transform(r.c, a -> abs(a)))) AS INT) AS j
                FROM r JOIN fg_moments m WHERE r.k < 10)))))
        ) SELECT k, j, round(lam, 6) AS lam, round(loss, 6) AS loss FROM r WHERE k > 0""")


@query(_loop("SELECT min(k)::INT AS stop_index FROM (SELECT k, loss / lag(loss) OVER (ORDER BY k) AS ratio FROM r) WHERE ratio >= 1 - 0.005", 50, 30))
def plateau_stop_index(spark, d):
    """First step whose loss ratio reaches one less the threshold, as a window over the stored trace."""
    f = rga(scalar_moments(spark, d), 50.0, 30)
    rows = [(0, float(f.loss0)), *[(r["k"], float(r["loss"])) for r in f.trace]]
    tr = spark.createDataFrame(rows, "k int, loss double")
    ratio = tr.withColumn("ratio", F.col("loss") / F.lag("loss").over(Window.orderBy("k")))
    return ratio.filter(F.col("ratio") >= 1 - 0.005).agg(F.min("k").alias("stop_index"))


@query(_loop("SELECT j::INT AS j, count(*)::BIGINT AS steps FROM r WHERE k BETWEEN 1 AND 12 GROUP BY j", 50, 12))
def srg_scalar_support(spark, d):
    f = rga(scalar_moments(spark, d), 50.0, 12)
    return spark.createDataFrame([(int(r["j"]),) for r in f.trace], "j int").groupBy("j").agg(F.count("*").alias("steps"))


# phase two on the columns 0, 8, 16, 35, 52: atoms are scaled by the inverse second moment, which is one here
_REFIT = (
    _LOOP.replace("FROM cv)", "FROM cv WHERE i IN (0, 8, 16, 35, 52))")
    .replace("ON a.vec_id = q.vec_id GROUP BY", "ON a.vec_id = q.vec_id AND a.i IN (0, 8, 16, 35, 52) AND q.i IN (0, 8, 16, 35, 52) GROUP BY")
    .replace("{L}", "50.0")
    .replace("{K}", "10")
)


@query(_REFIT + "SELECT k, [0, 8, 16, 35, 52][j + 1]::INT AS j, round(lam, 6) AS lam, round(loss, 6) AS loss FROM r WHERE k > 0")
def refit_scalar_path_10(spark, d):
    m = scalar_moments(spark, d).only([0, 8, 16, 35, 52])
    return _path_rows(spark, refit(m, dict.fromkeys(m.ids, 1), 50.0, 10, 0.0))


@query("""WITH m(k) AS (SELECT unnest(range(1, 6))), c(c) AS (SELECT unnest(range(4))), up AS (SELECT 'atom' AS kind, 8 * (500 + 10 + 2) AS b FROM m, c UNION ALL SELECT 'update', 8 * (500 + 10 + 3) FROM m, c UNION ALL SELECT 'flush', 8 * (500 + 10 + 3) FROM c)
SELECT kind, sum(b)::BIGINT AS bytes, count(*) AS messages FROM up GROUP BY ROLLUP (kind)""")
def ledger_rollup(spark, d):
    """Messages of five eager steps among four nodes on the label instance, by kind with the total."""
    b, s = label_blocks(spark, d)
    led = Ledger("labels", 4)
    rga(gram_moments(b, s), 3 * 10**0.5, 5, None, led)
    g = summary(led.frame(spark)).filter("phase IS NOT NULL")
    return g.select("kind", "bytes", "messages")


@query("""WITH c AS (SELECT DISTINCT l_partkey AS j FROM lineitem WHERE l_quantity >= 49), t AS (SELECT DISTINCT p_partkey AS j FROM part WHERE p_retailprice >= 1200)
SELECT (SELECT count(*) FROM (SELECT j FROM c EXCEPT SELECT j FROM t)) AS false_positives, (SELECT count(*) FROM (SELECT j FROM t EXCEPT SELECT j FROM c)) AS false_negatives""")
def fp_fn_counts(spark, d):
    """Chosen: parts of large lines; true: parts of a high price."""
    chosen = t(spark, d, "lineitem").filter("l_quantity >= 49").select(F.col("l_partkey").alias("j")).distinct()
    true = t(spark, d, "part").filter("p_retailprice >= 1200").select(F.col("p_partkey").alias("j")).distinct()
    return chosen.join(true, "j", "left_anti").agg(F.count("*").alias("false_positives")).join(true.join(chosen, "j", "left_anti").agg(F.count("*").alias("false_negatives")))


@query("""WITH z AS (SELECT l_returnflag || l_linestatus AS j, l_quantity - avg(l_quantity) OVER () AS y1, l_discount - avg(l_discount) OVER () AS y2, l_tax - avg(l_tax) OVER () AS y3 FROM lineitem)
SELECT j, round(sqrt(sum(y1) * sum(y1) + sum(y2) * sum(y2) + sum(y3) * sum(y3)), 3) AS score FROM z GROUP BY j""")
def multitask_scores(spark, d):
    """Common-support scores of one-hot columns over several responses: the length of the vector of products."""
    ys = ("l_quantity", "l_discount", "l_tax")
    li = t(spark, d, "lineitem").select(F.concat("l_returnflag", "l_linestatus").alias("j"), *ys)
    m = li.agg(*[F.avg(c).alias(f"m_{c}") for c in ys])
    g = li.join(F.broadcast(m)).groupBy("j").agg(*[F.sum(F.col(c) - F.col(f"m_{c}")).alias(c) for c in ys])
    return g.select("j", F.round(F.sqrt(sum((F.col(c) * F.col(c) for c in ys), F.lit(0.0))), 3).alias("score"))


@query("""WITH k AS (SELECT event_id AS i, '7|u|' || event_id AS k FROM events)
SELECT i AS id, ('0x' || substr(md5(k), 1, 8))::BIGINT AS raw, round((('0x' || substr(md5(k), 1, 8))::BIGINT + 0.5) / 4294967296.0, 6) AS u,
round(sqrt(-2 * ln((('0x' || substr(md5(k || 'a'), 1, 8))::BIGINT + 0.5) / 4294967296.0)) * cos(2 * pi() * ((('0x' || substr(md5(k || 'b'), 1, 8))::BIGINT + 0.5) / 4294967296.0)), 6) + 0.0 AS z FROM k""")
def draws_uniform_normal(spark, d):
    """Draws keyed by every event."""
    k = draws.key("7", "u", F.col("id"))
    return t(spark, d, "events").select(F.col("event_id").alias("id")).select("id", F.conv(F.substring(F.md5(k), 1, 8), 16, 10).cast("long").alias("raw"), F.round(draws.unif(k), 6).alias("u"), (F.round(draws.norm(k), 6) + 0.0).alias("z"))


_U = "(('0x' || substr(md5({k}), 1, 8))::BIGINT + 0.5) / 4294967296.0"
_N = "sqrt(-2 * ln(" + _U.replace("{k}", "{k} || 'a'") + ")) * cos(2 * pi() * " + _U.replace("{k}", "{k} || 'b'") + ")"


@query(f"""WITH k AS (SELECT c_custkey AS i, '7|p|' || c_custkey AS k FROM customer),
c AS (SELECT i, k, {_U.format(k="k")} AS u, {_N.format(k="k")} AS z, -2 * ln({_U.format(k="k || 'c0'")}) - 2 * ln({_U.format(k="k || 'c1'")}) + pow({_N.format(k="k || 'o'")}, 2) AS chi FROM k),
f AS (SELECT q, sum(exp(-2.5 + q * ln(2.5) - lgamma(q + 1))) OVER (ORDER BY q) AS upto FROM range(100) p(q))
SELECT i AS id, round(z / sqrt(chi / 5), 6) + 0.0 AS t5, (SELECT count(*) FROM f WHERE upto < u)::INT AS poisson FROM c""")
def draws_heavy_poisson(spark, d):
    """Heavy-tailed and counting draws keyed by every customer."""
    k = draws.key("7", "p", F.col("id"))
    return t(spark, d, "customer").select(F.col("c_custkey").alias("id")).select("id", (F.round(draws.t_draw(k), 6) + 0.0).alias("t5"), draws.poisson(k, F.lit(2.5)).alias("poisson"))


# multivariate, without SQL


def _coef(spark, coef):
    return spark.createDataFrame([(int(j), r, c, round(float(v), 6)) for j, b in coef.items() for (r, c), v in np.ndenumerate(b)], "j int, row int, col int, b double")


@query()
def threshold_tuning(spark, d):
    b, s = label_blocks(spark, d, 125)
    by = gram_moments(b, s, by_segment=True)
    train, held = grid.pooled({h: m for h, m in by.items() if h}), by[0]
    _, table = tune(train, held, SRGConfig(radius=50.0, cap=60, refit_iters=200))
    return spark.createDataFrame([(r["grid"], r["threshold"], r["stop_index"], round(r["rmse"], 8)) for r in table], "grid double, threshold double, stop_index int, rmse double")


@query("""WITH e AS (SELECT vec_id, label, list_transform(embedding, lambda x: x::DOUBLE) AS x FROM embeddings), c AS (SELECT vec_id, unnest(x) AS v, unnest(range(64)) AS i, (label = 3)::INT - (SELECT avg((label = 3)::INT) FROM e) AS y FROM e)
SELECT i::INT AS i, round(sum(v * y), 6) + 0.0 AS xy FROM c GROUP BY 1""")
def block_response_products(spark, d):
    w = label_wide(spark, d).select("f", F.col("y")[3].alias("y"))
    return w.select(F.posexplode("f").alias("i", "v"), "y").groupBy("i").agg((F.round(F.sum(F.col("v") * F.col("y")), 6) + 0.0).alias("xy"))


@query()
def oracle_by_phase_two(spark, d):
    """Unconstrained phase two on given blocks reaches their least squares."""
    b, s = label_blocks(spark, d)
    m = gram_moments(b, s, [0, 3])
    ls = lowrank.oracle_ls(m, [0, 3])
    f = refit(m, None, 50.0, 20000, 1e-16, total_rank=float("inf"))
    gap = max(float(np.abs(f.coef()[j] - ls[j]).max()) for j in ls)
    return spark.createDataFrame([(f.stop_index, gap < 1e-3)], "steps int, close boolean")


@query()
def rr_gcv_rank(spark, d):
    b, s = label_blocks(spark, d)
    m = gram_moments(b, s)
    coef, rank = lowrank.reduced_rank(m.g, m.c0, m.yy, m.n)
    return spark.createDataFrame([(rank, lowrank.rank_select(m.g, m.c0, 2.0), round(float(np.linalg.norm(coef)), 6))], "gcv_rank int, selected_rank int, norm_f double")


@query()
def splitting_path(spark, d):
    b, s = label_blocks(spark, d)
    m = gram_moments(b, s)
    top = max(np.linalg.norm(m.block(m.c0, j), 2) for j in m.ids) / m.n
    rows = [(float(lv), len(c), round(float(sum(np.linalg.svd(x, compute_uv=False).sum() for x in c.values())), 6)) for lv, c in lowrank.multiview_admm(m, top * 0.5 ** np.arange(8))]
    return spark.createDataFrame(rows, "level double, blocks int, nuclear double")


@query("WITH d AS (SELECT l_returnflag || l_linestatus AS j, (l_quantity > 25)::INT AS y FROM lineitem) SELECT j, round(sum(y - 0.5), 4) AS score FROM d GROUP BY 1 ORDER BY abs(sum(y - 0.5)) DESC, j LIMIT 1")
def glm_logit_first_pick(spark, d):
    """At fit zero the residual is the response less one half."""
    li = t(spark, d, "lineitem").select(F.concat("l_returnflag", "l_linestatus").alias("j"), (F.col("l_quantity") > 25).cast("int").alias("y"))
    g = li.groupBy("j").agg(F.sum(F.col("y") - LOGIT.mean_column(F.lit(0.0))).alias("s"))
    return g.orderBy(F.abs("s").desc(), "j").limit(1).select("j", F.round("s", 4).alias("score"))


@query("""WITH c AS (SELECT user_id, ts::DATE AS day, event_type, count(*) AS y FROM events GROUP BY 1, 2, 3) SELECT event_type AS j, sum(y - 1)::DOUBLE AS score FROM c GROUP BY 1 ORDER BY abs(sum(y - 1)) DESC, j LIMIT 1""")
def glm_poisson_first_pick(spark, d):
    """At fit zero the residual is the count less one."""
    c = t(spark, d, "events").groupBy("user_id", F.to_date("ts").alias("day"), "event_type").agg(F.count("*").alias("y"))
    g = c.groupBy(F.col("event_type").alias("j")).agg(F.sum(F.col("y") - POISSON.mean_column(F.lit(0.0))).alias("score"))
    return g.orderBy(F.abs("score").desc(), "j").limit(1)


@query("""WITH e AS (SELECT user_id, ts::DATE AS day, value / 100 AS g, (event_type = 'click')::INT AS y FROM events) SELECT round(avg(ln(1 + exp(-abs(g))) + greatest(g, 0) - y * g), 6) AS logit_loss, round(avg(exp(g) - y * g), 6) AS poisson_loss, round(avg(g * g / 2 - y * g), 6) AS gaussian_loss FROM e""")
def family_losses(spark, d):
    from featgreedy.functions.families import GAUSSIAN

    e = t(spark, d, "events").select((F.col("value") / 100).alias("g"), (F.col("event_type") == "click").cast("double").alias("y"))
    return e.agg(*[F.round(F.avg(f.loss_column(F.col("y"), F.col("g"))), 6).alias(f"{f.name}_loss") for f in (LOGIT, POISSON, GAUSSIAN)])


@query()
def assumption_diagnostics(spark, d):
    x = planted.local(planted.predictors(spark, d, 240))
    f = planted.plant_views(x, "diag", 10, 12, 1, 2)
    return spark.createDataFrame([(r["assumption"], round(r["value"], 6)) for r in measures.diagnose(f)], "assumption string, value double")


@query()
def two_factor_revelation(spark, d):
    """The identifiability example: the residual is small when factors reveal themselves, one when one hides the other."""
    rows = [(name, round(measures.revelation(planted.two_factor(fail)), 6)) for name, fail in (("revealed", False), ("hidden", True))]
    return spark.createDataFrame(rows, "variant string, residual double")


@query()
def noiseless_companion(spark, d):
    x = planted.local(planted.base(spark, d))
    f = planted.plant_views(x, "companion", 6, 8, 2, 1)
    one = rga(f.moments(), 1e3, 20)
    path = measures.noiseless_path(one, f.x, f.x @ f.beta, 8)
    return spark.createDataFrame([(r["k"], round(r["companion_loss"], 8), round(r["actual_loss"], 8)) for r in path], "k int, companion_loss double, actual_loss double")


@query()
def sparse_baselines(spark, d):
    """Test error of the sparse baselines on one planted scalar fixture."""
    x = planted.local(planted.predictors(spark, d, 128))
    f = planted.plant_scalar(x, "baseline")
    y, n = f.y[:, 0], len(f.y)
    lam = 2 * float(np.sqrt(np.log(x.shape[1]) / n))
    m = f.moments()
    keep = sparse.marginal_screen(f.x, y, 40)
    hs = np.zeros(x.shape[1])
    hs[keep] = lowrank.hessian_sketch(f.x[:, keep], y, 200)
    model = from_moments(m, SRGConfig(radius=500.0))
    two = np.zeros(x.shape[1])
    for j, b in model.coef.items():
        two[j] = b[0, 0]
    found = {
        "two_phase": two,
        "lasso_cv": sparse.lasso_cv(f.x, y, count=20)[0],
        "coordinate_50": sparse.coord_descent(f.x, y, lam, 0.5, rounds=100)[0],
        "sharing": sparse.sharing_admm(f.x, y, lam, rounds=60),
        "orthogonal_greedy": sparse.ortho_greedy(f.x, y, 30)[0],
        "sketch_ridge": lowrank.dual_sketch_ridge(f.x, y, 0.01, 32)[0],
        "screen_and_clean": hs,
        "sgd": lowrank.feature_sgd(f.x, y),
    }
    rows = [(k, round(measures.rmse(f.x_test @ b, f.y_test[:, 0]), 5), round(float(((b - f.beta[:, 0]) ** 2).sum()), 5), *measures.fp_fn(np.flatnonzero(np.abs(b) > 1e-6), list(f.truth))) for k, b in found.items()]
    return spark.createDataFrame(rows, "method string, test_rmse double, err_sq double, false_positives int, false_negatives int")


@query("SELECT 8::BIGINT AS rows, 4::BIGINT AS columns, 28.0::DOUBLE AS total")
def udtf_explode_block(spark, d):
    from featgreedy.functions import registered

    registered.register(spark)
    g = spark.sql("SELECT * FROM explode_block(transform(sequence(0, 7), x -> CAST(x AS DOUBLE)), 2, 10)")
    return g.agg(F.count("*").alias("rows"), F.count_distinct("l").alias("columns"), F.sum("v").alias("total"))


@query("""WITH RECURSIVE r(k, a, b, s) AS (SELECT 0, 3.0::DOUBLE, 0.0::DOUBLE, 0.0::DOUBLE UNION ALL SELECT k + 1, (3 * u + w) / l, 2 * w / l, sqrt((3 * u + w) * (3 * u + w) + 4 * w * w) / l
FROM (SELECT k, u, w, sqrt(u * u + w * w) AS l FROM (SELECT k, 3 * a / sqrt(a * a + b * b) AS u, (a + 2 * b) / sqrt(a * a + b * b) AS w FROM r WHERE k < 12)))
SELECT k, round(s, 8) AS s FROM r WHERE k > 0""")
def udtf_power_trace(spark, d):
    from featgreedy.functions import registered

    registered.register(spark)
    return spark.sql("SELECT k, round(s, 8) AS s FROM power_trace(array(3.0D, 0.0D, 1.0D, 2.0D), 2, 12)")


@query("SELECT label, round(avg(list_sum(list_transform(embedding, lambda x: x::DOUBLE))), 6) + 0.0 AS mean_total FROM embeddings GROUP BY label")
def udf_grouped_sum(spark, d):
    """Grouped aggregate Arrow function: element sums, then their mean total."""
    from featgreedy.functions.registered import sum_arrays

    e = t(spark, d, "embeddings").select("label", doubles(F.col("embedding")).alias("f"))
    g = e.groupBy("label").agg(sum_arrays("f").alias("s"))
    n = e.groupBy("label").agg(F.count("*").alias("n"))
    return g.join(n, "label").select("label", (F.round(F.aggregate("s", F.lit(0.0), lambda a, x: a + x) / F.col("n"), 6) + 0.0).alias("mean_total"))


@query()
def ml_estimator(spark, d):
    from featgreedy.ml.estimator import TwoPhaseRegression

    w = scalar_wide(spark, d).select("f", F.col("y")[0].alias("label"))
    m = TwoPhaseRegression(featuresCol="f", labelCol="label", radius=50.0, cap=20).fit(w)
    p = m.transform(w)
    return p.agg(F.round(F.sqrt(F.avg(F.pow(F.col("prediction") - F.col("label"), 2))), 6).alias("rmse"), F.count("*").alias("rows"))


@query()
def rank_k_atoms(spark, d):
    """Losses after ten steps with atoms of rank one, two and four, and the doubles each step ships."""
    from featgreedy.operators.greedy import rga_rank_k

    b, s = label_blocks(spark, d)
    m = gram_moments(b, s)
    rows = []
    for k in (1, 2, 4):
        m.reset()
        rows.append((k, round(rga_rank_k(m, 3 * 10**0.5, 10, k)[-1], 8), k * (m.n + m.d)))
    return spark.createDataFrame(rows, "atom_rank int, loss double, doubles_per_step int")


@query()
def lasso_two_solvers(spark, d):
    """The library's L1 regression and covariance updates reach one solution (levels scaled alike)."""
    from pyspark.ml.functions import array_to_vector
    from pyspark.ml.regression import LinearRegression

    w = scalar_wide(spark, d)
    m = gram_moments(layout.to_blocks(w, [1] * 64), layout.to_segments(w))
    lam = 0.1
    own = sparse.lasso_gram(m.g, m.c0[:, 0], m.n, lam)
    rows = w.select(array_to_vector("f").alias("features"), F.col("y")[0].alias("label"))
    lib = LinearRegression(elasticNetParam=1.0, regParam=lam, standardization=False, fitIntercept=False, maxIter=500, tol=1e-10).fit(rows)
    gap = float(np.abs(lib.coefficients.toArray() - own).max())
    return spark.createDataFrame([(int((own != 0).sum()), gap < 1e-3)], "selected int, same boolean")


@query()
def lookahead_passes(spark, d):
    """Data passes of per-block state with and without fetching the next best blocks' products."""
    b, s = label_blocks(spark, d)
    b.cache()
    rows = []
    for k in (1, 4):
        m = StateMoments(b, s, k)
        rows.append((k, ",".join(str(int(r["j"])) for r in rga(m, 3 * 10**0.5, 5).trace), m.passes))
    return spark.createDataFrame(rows, "lookahead int, path string, passes int")
