import numpy as np
import pytest
from pyspark.sql import functions as F

from featgreedy.functions import draws, text
from featgreedy.operators import glm, layout
from featgreedy.operators.greedy import rga
from featgreedy.operators.model import SRGConfig, fit, load_coef, predict, wired
from featgreedy.operators.moments import StateMoments, cross, gram_moments, pick_winner, score_blocks
from featgreedy.plans.cost import Shape, choose, explain
from featgreedy.sources import blockstore
from tests.reference import direct_rga


@pytest.fixture(scope="module")
def small(spark):
    rng = np.random.default_rng(0)
    x, b = rng.standard_normal((90, 12)), rng.standard_normal((3, 2))
    y = x[:, :3] @ b * 4 + rng.standard_normal((90, 2))
    wide = spark.createDataFrame([(i, r.tolist(), z.tolist()) for i, (r, z) in enumerate(zip(x, y, strict=True))], "t long, f array<double>, y array<double>")
    return x, y, wide


def frames(wide, seg=1000):
    return layout.to_blocks(wide, [3] * 4, seg).cache(), layout.to_segments(wide, seg).cache()


def test_layouts_round_trip(spark, small):
    x, _, wide = small
    b, s = frames(wide, 40)
    assert b.count() == 12 and s.count() == 3
    cells = layout.blocks_to_cells(b).toPandas()
    back = np.zeros_like(x)
    back[cells["t"], cells["j"] * 3 + cells["l"]] = cells["v"]
    assert np.array_equal(back, x)
    again = layout.cells_to_wide(layout.to_cells(wide, 3), 3).toPandas().sort_values("t")
    assert np.array_equal(np.stack(again["f"]), x)


def test_ragged_rows_raise(spark):
    wide = spark.createDataFrame([(0, [1.0, 2.0], [1.0]), (1, [1.0], [1.0])], "t long, f array<double>, y array<double>")
    with pytest.raises(Exception, match="wide"):
        layout.to_blocks(wide, [2]).collect()


def test_null_policies(spark):
    wide = spark.createDataFrame([(0, [1.0, None], [1.0]), (1, [3.0, float("nan")], [1.0]), (2, [5.0, 4.0], [1.0])], "t long, f array<double>, y array<double>")
    got = {p: [r["f"] for r in layout.clean(wide, p).orderBy("t").collect()] for p in ("drop_row", "zero", "mean")}
    assert got == {"drop_row": [[5.0, 4.0]], "zero": [[1.0, 0.0], [3.0, 0.0], [5.0, 4.0]], "mean": [[1.0, 4.0], [3.0, 4.0], [5.0, 4.0]]}
    with pytest.raises(Exception, match="null"):
        layout.clean(wide, "error").collect()
    with pytest.raises(ValueError):
        layout.clean(wide, "guess")


def test_moments_equal_numpy(spark, small):
    x, y, wide = small
    b, s = frames(wide, 40)
    m = gram_moments(b, s)
    assert np.allclose(m.g, x.T @ x) and np.allclose(m.c0, x.T @ y) and m.n == 90 and np.allclose(m.sums, x.sum(0))
    part = gram_moments(b, s, [1, 3])
    assert np.allclose(part.c0, np.vstack([x[:, 3:6], x[:, 9:]]).reshape(2, 90, 3).transpose(0, 2, 1).reshape(6, 90) @ y) or part.ids == [1, 3]
    c = cross(b, s.select("h", F.col("d").alias("k"), F.col("y").alias("a")))
    w = pick_winner(score_blocks(c))
    assert w["j"] == 0 and w["s1"] == pytest.approx(np.linalg.svd(x[:, :3].T @ y, compute_uv=False)[0])


def test_all_modes_take_the_same_path(spark, small):
    x, y, wide = small
    b, s = frames(wide)
    ref = [(r[0], round(r[2], 9)) for r in direct_rga([x[:, i : i + 3] for i in range(0, 12, 3)], y, 30.0, 4)]
    gram = [(t["j"], round(t["loss"], 9)) for t in rga(gram_moments(b, s), 30.0, 4).trace]
    state = StateMoments(b, s)
    assert gram == ref == [(t["j"], round(t["loss"], 9)) for t in rga(state, 30.0, 4).trace]
    assert state.passes == 1 + len({j for j, _ in ref})
    ahead = StateMoments(b, s, lookahead=4)
    assert ref == [(t["j"], round(t["loss"], 9)) for t in rga(ahead, 30.0, 4).trace] and ahead.passes == 2
    for lazy in (False, True):
        assert ref == [(j, round(loss, 9)) for j, _, loss in wired(b, s, 30.0, 4, 2, lazy)[0]]


def test_partitions_and_segments_do_not_matter(spark, small):
    _, _, wide = small
    b, s = frames(wide)
    b2, s2 = layout.to_blocks(wide.repartition(7), [3] * 4, 25), layout.to_segments(wide, 25)
    config = SRGConfig(radius=50.0, threshold=0.02, cap=30)
    one, two = fit(b, s, config), fit(b2, s2, config)
    assert one.support == two.support
    assert all(np.allclose(one.coef[j], two.coef[j]) for j in one.coef)


def test_state_mode_fit_predict_save(spark, small, tmp_path):
    x, y, wide = small
    b, s = frames(wide, 45)
    m = fit(b, s, SRGConfig(radius=50.0, threshold=0.1, cap=3, mode="state"))
    assert 0 in m.support
    p = {r["h"]: np.array(r["yhat"]).reshape(-1, 2) for r in predict(b, m.coef, 2).collect()}
    assert np.allclose(np.vstack([p[0], p[1]]), sum(x[:, 3 * j : 3 * j + 3] @ c for j, c in m.coef.items()))
    m.save(spark, str(tmp_path / "m"))
    coef, _ = load_coef(spark, str(tmp_path / "m"))
    assert all(np.allclose(coef[j], m.coef[j]) for j in m.coef)
    assert m.trace_frame(spark).count() == len(m.phase1.trace) + len(m.phase2.trace)


def test_pruned_block_store(spark, small, tmp_path):
    _, _, wide = small
    b, _ = frames(wide, 45)
    blockstore.write_blocks(b, str(tmp_path / "b"), 2)
    got = blockstore.read_blocks(spark, str(tmp_path / "b"), [1], [0], 2)
    assert [(r["j"], r["h"]) for r in got.select("j", "h").collect()] == [(1, 0)]
    plan = got._jdf.queryExecution().toString()
    assert "PartitionFilters: [" in plan and "j_bucket" in plan


def test_generalized_loop_on_segments_equals_arrays(spark):
    from featgreedy.functions.families import LOGIT

    rng = np.random.default_rng(1)
    x = rng.standard_normal((120, 4))
    y = (rng.random(120) < 1 / (1 + np.exp(-3 * x[:, 0]))).astype(float)
    wide = spark.createDataFrame([(i, r.tolist(), [float(z)]) for i, (r, z) in enumerate(zip(x, y, strict=True))], "t long, f array<double>, y array<double>")
    out = glm.glm_rga(layout.to_blocks(wide, [2, 2], 60), layout.to_segments(wide, 60), LOGIT, 10.0, 3, 0.0)
    ref = glm.glm_local(x, y, LOGIT, 10.0, 3, 0.0)
    assert [2 * r["j"] + r["l"] for r in out["trace"]] == [r["j"] for r in ref["trace"]]
    assert np.allclose([r["loss"] for r in out["trace"]], [r["loss"] for r in ref["trace"]], atol=1e-5)


def test_draws_agree_across_engines(spark):
    k = draws.key("s", "r", F.col("id"))
    got = spark.range(50).select("id", draws.unif(k).alias("u"), draws.norm(k).alias("z"), draws.t_draw(k).alias("t")).collect()
    for r in got:
        key = f"s|r|{r['id']}"
        assert r["u"] == draws.py_unif(key)
        assert r["z"] == pytest.approx(draws.py_norm(key)) and r["t"] == pytest.approx(draws.py_t(key))
    p = spark.range(4000).select(draws.poisson(draws.key("s", "p", F.col("id")), F.lit(2.0)).alias("x")).agg(F.avg("x"), F.variance("x")).first()
    assert abs(p[0] - 2) < 0.1 and abs(p[1] - 2) < 0.2


def test_latent_scores_match_the_decomposition(spark):
    rows = [(d, f"w{(d * 7 + i * i) % 11}xx", 1 + (d + i) % 3) for d in range(20) for i in range(6)]
    tok = spark.createDataFrame(rows, "doc long, token string, tf long").groupBy("doc", "token").agg(F.sum("tf").alias("tf"))
    w = text.tfidf(tok, text.idf(tok))
    left, scores, vals = text.lsi_fit(w, 3, extra=8, sweeps=6)
    pdf = w.toPandas().pivot_table(index="token", columns="doc", values="w", fill_value=0.0)
    u, s, vt = np.linalg.svd(pdf.to_numpy(), full_matrices=False)
    assert np.allclose(vals, s[:3], rtol=1e-6)
    got = np.stack(scores.toPandas().sort_values("doc")["x"])
    assert np.allclose(np.abs(got), np.abs((s[:3, None] * vt[:3]).T), atol=1e-4)
    proj = np.stack(text.lsi_project(w, left).toPandas().sort_values("doc")["x"])
    assert np.allclose(proj, got, atol=1e-6)


def test_latent_scores_from_documents_counted_in_place(spark):
    """texts are read once, counted without a shuffle; tokens beyond the head meet their weights by joins."""
    rows = [(d, " ".join(f"w{'abcdefghijk'[(d * 7 + i * i) % 11]}xx" for i in range(d % 5 + 6)) + " the and") for d in range(20)] + [(20, ""), (21, None), (22, "the 12")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    by_doc = text.counted(docs, 1)
    assert "Exchange" not in by_doc._jdf.queryExecution().executedPlan().toString()
    flat = {(r["doc"], w): int(n) for r in by_doc.collect() for w, n in zip(r["token"], r["tf"], strict=True)}
    assert flat == {(r["doc"], r["token"]): r["tf"] for r in text.tokenise(docs, 1).collect()}
    twice = docs.union(docs.limit(3))
    flat = {(r["doc"], w): int(n) for r in text.counted(twice, 1).collect() for w, n in zip(r["token"], r["tf"], strict=True)}
    assert flat == {(r["doc"], r["token"]): r["tf"] for r in text.tokenise(twice, 1).collect()}
    tok = text.tokenise(docs, 1)
    w = text.tfidf(tok, text.idf(tok)).toPandas().pivot_table(index="token", columns="doc", values="w", fill_value=0.0)
    u, s, vt = np.linalg.svd(w.to_numpy(), full_matrices=False)
    for head in (3, 100):
        _, scores, vals = text.lsi_fit(text.Weights(text.counted(docs, 1), head=head), 3, extra=8, sweeps=6)
        assert np.allclose(vals, s[:3], rtol=1e-6)
        got = scores.toPandas().sort_values("doc")
        assert list(got["doc"]) == list(w.columns) and np.allclose(np.abs(np.stack(got["x"])), np.abs((s[:3, None] * vt[:3]).T), atol=1e-4)


def test_cost_choices():
    assert choose(Shape(500, 10, 64, 8, 16, 20, 5)) == "gram"
    assert choose(Shape(10_000_000, 100, 1_250_000, 12_500, 2000, 100, 25, 64, 1000, 100)) == "state"
    assert "gram" in explain(Shape(500, 10, 64, 8, 16, 20, 5))


def test_estimator(spark):
    from pyspark.ml.feature import VectorAssembler
    from pyspark.ml import Pipeline

    from featgreedy.ml.estimator import TwoPhaseRegression

    rng = np.random.default_rng(2)
    x = rng.standard_normal((80, 3))
    df = spark.createDataFrame([(*map(float, r), float(2 * r[0] + 5)) for r in x], "a double, b double, c double, label double")
    m = Pipeline(stages=[VectorAssembler(inputCols=["a", "b", "c"], outputCol="features"), TwoPhaseRegression(threshold=0.05, radius=50.0)]).fit(df)
    got = m.transform(df).toPandas()
    assert np.allclose(got["prediction"], got["label"], atol=1e-3)


def test_entry_and_names(spark):
    import __spark_entry__ as e

    q, o = e.queries(), e.oracle_sql()
    assert set(o) <= set(q) and len(q) > 100
    assert e.entry(spark).count() > 0


def test_entry_works_without_the_subpackage(tmp_path):
    import os
    import shutil
    import subprocess
    import sys

    here = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    shutil.copytree(os.path.join(here, "featgreedy"), tmp_path / "featgreedy", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(os.path.join(here, "__spark_entry__.py"), tmp_path)
    code = "import __spark_entry__ as e; q = e.queries(); assert len(q) > 90 and not any(k.startswith('op') or k == 'pipeline' for k in q), list(q)"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True, timeout=120, env={k: v for k, v in os.environ.items() if k != "PYTHONPATH"})


def test_bucketed_tables_join_without_exchange(spark, tmp_path):
    spark.sql("DROP TABLE IF EXISTS fg_blocks")
    spark.sql("DROP TABLE IF EXISTS fg_coef")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        for name, rows in (("fg_blocks", 40), ("fg_coef", 10)):
            spark.range(rows).select((F.col("id") % 10).alias("j"), F.col("id").alias("v")).write.bucketBy(4, "j").sortBy("j").mode("overwrite").option("path", str(tmp_path / name)).saveAsTable(name)
        j = spark.table("fg_blocks").join(spark.table("fg_coef"), "j")
        assert j.count() == 40
        assert "Exchange hashpartitioning(j" not in j._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
        spark.sql("DROP TABLE IF EXISTS fg_blocks")
        spark.sql("DROP TABLE IF EXISTS fg_coef")


def test_scans_are_pruned_and_aggregates_partial(spark):
    from featgreedy.queries.relational import pooled_moments_by_year, scan_lineitem_pruned

    sf = "/root/testdata/sf0.001"
    plan = scan_lineitem_pruned(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(l_shipdate)" in plan and "l_extendedprice" not in plan
    plan = pooled_moments_by_year(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "partial_sum" in plan and plan.count("Exchange") == 1


def test_one_block_fit(spark):
    rng = np.random.default_rng(5)
    x = rng.standard_normal((200, 6))
    b = rng.standard_normal((6, 1)) @ rng.standard_normal((1, 5)) * 4
    y = x @ b + rng.standard_normal((200, 5))
    wide = spark.createDataFrame([(i, r.tolist(), z.tolist()) for i, (r, z) in enumerate(zip(x, y, strict=True))], "t long, f array<double>, y array<double>")
    m = fit(layout.to_blocks(wide, [6]), layout.to_segments(wide), SRGConfig(radius=1e3, threshold=0.05))
    assert m.support == [0] and m.summary()["ranks"][0] <= m.ranks[0] and m.summary()["bytes"] > 0
    assert np.abs(m.coef[0] - b).max() < 0.6


def test_node_maps_do_not_change_the_path(spark, small):
    from featgreedy.operators.ledger import Ledger

    _, _, wide = small
    m = gram_moments(*frames(wide))
    paths = []
    for of in (lambda j: j % 2, lambda j: j // 2, lambda j: (7 * j + 3) % 2):
        m.reset()
        paths.append([t["j"] for t in rga(m, 30.0, 6, None, Ledger("n", 2), "lazy", of).trace])
    assert paths[0] == paths[1] == paths[2]


def test_phase_two_takes_all_steps_in_the_whole_space_of_a_block(spark):
    """With one screened rank and no tolerance, blocks keep both columns and no step is left out."""
    from featgreedy.operators import grid
    from featgreedy.operators.moments import GramMoments
    from featgreedy.operators.refit import refit

    rng = np.random.default_rng(8)
    x, e = rng.standard_normal((60, 2)), rng.standard_normal((60, 3))
    y = x @ rng.standard_normal((2, 3)) + e
    half = lambda r: GramMoments([0], [2], x[r].T @ x[r], x[r].T @ y[r], (y[r] ** 2).sum(), len(y[r]), x[r].sum(0), y[r].sum(0))
    whole, by = half(slice(None)), {0: half(slice(0, 30)), 1: half(slice(30, 60))}
    one = refit(whole, {0: 1}, 20.0, 300, 0.0, total_rank=float("inf"))
    two = grid.grid_refit(by, {0: 1}, 20.0, 300, 0.0, total_rank=float("inf"))
    assert one.stop_index == two.stop_index == 300
    best = np.linalg.lstsq(x, y, rcond=None)[0]
    for f in (one, two):
        assert np.linalg.matrix_rank(f.coef()[0]) == 2 and np.allclose(f.coef()[0], best, atol=0.05)


def test_range_frame_rounds_seconds_as_the_sql_does(spark, tmp_path):
    """half seconds go to the even second."""
    import datetime as dt

    import duckdb

    from featgreedy.queries import catalogue

    t0 = dt.datetime(2024, 1, 1)
    at = [0, 86_400.4, 86_400.5, 86_400.6, 86_401.5, 172_800.9, 172_801.5, 172_802.5]
    spark.createDataFrame([(i, 1, t0 + dt.timedelta(seconds=s)) for i, s in enumerate(at)], "event_id long, user_id long, ts timestamp").write.parquet(str(tmp_path / "events.parquet"))
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT event_id, user_id, ts::TIMESTAMP AS ts FROM read_parquet('{tmp_path}/events.parquet/*.parquet')")
    got = sorted(tuple(r) for r in catalogue.QUERIES["window_range_frame"](spark, str(tmp_path)).collect())
    assert got == sorted(con.execute(catalogue.ORACLES["window_range_frame"]).fetchall())


@pytest.mark.parametrize("name", ["auto_threshold", "cost_choice", "draws_heavy_poisson", "draws_uniform_normal", "fp_fn_counts"])
def test_small_queries_work_on_given_tables(spark, name):
    """They read a table, and give what the SQL gives."""
    import duckdb

    from featgreedy.queries import catalogue

    d = "/root/testdata/sf0.01"
    con = duckdb.connect()
    for x in ("events", "orders", "customer", "lineitem", "part"):
        con.execute(f"CREATE VIEW {x} AS SELECT * FROM '{d}/{x}.parquet'")
    sql = catalogue.ORACLES[name]
    assert any(x in sql for x in ("events", "orders", "customer", "lineitem"))
    assert sorted(tuple(r) for r in catalogue.QUERIES[name](spark, d).collect()) == sorted(con.execute(sql).fetchall())


def test_top_order_takes_null_keys_last_as_the_sql_does(spark, tmp_path):
    """equal prices with a null key, null prices, NaN and signed zeros, customers twice and without orders."""
    import duckdb

    from featgreedy.queries import catalogue

    prices = [(10, 1, 5.0), (11, 1, 5.0), (12, 2, None), (13, 2, 1.0), (14, 3, float("nan")), (15, 3, 9.0), (17, 4, 0.0), (16, 4, -0.0), (20, 5, None), (19, 5, None), (21, None, 4.0), (None, 6, 7.0), (30, 6, 7.0), (None, 7, 1.0)]
    spark.createDataFrame([(k,) for k in (1, 1, 2, 3, 4, 5, 6, 7, 8, None)], "c_custkey long").write.parquet(str(tmp_path / "customer.parquet"))
    spark.createDataFrame(prices, "o_orderkey long, o_custkey long, o_totalprice double").write.parquet(str(tmp_path / "orders.parquet"))
    con = duckdb.connect()
    for x in ("customer", "orders"):
        con.execute(f"CREATE VIEW {x} AS SELECT * FROM read_parquet('{tmp_path}/{x}.parquet/*.parquet')")
    got = sorted((tuple(r) for r in catalogue.QUERIES["join_lateral_top"](spark, str(tmp_path)).collect()), key=str)
    assert (6, 30) in got and got == sorted(con.execute(catalogue.ORACLES["join_lateral_top"]).fetchall(), key=str)


def test_large_trajectory_stores_no_rows(spark, tmp_path, monkeypatch):
    """rows drawn where they are multiplied give the stored blocks' moments, over quarters cut into several runs and chunks."""
    from featgreedy.functions.draws import normals, py_norm
    from featgreedy.queries import workloads as w
    from featgreedy.sources import planted

    got = normals("planted|x", range(8, 1002), 11)
    assert np.allclose(got[[0, 1, 2, 92, 993]][:, [0, 9, 10]], [[py_norm(f"planted|x|{t}|{c}") for c in (0, 9, 10)] for t in (8, 9, 10, 100, 1001)], rtol=1e-14, atol=0)
    shape = (203, 3, 6, 4)
    b, s, truth = w.large_frames(spark, None, *shape)
    want = gram_moments(b, s)
    monkeypatch.setattr(planted, "RUN_BYTES", 8 * 18 * 9)
    monkeypatch.setattr(planted, "CHUNK_BYTES", 8 * 18 * 4)
    got = planted.large_moments(spark, *shape, truth)
    assert got.n == want.n == 203 and got.ids == want.ids and np.isclose(got.yy, want.yy)
    assert np.allclose(got.g, want.g) and np.allclose(got.c0, want.c0) and np.allclose(got.sums, want.sums) and np.allclose(got.y_sum, want.y_sum)
    monkeypatch.setattr(w, "large_shape", lambda spark, d: shape)
    monkeypatch.setattr("featgreedy.session.shared_dir", lambda spark: str(tmp_path))
    assert w.workload_large_trajectory(spark, None).count() > 1
    assert not list(tmp_path.rglob("*.parquet"))
