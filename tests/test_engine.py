"""The predictive methods against numpy, planted truth and each other."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from pagecast.baselines import learners
from pagecast.operators import answers, factor, ingest, pagematrix, segments
from pagecast.plans import metrics, sqlfront, theory
from pagecast.plans.config import ModelConfig, half_window, page_height, settle
from pagecast.plans.engine import Engine
from pagecast.sources import synth
from pagecast.streaming.models import IncrementalModel


@pytest.fixture(scope="module")
def noisy(spark):
    return synth.plant(synth.grid(spark, 4, 240), 240, 1.0, 0.2).persist()


def matrix(df, w, steps, column="value"):
    rows = df.where(F.col("step") < steps - steps % w).select("series_id", "step", column).toPandas()
    wide = rows.pivot(index="series_id", columns="step", values=column).fillna(0.0).sort_index().to_numpy()
    return np.concatenate([row.reshape(-1, w).T for row in wide], axis=1)


def test_imputation_equals_the_svd(spark, noisy):
    w, r = 8, 3
    z = matrix(noisy, w, 240)
    u, s, v = np.linalg.svd(z, full_matrices=False)
    want = u[:, :r] * s[:r] @ v[:r]
    pages = pagematrix.build(noisy, w)
    for backend in ("gram", "local"):
        models = factor.train(pages, 1 << 20, ModelConfig(w=w, r_impute=r, r_forecast=r, backend=backend))
        got = matrix(answers.impute(pages, models, 1 << 20, w), w, 240, "mean")
        assert np.abs(got - want).max() < 1e-8


def test_weights_equal_principal_component_regression(spark, noisy):
    w, r = 8, 4
    z = matrix(noisy, w, 240)
    u, s, v = np.linalg.svd(z[:-1], full_matrices=False)
    low = u[:, :r] * s[:r] @ v[:r]
    want = np.linalg.lstsq(low.T, z[-1], rcond=1e-10)[0]
    models = factor.train(pagematrix.build(noisy, w), 1 << 20, ModelConfig(w=w, r_impute=r, r_forecast=r))
    got = models.where("moment = 1").first()["weights"]
    assert np.abs(np.array(got) - want).max() < 1e-8


def test_noiseless_recurrence_is_recovered_and_forecast(spark):
    clean = synth.plant(synth.grid(spark, 2, 240), 240).persist()
    engine = Engine(spark)
    engine.create_model("m", clean.where("step < 216"), ModelConfig(w=18, r_impute=9, r_forecast=9))
    error = metrics.nrmse(engine.predict("m", 0, 215), clean).first()["nrmse"]
    ahead = metrics.nrmse(engine.predict("m", 216, 239), clean.where("step >= 216")).first()["nrmse"]
    assert error < 1e-6 and ahead < 0.2


def test_windows_cover_each_half_twice(spark, noisy):
    pages = pagematrix.build(noisy, 6)
    models = factor.train(pages, 10, ModelConfig(w=6, r_impute=6, r_forecast=5))
    assert sorted(r[0] for r in models.select("model_idx").distinct().collect()) == [0, 1, 2]
    got = answers.impute(pages, models, 10, 6).join(noisy, ["cohort", "series_id", "step"])
    assert got.agg(F.max(F.abs(got["mean"] - got["value"]))).first()[0] < 1e-8


def test_stored_factors_answer_like_the_pages(spark, noisy):
    engine = Engine(spark)
    engine.create_model("m", noisy, ModelConfig(w=6, capacity=480), keep_right=True)
    asks = noisy.select("cohort", "series_id", "step").where("step % 17 = 3")
    both = engine.point("m", asks).alias("p").join(engine.predict("m", 0, 239).alias("q"), ["cohort", "series_id", "step"])
    row = both.agg(F.count("*"), F.max(F.abs(F.col("p.mean") - F.col("q.mean")))).first()
    assert row[0] == asks.count() and row[1] < 1e-8


def test_intervals_widen_and_cover(spark, noisy):
    engine = Engine(spark)
    engine.create_model("m", noisy, ModelConfig(w=8))
    width = lambda c, m: metrics.coverage(engine.predict("m", 0, 239, confidence=c, method=m), noisy).first()
    a, b, c = width(80, "gaussian"), width(95, "gaussian"), width(95, "chebyshev")
    assert a["width"] < b["width"] < c["width"] and a["coverage"] <= b["coverage"] <= c["coverage"]
    with pytest.raises(ValueError):
        engine.predict("m", 0, 1, confidence=100)


def test_too_few_observations_give_the_average(spark):
    few = spark.createDataFrame([("all", "a", 0, 1.0), ("all", "a", 1, 3.0)], "cohort string, series_id string, step long, value double")
    engine = Engine(spark)
    engine.create_model("m", few)
    assert [r["mean"] for r in engine.predict("m", 1, 3).collect()] == [2.0, 2.0, 2.0]


def test_edge_inputs(spark):
    schema = "cohort string, series_id string, step long, value double"
    rows = [("all", "empty", s, None) for s in range(50)] + [("all", "flat", s, 5.0) for s in range(120)]
    engine = Engine(spark)
    engine.create_model("m", spark.createDataFrame(rows, schema), ModelConfig(w=6, least=10))
    got = {(r["series_id"], r["step"]): r for r in engine.predict("m", 0, 121).collect()}
    assert abs(got["flat", 7]["mean"] - 5.0) < 1e-9 and got["flat", 7]["sd"] < 1e-4
    assert abs(got["flat", 121]["mean"] - 5.0) < 1e-9 and got["empty", 7]["mean"] == 0.0
    none = spark.createDataFrame([], schema)
    engine.create_model("n", none)
    assert engine.predict("n", 0, 3).count() == 0
    bad = spark.createDataFrame([("a", "2024-01-01 00:10:00", float("nan")), ("a", "2024-01-01 00:20:00", 4.0), ("a", None, 2.0)], "k string, t string, v double")
    assert [r["value"] for r in ingest.regularize(bad, "t", "v", ["k"], "1 hour", origin="2024-01-01").collect()] == [4.0]


def test_statements(spark):
    days = spark.range(300).select(F.expr("timestamp_ntz'2020-01-01' + make_dt_interval(cast(id as int))").alias("day"), F.cos(F.col("id") / 3).alias("c1"), F.sin(F.col("id") / 3).alias("c2"))
    days.createOrReplaceTempView("stock")
    engine = Engine(spark)
    made = sqlfront.run(engine, "create prediction model m on stock (c1, c2) time day every '1 day' origin '2020-01-01' with (w = 10)")
    assert made.first()["n_series"] == 2
    ahead = sqlfront.run(engine, "PREDICT c1 FROM m WHERE step = 301 CONFIDENCE 90 INTERVAL chebyshev").collect()
    assert len(ahead) == 1 and ahead[0]["task"] == "forecast" and abs(ahead[0]["mean"] - np.cos(301 / 3)) < 1e-3
    assert sqlfront.run(engine, "PREDICT * FROM m WHERE step BETWEEN 3 AND 5 INTERVAL none").columns == ["cohort", "series_id", "step", "task", "mean"]
    assert sqlfront.run(engine, "SELECT count(*) AS n FROM stock").first()["n"] == 300
    for wrong in ("PREDICT c1 FROM m", "PREDICT c1 FROM other WHERE step = 1", "create prediction model x on stock (c1) time day every '1 day' with (no = 1)"):
        with pytest.raises(ValueError):
            sqlfront.run(engine, wrong)


def _same_models(got, want, tolerance=1e-8):
    pick = lambda m: {(r["cohort"], r["model_idx"], r["moment"]): r for r in m.select("cohort", "model_idx", "moment", "weights", "pages", "seen", "s").collect()}
    a, b = pick(got), pick(want)
    assert a.keys() == b.keys()
    for k in a:
        assert (a[k]["pages"], a[k]["seen"]) == (b[k]["pages"], b[k]["seen"])
        assert np.abs(np.array(a[k]["weights"]) - b[k]["weights"]).max() < tolerance, k


def _whole(spark, long, config, n):
    return factor.train(pagematrix.build(long, config.w), half_window(config, n) // config.w, config)


@pytest.mark.parametrize("how", ["in order", "one series lags", "late rows", "other order", "corrections"])
def test_incremental_equals_batch(spark, noisy, how):
    config = ModelConfig(w=6, capacity=480, r_impute=3, r_forecast=3, fill="inverse_rate")
    rows = noisy.where("step % 11 <> 5 or series_id <> 's0001'").select("cohort", "series_id", "step", "value")
    arrives = F.floor(F.col("step") / 53)
    if how == "one series lags":
        arrives = arrives + F.when(F.col("series_id") == "s0002", 1).otherwise(0)
    elif how == "late rows":
        arrives = F.when(F.col("step") % 17 == 3, 4).otherwise(arrives)
    elif how == "other order":
        arrives = 4 - arrives
    model = IncrementalModel(spark, 4, config)
    if how == "corrections":
        model.append(rows.where("step < 100").withColumn("value", F.col("value") + (F.col("step") % 3)))
    for k in range(6):
        model.append(rows.where(arrives == k))
    _same_models(model.factors, _whole(spark, rows, config, 4))
    _same_models(model.solve(), _whole(spark, rows, config, 4))
    assert model.count == rows.count() and model.log[0][2] == "retrain"


def test_replayed_batches_change_nothing(spark, noisy):
    config = ModelConfig(w=6, capacity=480, r_impute=3, r_forecast=3)
    model = IncrementalModel(spark, 4, config)
    part = lambda k: noisy.where(F.floor(F.col("step") / 80) == k)
    model.append(part(0), 7)
    model.append(part(1), 8)
    model.append(part(1), 8)
    again = IncrementalModel(spark, 4, config, model.root)
    again.append(part(0), 7)
    again.append(part(2), 9)
    _same_models(again.factors, _whole(spark, noisy, config, 4))
    assert [x[0] for x in again.log] == [7, 8, 9]


def test_updates_between_full_solves(spark, noisy):
    """Folded-in columns follow the full solve closely; the schedule's full
    solves are exact; folding alone keeps the vectors."""
    config = ModelConfig(w=6, capacity=4000, r_impute=5, r_forecast=5, growth=1.0)
    cuts = [0, 120, 150, 180, 240]
    for update in ("columns", "fold"):
        model = IncrementalModel(spark, 4, config, update=update)
        kinds, gaps = [], []
        for lo, hi in zip(cuts, cuts[1:]):
            model.append(noisy.where((F.col("step") >= lo) & (F.col("step") < hi)))
            want = _whole(spark, noisy.where(F.col("step") < hi), config, 4).where("moment = 1").first()
            got = model.factors.where("moment = 1").first()
            kinds.append(model.log[-1][2])
            gaps.append(np.abs(np.array(got["weights"]) - want["weights"]).max())
        assert kinds == ["retrain", "update", "update", "retrain"]
        assert gaps[0] < 1e-8 and gaps[3] < 1e-8
        assert max(gaps[1:3]) < (0.05 if update == "columns" else 0.2)
        if update == "columns":  # full rank: nothing is lost
            assert max(gaps[1:3]) < 1e-8


def test_column_update_and_fold_in():
    rng = np.random.default_rng(2)
    z = rng.normal(size=(10, 3)) @ rng.normal(size=(3, 40))
    u, s, vt = np.linalg.svd(z[:, :30], full_matrices=False)
    a, b, c = factor.update_columns(u[:, :3], s[:3], vt[:3].T, z[:, 30:], 3)
    assert np.abs(a * b @ c.T - z).max() < 1e-8
    f = factor.fold_in(u[:, :3], s[:3], vt[:3].T, z[:, 30:])
    assert np.abs(f[0] * f[1] @ f[2].T - z).max() < 1e-8


def test_power_and_row_matrix_agree(spark, noisy):
    pages = pagematrix.build(noisy, 8).persist()
    s = np.linalg.svd(matrix(noisy, 8, 240), compute_uv=False)
    assert np.allclose(factor.power_iterate(pages, 2, 200)[1], s[:2], rtol=1e-5)
    assert np.allclose(factor.svd_mllib(pages, 2), s[:2], rtol=1e-8)


def test_rank_bounds(spark):
    ranks = [theory.numeric_rank(pagematrix.build(synth.plant(synth.grid(spark, n, 240), 240), 20)) for n in (1, 6)]
    assert max(ranks) <= theory.stacked_bound(4, 2) + 1
    assert theory.recurrence_bound(3, 1) == 18 and theory.second_moment_bound(2, 3, 1, 2) == 38


def test_geometry():
    assert segments.retrain_points(100, 500, 0.5) == [100, 150, 225, 337]
    c = ModelConfig(capacity=1000)
    assert segments.action(50, 0, c) == ("average", 0)
    assert segments.action(120, 90, c) == ("retrain", 0)
    assert segments.action(140, 120, c) == ("update", 0)
    assert segments.action(2100, 1900, c)[1] == 3
    assert page_height(5, 2405, 2_500_000) == 34 and settle(ModelConfig(), 1, 50).w == 2
    with pytest.raises(ValueError):
        ModelConfig(w=1)


def test_hankel_layout_helps_short_series(spark, noisy):
    h = pagematrix.hankel(noisy, 8)
    assert h.count() == 4 * (240 - 7)
    models = factor.train(h, 1 << 20, ModelConfig(w=8))
    assert models.count() == 2


def test_factorisation_objective_falls():
    rng = np.random.default_rng(1)
    y = rng.normal(size=(4, 3)) @ rng.normal(size=(3, 60))
    y[rng.random(y.shape) < 0.2] = np.nan
    trace = []
    learners.trmf_fit(y, rank=3, rounds=6, trace=trace)
    assert all(b <= a * (1 + 1e-9) for a, b in zip(trace, trace[1:]))


@pytest.mark.parametrize("probabilistic", [False, True])
def test_network_gradient(probabilistic):
    net = learners.Recurrent(4, probabilistic)
    rng = np.random.default_rng(0)
    x, y = rng.normal(size=(5, 6)), rng.normal(size=5)
    out, tape = net.forward(x)
    grads = net.gradient(net.loss(out, y)[1], tape)
    for name, p in net.p.items():
        flat, g = p.reshape(-1), grads[name].reshape(-1)
        for i in (0, len(flat) - 1):
            flat[i] += 1e-6
            up = net.loss(net.forward(x)[0], y)[0]
            flat[i] -= 2e-6
            down = net.loss(net.forward(x)[0], y)[0]
            flat[i] += 1e-6
            assert abs((up - down) / 2e-6 - g[i]) < 1e-5


def test_more_series_lower_the_error(spark):
    from pagecast.plans.workloads import series_count

    rows = {r["n_series"]: r["nrmse"] for r in series_count(spark, "", (1, 10), 400).collect()}
    assert rows[10] < rows[1] == 1.0


def test_two_methods_share_one(spark):
    r = spark.createDataFrame([("e", "a", 1.0), ("e", "b", 3.0), ("f", "a", 2.0), ("f", "b", 2.0)], "experiment string, method string, nrmse double")
    got = {x["method"]: x["wbc"] for x in metrics.wbc(r).collect()}
    assert abs(got["a"] + got["b"] - 1) < 1e-12 and got["a"] == pytest.approx(0.625)
