"""Where answers come from: files read, cohorts of their own length, other engines."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from pagecast.baselines import learners
from pagecast.operators import segments
from pagecast.plans import metrics, sqlfront
from pagecast.plans.config import ModelConfig
from pagecast.plans.engine import Engine
from pagecast.sources import synth


def plan_of(df) -> str:
    return df._jdf.queryExecution().toString()


@pytest.fixture(scope="module")
def hourly(spark):
    return synth.plant(synth.grid(spark, 3, 900), 900, 0.8, 0.1).select("cohort", "series_id", "step", "value").persist()


def test_questions_read_the_folders_they_need(spark, hourly):
    engine = Engine(spark)
    model = engine.create_model("m", hourly, ModelConfig(w=10, capacity=1200))
    model.bucket_halves = 1
    engine.create_model("m", hourly, ModelConfig(w=10, capacity=1200))
    past = plan_of(engine.predict("m", 100, 100, ["s0001"], uncertainty=False))
    assert "PartitionFilters" in past and "bucket" in past
    ahead = plan_of(engine.predict("m", 905, 905, ["s0001"], uncertainty=False))
    assert "/pages" not in ahead and "m2" not in ahead


def test_a_series_before_its_first_row_and_a_late_start(spark):
    rows = [("all", "a", s, float(s % 4)) for s in range(500, 740)] + [("all", "b", s, 1.0) for s in range(620, 740)]
    long = spark.createDataFrame(rows, "cohort string, series_id string, step long, value double")
    engine = Engine(spark)
    model = engine.create_model("m", long, ModelConfig(w=8, least=10))
    assert model.steps == 240 and model.first == (500, 500)
    got = {(r["series_id"], r["step"]): r for r in engine.predict("m", 490, 745).collect()}
    assert len(got) == 2 * 246 and min(s for _, s in got) == 500
    assert abs(got["a", 503]["mean"] - 3.0) < 0.2 and got["a", 741]["task"] == "forecast"


def test_cohorts_end_where_their_rows_end(spark, hourly):
    long = segments.cohorts(hourly.where("series_id < 's0002'"), "each").where("cohort = 's0001' or step < 500")
    engine = Engine(spark)
    engine.create_model("m", long, ModelConfig(w=10, r_impute=6, r_forecast=6), keep_right=True)
    asked = engine.predict("m", 480, 520)
    kinds = {(r["cohort"], r["step"]): r["task"] for r in asked.collect()}
    assert kinds["s0000", 505] == "forecast" and kinds["s0001", 505] == "impute"
    both = engine.point("m", asked.select("cohort", "series_id", "step")).join(asked.withColumnsRenamed({"mean": "m", "sd": "s", "lower": "l", "upper": "u"}), ["cohort", "series_id", "step"])
    row = both.agg(F.count("*"), F.max(F.abs(F.col("m") - F.col("mean"))), F.max(F.abs(F.col("s") - F.col("sd")))).first()
    assert row[0] == 82 and row[1] < 1e-8 and row[2] < 1e-6


def test_a_cohort_that_is_too_small_answers_with_its_average(spark, hourly):
    few = spark.createDataFrame([("few", "x", 3, 2.0), ("few", "x", 5, 4.0)], "cohort string, series_id string, step long, value double")
    engine = Engine(spark)
    engine.create_model("m", hourly.unionByName(few), ModelConfig(w=10))
    got = [r for r in engine.predict("m", 4, 6).collect() if r["cohort"] == "few"]
    assert [(r["task"], r["mean"]) for r in got] == [("average", 3.0)] * 3


def test_another_engine_over_the_same_folder(spark, hourly, tmp_path):
    root = f"file://{tmp_path}/models"
    one = Engine(spark, root)
    one.create_model("m", hourly, ModelConfig(w=10))
    a = one.predict("m", 880, 910).orderBy("series_id", "step").collect()
    assert a == Engine(spark, root).predict("m", 880, 910).orderBy("series_id", "step").collect()
    with pytest.raises(ValueError):
        Engine(spark, root).predict("other", 0, 1)


def test_statements_by_time(spark):
    hours = spark.range(720).select(F.expr("timestamp_ntz'2024-03-01' + make_dt_interval(0, cast(id as int))").alias("ts"), (F.col("id") * 5 + 100).alias("tick"), (F.cos(F.col("id") / 4) + 3).alias("v"))
    hours.createOrReplaceTempView("hours")
    engine = Engine(spark)
    sqlfront.run(engine, "CREATE PREDICTION MODEL m ON hours (v) TIME ts EVERY '1 hour' WITH (fill = inverse_rate)")
    model = engine.model("m")
    assert model.steps == 720 and model.w >= 8  # decades before the first row are not history
    got = sqlfront.run(engine, "PREDICT v FROM m WHERE ts BETWEEN TIMESTAMP '2024-03-02 05:00:00' AND '2024-03-02 07:59:00'").orderBy("ts").collect()
    assert [str(r["ts"]) for r in got] == [f"2024-03-02 0{k}:00:00" for k in (5, 6, 7)]
    assert all(abs(r["mean"] - np.cos((29 + k) / 4) - 3) < 0.05 for k, r in enumerate(got))
    sqlfront.run(engine, "CREATE PREDICTION MODEL n ON hours (v) TIME tick EVERY '5'")
    got = sqlfront.run(engine, "PREDICT v FROM n WHERE tick = 145 INTERVAL none").collect()
    assert len(got) == 1 and got[0]["tick"] == 145.0 and abs(got[0]["mean"] - np.cos(9 / 4) - 3) < 0.05
    for wrong in ("PREDICT v FROM m WHERE day = 3", "PREDICT v FROM m WHERE ts = 'never'"):
        with pytest.raises(Exception):
            sqlfront.run(engine, wrong).collect()


def test_scaled_models_agree_with_plain_ones_on_clean_series(spark):
    clean = synth.plant(synth.grid(spark, 2, 240), 240).withColumn("value", F.col("value") * 40 + 500)
    for config in (ModelConfig(w=12, r_impute=11, r_forecast=9, standardize=True), ModelConfig(w=12, r_impute=11, r_forecast=9, fill="inverse_rate")):
        engine = Engine(spark)
        engine.create_model("m", clean, config)
        truth = clean.withColumn("latent", F.col("value"))
        assert metrics.nrmse(engine.predict("m", 0, 239), truth).first()["nrmse"] < 1e-6


def test_rivals_learn_from_every_window():
    y = np.vstack([np.sin(np.arange(300) / 5), np.cos(np.arange(300) / 7)])
    x, target, *_ = learners._samples(y, 24)
    assert len(x) == len(target) == 2 * (300 - 24)
    mean, low, high = learners.probabilistic_fitted(y, epochs=2)(5, 95)
    assert mean.shape == (2, 5) and (low <= high).all()
    assert np.allclose(learners.deviation_of(np.array([-1.959963984540054]), np.array([1.959963984540054])), 1.0)
    for fit in learners.FITTED.values():
        out = fit(y)(3)
        assert (out[0] if isinstance(out, tuple) else out).shape == (2, 3)
