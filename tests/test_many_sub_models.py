"""Small capacities make thousands of sub-models; none of them may cost a group of its own."""

import os

import numpy as np
import pytest
from pyspark.sql import functions as F

from pagecast.operators import factor, segments
from pagecast.plans import workloads
from pagecast.plans.config import ModelConfig
from pagecast.streaming import models

SF = "/root/testdata/sf0.001"


@pytest.fixture
def tiny_batches(spark):
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, "3")
    yield
    spark.conf.set(name, before)


def test_sums_and_factors_come_without_a_group_for_each(spark, tiny_batches):
    """Keys go on from one batch to the next; parts are added up, others taken away."""
    w, half_pages, halves = 3, 4, 30
    z = np.random.default_rng(5).normal(size=(halves * half_pages, w))
    gone = set(range(0, len(z), 7))
    rows = [("all", k // half_pages, "s", k, [float(x) for x in z[k]], w, sign) for k in range(len(z)) for sign in ((1, -1) if k in gone else (1,))]
    pages = spark.createDataFrame(rows, "cohort string, half bigint, series_id string, page bigint, vals array<double>, seen bigint, sign int")
    pages = pages.withColumn("salt", F.lit(0)).repartition(5, "page").sortWithinPartitions("half", "sign")
    gram = factor.merge_gram(factor.gram_rows(pages, half_pages))
    left = lambda a, b: z[[k for k in range(a * half_pages, b * half_pages) if k not in gone]]
    found = {(r["half"], r["moment"]): r for r in gram.collect()}
    assert len(found) == 2 * halves
    for (half, moment), r in found.items():
        x = left(half, half + 1) ** moment
        assert r["pages"] == len(x) and r["seen"] == w * len(x)
        assert np.abs(np.frombuffer(r["g"]).reshape(w, w) - x.T @ x).max() < 1e-12
    solved = factor.solve(gram, ModelConfig(w=w, r_impute=2, r_forecast=2))
    got = {(r["model_idx"], r["moment"]): r["s"] for r in solved.collect()}
    assert sorted(got) == [(j, m) for j in range(halves - 1) for m in (1, 2)]
    for (j, moment), s in got.items():
        assert np.abs(np.array(s) - np.linalg.svd(left(j, j + 2) ** moment, compute_uv=False)[:2]).max() < 1e-7
    plan = solved._jdf.queryExecution().toString() + gram._jdf.queryExecution().toString()
    assert "MapInArrow" in plan and "FlatMapGroups" not in plan


@pytest.mark.skipif(not os.path.isdir(SF), reason="no test tables")
def test_growths_of_one_schedule_share_a_model(spark, monkeypatch):
    """Of these growths 0.2 and 0.21 ask for the same at the bulk load and both batches, 1 does not."""
    trained = []

    class Counted:
        def __init__(self, spark, n_series, config, update):
            self.config, self.count, self.log = config, 0, []
            trained.append(self)

        def append(self, batch):
            count = self.count + batch.count()
            self.log.append(segments.action(count, self.count, self.config)[0])
            self.count = count

        def weights(self):
            rows = [("all", m, [0.0] * (self.config.w - 2) + [1.0]) for m in (1, 2)]
            return spark.createDataFrame(rows, "cohort string, moment int, beta array<double>")

    monkeypatch.setattr(models, "IncrementalModel", Counted)
    found = {r["growth"]: r for r in workloads.capacity_growth(spark, SF, (60000,), (0.2, 0.21, 1.0)).collect()}
    assert [m.config.growth for m in trained] == [0.2, 1.0] and len({m.count for m in trained}) == 1
    assert [m.log for m in trained] == [["retrain", "retrain", "update"], ["retrain", "update", "update"]]
    same = ("bulk_s", "batch_s", "forecast_ms", "rmse")
    assert [found[0.2][c] for c in same] == [found[0.21][c] for c in same]
    assert found[0.2]["retrains"] > found[1.0]["retrains"]
