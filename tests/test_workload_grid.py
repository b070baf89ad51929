"""The registered workloads run over all data sets and the whole grid."""

import inspect
import os

import pytest

from pagecast.catalog_queries import QUERIES
from pagecast.plans import workloads
from pagecast.sources import synth

FULL = {
    "q_w01_mean_imputation": ("mean_imputation", {"keeps": (1.0, 0.8, 0.5), "sigmas": (0.0, 0.1, 0.2, 0.5, 1.0), "only": ("orders", "lineitem", "events", "synthetic")}),
    "q_w02_mean_forecasting": ("mean_forecasting", {"keeps": (1.0, 0.8, 0.5), "sigmas": (0.0, 0.1, 0.2, 0.5, 1.0), "only": ("orders", "lineitem", "events", "synthetic")}),
    "q_w03_variance_imputation": ("variance_imputation", {"keeps": (1.0, 0.8, 0.5), "n": 10, "steps": 600}),
    "q_w04_variance_forecasting": ("variance_forecasting", {"keeps": (1.0, 0.8, 0.5), "n": 10, "steps": 600}),
    "q_w05_noise_kinds": ("noise_kinds", {"n": 10, "steps": 2000}),
    "q_w16_summary": ("variance_imputation", {"keeps": (1.0, 0.8, 0.5), "n": 10, "steps": 600}),
}


@pytest.mark.parametrize("name", sorted(FULL))
def test_nothing_is_left_out(monkeypatch, name):
    function, want = FULL[name]
    signature, got = inspect.signature(getattr(workloads, function)), {}

    def called(*args, **options):
        bound = signature.bind(*args, **options)
        bound.apply_defaults()
        got.update(bound.arguments)

    monkeypatch.setattr(workloads, function, called)
    monkeypatch.setattr(workloads, "summary", lambda results: results)
    QUERIES[name](None, "")
    assert {k: got[k] for k in want} == want


def test_grid_points_are_the_single_ones(spark):
    cells = synth.grid(spark, 3, 40)
    every = synth.plant_grid(cells, 40, [1.0, 0.5], [0.0, 0.2])
    columns = ["series_id", "rank", "step", "latent", "value"]
    for keep in (1.0, 0.5):
        for sigma in (0.0, 0.2):
            want = synth.plant(cells, 40, keep, sigma).select(*columns).collect()
            got = every.where(f"cohort = 'p{keep:g}-s{sigma:g}'").select(*columns).collect()
            assert sorted(map(tuple, got), key=lambda r: (r[0], r[2])) == sorted(map(tuple, want), key=lambda r: (r[0], r[2]))


@pytest.mark.skipif(not os.path.isdir("/root/testdata/sf0.001"), reason="no test tables")
def test_errors_are_written(spark):
    """The result is short rows in files, not one plan over every grid point."""
    found = workloads.mean_imputation(spark, "/root/testdata/sf0.001", (1.0, 0.5), (0.2,), ("events",), rivals=False)
    assert found.count() == 4 and found.where("nrmse is null").count() == 0
    assert all("/errors-" in f for f in found.inputFiles())
