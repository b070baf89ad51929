"""Whole tables go through the operators, odd rows included."""

import math
import os

import pytest

from pagecast.catalog_queries import QUERIES
from pagecast.operators import relational
from pagecast.sources.series import orders_by_priority, table

SF = "/root/testdata/sf0.001"

pytestmark = pytest.mark.skipif(not os.path.isdir(SF), reason="no test tables")

ODD = [(1, 'a "quoted", x', 1.5), (2, None, None), (3, "", math.inf), (4, " two\nlines\\ ", -math.inf), (5, "\\", math.nan), (6, '"', -0.0)]


@pytest.mark.parametrize("kind", ["csv", "json"])
def test_round_trip_keeps_every_row(spark, kind):
    df = spark.createDataFrame(ODD, "id long, s string, x double")
    got = getattr(relational, f"{kind}_round_trip")(df).collect()
    assert sorted(map(repr, got)) == sorted(map(repr, df.collect()))


@pytest.mark.parametrize("kind, name, most", [("csv", "orders", 7), ("json", "events", 5)])
def test_whole_table_is_written(spark, monkeypatch, kind, name, most):
    paths, scratch = [], relational.scratch_path
    monkeypatch.setattr(relational, "scratch_path", lambda s, n: paths.append(scratch(s, n)) or paths[-1])
    n = table(spark, SF, name).count()
    assert QUERIES[f"q_s03_{kind}"](spark, SF).count() < n / most + 1
    assert spark.read.format(kind).options(**(relational._CSV if kind == "csv" else {})).load(paths[-1]).count() == n
    assert QUERIES[f"q_s03_{kind}_whole"](spark, SF).count() == n


def test_every_element_and_order(spark):
    want = {(r["vec_id"], i) for r in table(spark, SF, "embeddings").collect() for i in range(len(r["embedding"]))}
    got = [(r["vec_id"], r["i"]) for r in QUERIES["q_p07_explode_whole"](spark, SF).collect()]
    assert len(got) == len(want) and set(got) == want
    assert QUERIES["q_d01_sql_function_whole"](spark, SF).count() == table(spark, SF, "orders").count()


def test_point_answers_every_observed_step(spark):
    keys = ["cohort", "series_id", "step"]
    seen = {(r["series_id"], r["step"]) for r in orders_by_priority(spark, SF).select(*keys).collect()}
    got = [(r["series_id"], r["step"]) for r in QUERIES["q_m31_point"](spark, SF).where("mean is not null").collect()]
    assert len(got) == len(seen) and set(got) == seen


def test_windows_and_comparison_reach_the_last_step(spark):
    seen = {(r["series_id"], r["step"]): r["value"] for r in orders_by_priority(spark, SF).collect()}
    last = max(step for _, step in seen)
    halves = QUERIES["q_m26_two_windows_whole"](spark, SF).collect()
    assert {(r["series_id"], r["half"]) for r in halves} == {(s, step // 100) for s, step in seen}
    assert all(r["models"] == (1 if r["half"] in (0, last // 100) else 2) for r in halves)
    got = {(r["series_id"], r["step"]): (r["stored"], r["mean"]) for r in QUERIES["q_m33_compare_whole"](spark, SF).collect()}
    assert set(got) == {(s, step) for s in {s for s, _ in seen} for step in range(last + 1)}
    for at, (stored, mean) in got.items():
        assert stored == seen.get(at) and mean is not None
        # of full rank the pages come back; the steps after them are forecasts
        assert at[1] >= last + 1 - (last + 1) % 6 or abs(mean - (stored or 0.0)) < 1e-3
