"""Queries read the table that they are given: without it they fail."""

import pytest

from pagecast.catalog_queries import QUERIES

NAMES = [
    "q_a03_wbc",
    "q_a04_mean_error",
    "q_a05_wins",
    "q_a08_speedups",
    "q_a10_relative",
    "q_a12_relative",
    "q_b13_capabilities",
    "q_d08_recursive",
    "q_f03_probit",
    "q_f11_gauss",
    "q_f11_planted",
]


@pytest.mark.parametrize("name", NAMES)
def test_needs_its_table(spark, tmp_path, name):
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        QUERIES[name](spark, str(tmp_path)).collect()
