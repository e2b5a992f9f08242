"""Queries that once made their data up read a given table: other tables give other rows."""

from __future__ import annotations

import pytest

from tileaqp.operators.library import QUERIES

LARGER = "/root/testdata/sf0.01"


@pytest.mark.parametrize(
    "name",
    [
        "m03_pan",
        "m04_zoom",
        "m36_next_rate",
        "r08_interval_join",
        "r17_analytic_windows",
        "r23_recursive_quadtree",
        "s10_generated_uniform",
        "s10_generated_uniform_checked",
        "u02_quantile_functions",
        "u02_quantiles_checked",
    ],
)
def test_rows_come_from_the_tables(spark, sf, name):
    small, large = (sorted(map(tuple, QUERIES[name](spark, folder).collect())) for folder in (sf, LARGER))
    assert small and large and small != large
