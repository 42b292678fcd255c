"""Every query that has SQL gives the same rows in DuckDB."""

from __future__ import annotations

import pytest

from subpopgrid.plans.catalog import QUERIES, SQL
from tests.conftest import SF, same_rows

SLOW = {"w_W11", "err_pareto", "w_W9", "w_W3", "w_W4", "w_W10", "w_W11_runtime"}


@pytest.mark.parametrize("name", sorted(n for n in SQL if n not in SLOW))
def test_same_as_sql(spark, duck, name):
    same_rows(QUERIES[name](spark, SF), duck.execute(SQL[name]).df())


@pytest.mark.parametrize("name", sorted(n for n in QUERIES if n not in SQL and n not in SLOW))
def test_runs(spark, name):
    assert QUERIES[name](spark, SF).count() > 0
