"""The driver's contract, and independence from the optional operators."""

from __future__ import annotations

import subprocess
import sys

import __spark_entry__
from tests.conftest import ROOT, SF


def test_contract(spark):
    queries, sql = __spark_entry__.queries(), __spark_entry__.oracle_sql()
    assert set(sql) <= set(queries) and len(queries) > 150
    assert __spark_entry__.entry(spark).columns[0] == "subpop_key"
    assert queries["grid_example_video"](spark, SF).count() > 0


def test_nothing_else_imports_the_optional_operators():
    for p in ROOT.glob("subpopgrid/**/*.py"):
        if "llm" not in p.parts:
            assert "llm" not in p.read_text(), p


def test_queries_are_listed_without_a_session():
    code = "import __spark_entry__ as e; e.queries(); e.oracle_sql()"
    assert subprocess.run([sys.executable, "-c", code], cwd=ROOT, capture_output=True, timeout=120).returncode == 0
