"""Inputs at the edges: rows on which a query once differed from its SQL, or a table that it did not read."""

from __future__ import annotations

import duckdb
import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
import pytest

from subpopgrid.plans.catalog import QUERIES, SQL
from tests.conftest import SF


def test_arrays_of_single_floats(spark, tmp_path):
    """Products on the border of a whole number, short, empty and missing arrays, missing elements."""
    thousandths = (np.arange(-3000, 3000) / 1000).astype(np.float32)
    rows = [*thousandths.reshape(-1, 60).tolist(), [0.5], [], None, [0.25, None, -0.041, 0.1], [None]]
    table = pa.table({"vec_id": pa.array(range(len(rows)), pa.int64()), "embedding": pa.array(rows, pa.list_(pa.float32()))})
    pq.write_table(table, tmp_path / "embeddings.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW embeddings AS SELECT * FROM '{tmp_path}/embeddings.parquet'")
    got = [tuple(r) for r in QUERIES["op_scalar_arrays"](spark, str(tmp_path)).orderBy("vec_id").collect()]
    assert got == con.execute(SQL["op_scalar_arrays"] + " ORDER BY vec_id").fetchall()


def test_ablation_builds_from_counts_of_all_records(spark, monkeypatch):
    """w_W10: each combination is one row, and the rows' weights are all records."""
    from pyspark.sql import functions as F

    from subpopgrid.operators import bounded

    class Seen(Exception):
        pass

    def build(df, spec, cfg):
        rows = df.groupBy(*spec.dims, spec.metric).agg(F.count(F.lit(1)).alias("n"), F.sum("wgt").alias("wgt"))
        raise Seen(rows.agg(F.max("n"), F.sum("wgt")).first())

    monkeypatch.setattr(bounded, "build_bounded", build)
    with pytest.raises(Seen) as seen:
        QUERIES["w_W10"](spark, SF)
    assert tuple(seen.value.args[0]) == (1, spark.read.parquet(f"{SF}/lineitem.parquet").count())


READS = ("cfg_cost_model", "cfg_memory_model", "cfg_optimal_widths", "cfg_recommend", "cfg_rows_for_delta", "op_sql_functions", "op_udtf_cuboids", "stream_rate_source")


@pytest.mark.parametrize("name", READS)
def test_reads_a_given_table(spark, tmp_path, name):
    with pytest.raises(Exception, match="PATH_NOT_FOUND|does not exist"):
        QUERIES[name](spark, str(tmp_path / "none")).collect()


def test_lists_stay_within_full_combinations(spark):
    """No list is gathered for a whole subpopulation, and the statistics are those of all values, missing ones left out."""
    from pyspark.sql import functions as F

    from subpopgrid.operators import baselines as B
    from subpopgrid.schema import WorkloadSpec

    df = spark.range(1000).select((F.col("id") % 3).alias("a"), F.when(F.col("id") % 5 > 0, F.col("id") % 5).alias("b"), F.when(F.col("id") % 7 > 0, F.col("id") % 11).alias("m"))
    spec = WorkloadSpec(("a", "b"))
    lists = B.exact_lists(df, spec)
    plan = lists._jdf.queryExecution().optimizedPlan().toString()
    assert "collect_list" in plan and plan.index("Expand") < plan.index("collect_list")
    names = ["subpop_key", "l1", "l2", "card"]
    true = B.ground_truth(df.where("m IS NOT NULL"), spec)
    assert sorted(map(tuple, lists.select(names).collect())) == sorted(map(tuple, true.select(names).collect()))
