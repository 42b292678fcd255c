"""User functions registered for SQL: Arrow-batched Python where built-ins can't say it, SQL functions where they can."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType


@F.pandas_udf(DoubleType())
def sqrt_g(f: pd.Series) -> pd.Series:
    """A custom g, a batch at a time."""
    return f.astype("float64") ** 0.5


@F.pandas_udf(DoubleType())
def entropy_of(f: pd.Series) -> float:
    """Entropy of a group's frequencies."""
    import numpy as np

    p = f.to_numpy("float64")
    return float(np.log(p.sum()) - (p * np.log(p)).sum() / p.sum()) if len(p) else 0.0


@F.udtf(returnType="gid long, kept int")
class ExplodeCuboids:
    """All grouping-set ids of so many dimensions, with the number of dimensions each keeps."""

    def eval(self, dims: int):
        for gid in range(1 << dims):
            yield gid, dims - bin(gid).count("1")


@F.udtf(returnType="grid_row int, grid_col int")
class SubpopCells:
    """The cell of a subpopulation in each of r rows of w columns (portable hash)."""

    def eval(self, key: str, r: int, w: int, salt: int):
        import hashlib

        digits = min(15, 32 // r)
        h = hashlib.md5(f"s{salt}|{key}".encode()).hexdigest()
        for i in range(r):
            yield i, int(h[i * digits : (i + 1) * digits], 16) % w


def register(spark: SparkSession) -> None:
    spark.udf.register("entropy_of", entropy_of)
    spark.udtf.register("explode_cuboids", ExplodeCuboids)
    spark.udtf.register("subpop_cells", SubpopCells)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION bit_length_of(x BIGINT) RETURNS BIGINT RETURN CAST(length(bin(x)) - 1 AS BIGINT)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION cells_of(r INT, w INT) RETURNS TABLE(grid_row INT, grid_col INT) RETURN SELECT a.id, b.id FROM (SELECT explode(sequence(0, r - 1)) AS id) a CROSS JOIN (SELECT explode(sequence(0, w - 1)) AS id) b")
