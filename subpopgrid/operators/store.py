"""The sketch store: states as Parquet, partitioned by configuration and grid row, sorted by column."""

from __future__ import annotations

import json
from dataclasses import asdict

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..schema import GridConfig, WorkloadSpec
from .grid import GridState
from .merge import merge_full, merge_heaps

HEAPS = "layer int, subpop_key string, m long, f long, depth int, grid_col int, config_id string, part string, grid_row int"
COUNTERS = "layer int, cs_row int, cs_col int, c long, grid_col int, config_id string, part string, grid_row int"


def save(state: GridState, path: str, part: str = "0") -> None:
    """Adds one part (a window, a batch); saving a part again replaces it."""
    spark, cid = state.heaps.sparkSession, state.cfg.config_id
    manifest = {"config": asdict(state.cfg), "spec": asdict(state.spec), "frozen": state.frozen}
    spark.createDataFrame([(cid, json.dumps(manifest))], "config_id string, manifest string").coalesce(1).write.mode("overwrite").json(f"{path}/manifest/config_id={cid}")
    for name, df in (("heaps", state.heaps), ("counters", state.counters)):
        if df is not None:
            lined = df.repartitionByRange("grid_row", "grid_col").sortWithinPartitions("grid_row", "grid_col")
            lined.write.mode("overwrite").partitionBy("grid_row").parquet(f"{path}/{name}/config_id={cid}/part={part}")


def _read(spark: SparkSession, path: str, name: str, schema: str) -> DataFrame:
    return spark.read.schema(schema).option("basePath", f"{path}/{name}").parquet(f"{path}/{name}")


def load(spark: SparkSession, path: str, spec: WorkloadSpec, cfg: GridConfig, frozen: bool) -> list[GridState]:
    """One state a stored part of this configuration; filters on grid_row and grid_col prune folders and row groups."""
    heaps = _read(spark, path, "heaps", HEAPS).where(F.col("config_id") == cfg.config_id)
    counters = None if frozen else _read(spark, path, "counters", COUNTERS).where(F.col("config_id") == cfg.config_id)
    parts = [r["part"] for r in heaps.select("part").distinct().orderBy("part").collect()]  # a row a stored part
    pick = lambda df, p: None if df is None else df.where(F.col("part") == p).drop("part", "config_id")
    return [GridState(spec, cfg, pick(heaps, p), pick(counters, p)) for p in parts]


def append(state: GridState, path: str, part: str) -> None:
    save(state, path, part)


def compact(spark: SparkSession, path: str, spec: WorkloadSpec, cfg: GridConfig, frozen: bool) -> GridState:
    """All parts as one state: read once and grouped, however many parts there are."""
    heaps = _read(spark, path, "heaps", HEAPS).where(F.col("config_id") == cfg.config_id).drop("part", "config_id")
    if frozen:
        return merge_heaps(GridState(spec, cfg, heaps))
    counters = _read(spark, path, "counters", COUNTERS).where(F.col("config_id") == cfg.config_id).drop("part", "config_id")
    return merge_full(GridState(spec, cfg, heaps, counters))
