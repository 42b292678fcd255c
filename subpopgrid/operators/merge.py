"""Merging grid states: in full, by heaps only, and in rounds."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import add_fields
from . import universal as U
from .grid import GridState


def _same(states: tuple[GridState, ...]) -> None:
    if len({s.cfg.config_id for s in states}) != 1 or len({s.spec.dims for s in states}) != 1:
        raise ValueError("only states of one configuration and workload merge")


def _union(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def add_counters(counters: DataFrame) -> DataFrame:
    """Counters are linear: equal cells add up. Partial sums precede the shuffle."""
    return counters.groupBy(*U.CELL, "layer", "cs_row", "cs_col").agg(F.sum("c").alias("c"))


def merge_full(*states: GridState) -> GridState:
    """Counters add; the union of all heap keys is estimated anew from the sums and cut to k."""
    _same(states)
    first = states[0]
    if any(s.frozen for s in states):
        raise ValueError("a frozen state has no counters to merge in full")
    cfg = first.cfg
    state = add_counters(_union([s.counters for s in states]))
    if cfg.heap_value == "tracked":
        keys = _union([s.heaps for s in states]).groupBy(*U.CELL, "layer", "subpop_key", "m", "depth").agg(F.sum("f").alias("f"))
        return GridState(first.spec, cfg, U.top_k(keys, cfg.k), state)
    keys = _union([s.heaps for s in states]).select(*U.CELL, "layer", "subpop_key", "m").distinct().withColumn("f", F.lit(0).cast("long"))
    if cfg.layer_mode == "nested":  # a key stands in all its layers: start again from its deepest row
        keys = keys.drop("layer").distinct()
    else:
        keys = keys.drop("layer")
    return GridState(first.spec, cfg, U.heaps(add_fields(keys, cfg), state, cfg), state)


def merge_heaps(*states: GridState) -> GridState:
    """Only heaps merge: equal keys add, the k largest stay. The result answers queries but takes no more records."""
    _same(states)
    first = states[0]
    keys = _union([s.heaps for s in states]).groupBy(*U.CELL, "layer", "subpop_key", "m", "depth").agg(F.sum("f").alias("f"))
    return GridState(first.spec, first.cfg, U.top_k(keys, first.cfg.k))


def tree_merge(heaps: DataFrame, counters: DataFrame | None, state: GridState, fan_in: int = 32) -> GridState:
    """Two rounds for the parts of many tasks (rows with ``part``): sums per cell and bucket of parts, cut to k, then per cell.

    State is bounded per part, so the first round takes at most ``fan_in`` parts' heaps together and a second ends it.
    """
    bucket = F.pmod(F.col("part"), F.lit(fan_in)).alias("part")
    once = heaps.groupBy(bucket, *U.CELL, "layer", "subpop_key", "m", "depth").agg(F.sum("f").alias("f"))
    from pyspark.sql import Window as W

    line = W.partitionBy("part", *U.CELL, "layer").orderBy(F.desc("f"), "subpop_key", "m")
    kept = once.withColumn("_n", F.row_number().over(line)).where(F.col("_n") <= state.cfg.k).drop("_n", "part")
    final = kept.groupBy(*U.CELL, "layer", "subpop_key", "m", "depth").agg(F.sum("f").alias("f"))
    return GridState(state.spec, state.cfg, U.top_k(final, state.cfg.k), None if counters is None else add_counters(counters))
