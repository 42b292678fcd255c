"""The grid: build from records, estimate any statistics of any subpopulations, discover large ones."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.hashing import add_cells, canonical_key
from ..functions.statistics import deviation, entropy, mean, sum_exprs
from ..schema import GridConfig, WorkloadSpec
from . import universal as U
from .fanout import pair_counts


@dataclass
class GridState:
    """Heaps, and counters unless frozen; ``spec`` and ``cfg`` say what they mean."""

    spec: WorkloadSpec
    cfg: GridConfig
    heaps: DataFrame
    counters: DataFrame | None = None

    @property
    def frozen(self) -> bool:
        return self.counters is None


def build_grid(df: DataFrame, spec: WorkloadSpec, cfg: GridConfig) -> GridState:
    """Declarative build: exact candidates, truncated to heaps at the end (the specification; see ``bounded`` for scale)."""
    cells = U.to_cells(pair_counts(df, spec), cfg)
    state = U.counters(cells, cfg)
    heap = U.heaps(cells, state, cfg)
    return GridState(spec, cfg, heap, None if cfg.merge_mode == "heap_only" else state)


def row_sums(state: GridState, subpops: DataFrame | None = None, gs: dict[str, Column] | None = None) -> DataFrame:
    """(subpop_key, grid_row, one column a sum): G-sums of each grid row.

    With pair keys only entries of the asked subpopulation count; ``subpops`` (distinct ``subpop_key``) restricts or,
    with bare keys, names the subpopulations.
    """
    gs = gs or sum_exprs()
    nested = U.nested_view(state.heaps, state.cfg)
    if state.cfg.key_mode == "pair":
        if subpops is not None:
            nested = nested.join(subpops.select("subpop_key"), "subpop_key", "left_semi")
        return U.gsums(nested, state.cfg, gs, ["subpop_key", "grid_row"])
    if subpops is None:
        raise ValueError("a grid of bare values can't list subpopulations")
    per_cell = U.gsums(nested, state.cfg, gs, list(U.CELL))
    return add_cells(subpops.select("subpop_key"), state.cfg).join(per_cell, list(U.CELL), "left").drop("grid_col")


def combine(rows: DataFrame, cfg: GridConfig, names: list[str], clamp: bool = True) -> DataFrame:
    """Median over the r rows; a row that misses the subpopulation counts as 0. Entropy, mean and deviation are
    derived in each row before the median."""
    l1 = F.col("l1")
    derived = rows
    if {"l1", "flogf"} <= set(names):
        derived = derived.withColumn("entropy", entropy(l1, F.col("flogf"), F.col("card") if clamp and "card" in names else None))
    if {"l1", "mf", "mmf"} <= set(names):
        derived = derived.withColumn("mean", mean(l1, F.col("mf"))).withColumn("std", deviation(l1, F.col("mf"), F.col("mmf")))
    out = [c for c in derived.columns if c not in ("subpop_key", "grid_row")]
    missing = F.expr(f"{cfg.r} - count(1)").cast("int")
    med = [F.sort_array(F.concat(F.collect_list(F.coalesce(F.col(c).cast("double"), F.lit(0.0))), F.array_repeat(F.lit(0.0), missing)))[cfg.r // 2].alias(c) for c in out]
    return derived.groupBy("subpop_key").agg(F.count(F.lit(1)).cast("int").alias("found_rows"), *med)


def estimate(state: GridState, subpops: DataFrame | None = None, gs: dict[str, Column] | None = None) -> DataFrame:
    """subpop_key, found_rows and the estimates; asked subpopulations that no heap holds come out as 0."""
    names = list(gs or sum_exprs())
    out = combine(row_sums(state, subpops, gs), state.cfg, names)
    if subpops is None:
        return out
    keys = subpops.select("subpop_key").distinct()
    values = [c for c in out.columns if c != "subpop_key"]
    return keys.join(out, "subpop_key", "left").select("subpop_key", *(F.coalesce(c, F.lit(0)).alias(c) for c in values))


def heavy_hitters(state: GridState, alpha: float, subpops: DataFrame | None = None) -> DataFrame:
    """(subpop_key, m, f): values held by most grid rows whose median count is at least alpha of the estimated L1."""
    cfg = state.cfg
    top = U.nested_view(state.heaps, cfg).where("layer = 0")
    if subpops is not None:
        top = top.join(subpops.select("subpop_key"), "subpop_key", "left_semi")
    keys = top.groupBy("subpop_key", "m").agg(F.sort_array(F.collect_list("f")).alias("fs")).where(F.size("fs") > cfg.r // 2)
    found = keys.select("subpop_key", "m", F.col("fs")[F.floor((F.size("fs") - 1) / 2).cast("int")].alias("f"))
    l1 = estimate(state, subpops, {"l1": F.col("f")}).select("subpop_key", "l1")
    return found.join(l1, "subpop_key").where(F.col("f") >= alpha * F.col("l1")).select("subpop_key", "m", "f")


def weighted_median(state: GridState, subpops: DataFrame | None = None) -> DataFrame:
    """(subpop_key, median): the middle of the recovered values, weighted by the fold. Best effort: no guarantee.

    A row's value masses are sums of entry weights times counts; the median over the rows that hold the subpopulation.
    """
    nested = U.nested_view(state.heaps, state.cfg).withColumn("_w", U.entry_weight(state.cfg))
    if subpops is not None:
        nested = nested.join(subpops.select("subpop_key"), "subpop_key", "left_semi")
    mass = nested.groupBy("subpop_key", "grid_row", "m").agg(F.sum(F.col("_w") * F.col("f")).alias("mass")).where("mass > 0")
    line = W.partitionBy("subpop_key", "grid_row")
    ranked = mass.withColumn("upto", F.sum("mass").over(line.orderBy("m"))).withColumn("whole", F.sum("mass").over(line))
    rows = ranked.where("2 * upto >= whole").groupBy("subpop_key", "grid_row").agg(F.min("m").alias("mid"))
    return rows.groupBy("subpop_key").agg(F.sort_array(F.collect_list("mid")).alias("v")).select("subpop_key", F.col("v")[F.floor((F.size("v") - 1) / 2).cast("int")].alias("median"))


def discover(state: GridState, stat: str, least: float) -> DataFrame:
    """Subpopulations the heaps know whose estimate reaches ``least``."""
    if state.cfg.key_mode != "pair":
        raise ValueError("only pair keys name their subpopulations")
    return estimate(state).where(F.col(stat) >= least)


@dataclass(frozen=True)
class StatQuery:
    """``SELECT stats GROUP BY dims``: plans to the distinct subpopulations of the records, or those discovered."""

    dims: tuple[str, ...]
    stats: tuple[str, ...]
    where: str | None = None

    def subpops(self, df: DataFrame, spec: WorkloadSpec) -> DataFrame:
        gid = spec.gid(self.dims)
        rows = df.where(self.where) if self.where else df
        named = rows.select(*self.dims).distinct()
        full = named.select(F.lit(gid).cast("long").alias("gid"), *(F.col(d) if d in self.dims else F.lit(None).cast(dict(df.dtypes)[d]).alias(d) for d in spec.dims))
        return full.withColumn("subpop_key", canonical_key(spec))

    def run(self, state: GridState, df: DataFrame) -> DataFrame:
        keys = self.subpops(df, state.spec)
        return keys.join(estimate(state, keys), "subpop_key").select(*self.dims, *self.stats)
