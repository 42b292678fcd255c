"""Fan-out of records to every subpopulation they belong to."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import canonical_key
from ..schema import WorkloadSpec


def weight_of(spec: WorkloadSpec) -> Column:
    """The record's weight; negative ones are refused, since heaps can't take them back."""
    if spec.weight is None:
        return F.lit(1).cast("long")
    w = F.col(spec.weight).cast("long")
    return F.when(w < 0, F.raise_error(F.lit("negative weight"))).otherwise(w)


def preaggregate(df: DataFrame, spec: WorkloadSpec) -> DataFrame:
    """One row a combination of all dimensions and value: counts add, so the fan-out may run on them."""
    return df.groupBy(*spec.dims, spec.metric).agg(F.sum(weight_of(spec)).alias("wgt"))


def fan_out(df: DataFrame, spec: WorkloadSpec) -> DataFrame:
    """A row for each record and cuboid: gid, dims (null where rolled up), subpop_key, m, wgt. One explode, no shuffle."""
    gids = F.array(*(F.lit(spec.gid(c)).cast("long") for c in spec.sets()))
    rows = df.select(*spec.dims, F.col(spec.metric).cast("long").alias("m"), weight_of(spec).alias("wgt"), F.explode(gids).alias("gid"))
    n = len(spec.dims)
    keyed = rows.withColumn("subpop_key", canonical_key(spec))
    dims = [F.when(F.col("gid").bitwiseAND(1 << (n - 1 - i)) == 0, F.col(d)).alias(d) for i, d in enumerate(spec.dims)]
    return keyed.select("gid", *dims, "subpop_key", "m", "wgt")


def pair_counts(df: DataFrame, spec: WorkloadSpec, preaggregated: bool = True) -> DataFrame:
    """gid, dims, subpop_key, m, f: the frequency of every (subpopulation, value) pair.

    Grouping sets expand counts of full combinations rather than records: two shuffles with partial aggregation.
    """
    rows = preaggregate(df, spec) if preaggregated else df.select(*spec.dims, F.col(spec.metric), weight_of(spec).alias("wgt"))
    sets = [[F.col(d) for d in c] + [F.col(spec.metric)] for c in spec.sets()]
    grouped = rows.groupingSets(sets, *spec.dims, spec.metric).agg(F.sum("wgt").alias("f"), F.grouping_id().alias("_g"))
    out = grouped.select(F.shiftright("_g", 1).cast("long").alias("gid"), *spec.dims, F.col(spec.metric).cast("long").alias("m"), "f")
    return out.withColumn("subpop_key", canonical_key(spec)).select("gid", *spec.dims, "subpop_key", "m", "f")


def shape(df: DataFrame, spec: WorkloadSpec) -> DataFrame:
    """Records, subpopulations, pairs, and the sums over all subpopulations of L1 and of squared frequencies."""
    p = pair_counts(df, spec)
    return p.agg(F.count_distinct("subpop_key").alias("subpops"), F.count(F.lit(1)).alias("pairs"), F.sum("f").alias("gs_l1"), F.sum(F.col("f") * F.col("f")).alias("gs_l2"))
