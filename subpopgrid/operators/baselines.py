"""What the grid is compared with: exact lists, key-value stores, roll-ups, samples and a sketch per subpopulation."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import HEX, add_fields
from ..functions.statistics import entropy, truth
from ..schema import GridConfig, WorkloadSpec
from . import universal as U
from .fanout import fan_out, pair_counts, weight_of


def exact_lists(df: DataFrame, spec: WorkloadSpec) -> DataFrame:
    """The raw-row engine: all values gathered in lists at query time, statistics by functions over them.

    A list holds the values of one full combination. A subpopulation's list is those of its combinations one after another; it is
    never laid out, as its run lengths are sums of theirs. Memory grows with the largest combination: ``ground_truth``
    is the good form.
    """
    lists = df.groupBy(*spec.dims).agg(F.sort_array(F.collect_list(F.col(spec.metric).cast("long"))).alias("v"))
    # one pass over the sorted list: a run begins where the value changes, and ends where the next begins
    starts = lists.withColumn("at", F.expr("filter(transform(v, (x, i) -> IF(i = 0 OR v[i - 1] != x, i, NULL)), i -> i IS NOT NULL)"))
    runs = starts.select(*spec.dims, F.expr("inline_outer(transform(at, (i, k) -> named_struct('m', v[i], 'n', CAST(coalesce(get(at, k + 1), size(v)) - i AS BIGINT))))"))
    own = WorkloadSpec(spec.dims, "m", "n", None, spec.max_order, spec.include_total, spec.cuboids)
    f = F.col("f")
    sums = pair_counts(runs, own, preaggregated=False).groupBy("subpop_key").agg(
        *(F.coalesce(F.sum(g), F.lit(0)).alias(c) for c, g in (("l1", f), ("l2", f * f))), F.count(f).alias("card"), F.coalesce(F.sum(f * F.log(f.cast("double"))), F.lit(0.0)).alias("flogf")
    )
    return sums.withColumn("entropy", entropy(F.col("l1"), F.col("flogf"))).drop("flogf")


def ground_truth(df: DataFrame, spec: WorkloadSpec) -> DataFrame:
    """Exact statistics through pair counts: two hash aggregations."""
    return truth(pair_counts(df, spec), ["subpop_key"])


def quantiles_exact(df: DataFrame, spec: WorkloadSpec, points: tuple[float, ...] = (0.25, 0.5, 0.75)) -> DataFrame:
    """Exact quantiles of the metric, weighted by pair counts."""
    pairs = pair_counts(df, spec)
    return pairs.groupBy("subpop_key").agg(*(F.expr(f"percentile(m, {p}D, f)").alias(f"q{round(100 * p)}") for p in points))


def quantiles_sketched(df: DataFrame, spec: WorkloadSpec, points: tuple[float, ...] = (0.25, 0.5, 0.75)) -> DataFrame:
    """Quantiles from one mergeable sketch a subpopulation."""
    one = fan_out(df, spec).groupBy("subpop_key").agg(F.expr("kll_sketch_agg_bigint(m)").alias("s"))
    return one.select("subpop_key", *(F.expr(f"kll_sketch_get_quantile_bigint(s, {p}D)").alias(f"q{round(100 * p)}") for p in points))


def kv_build(df: DataFrame, spec: WorkloadSpec) -> DataFrame:
    """The key-value store: the count of every pair, made at ingestion."""
    return pair_counts(df, spec).select("subpop_key", "m", "f")


def kv_query(store: DataFrame) -> DataFrame:
    return truth(store, ["subpop_key"])


def rollup_build(df: DataFrame, spec: WorkloadSpec) -> DataFrame:
    """The roll-up store: only the finest combinations, sorted for reading."""
    return df.groupBy(*spec.dims, F.col(spec.metric).alias("m")).agg(F.sum(weight_of(spec)).alias("wgt")).sortWithinPartitions(*spec.dims)


def rollup_query(store: DataFrame, spec: WorkloadSpec) -> DataFrame:
    """Any cuboid is rolled up from the finest at query time."""
    return truth(pair_counts(store, WorkloadSpec(spec.dims, "m", "wgt", None, spec.max_order, spec.include_total, spec.cuboids), preaggregated=False), ["subpop_key"])


def hash_slice(text: Column) -> Column:
    return F.conv(F.substring(F.md5(text), 1, HEX), 16, 10).cast("long")


def hash_sample_card(df: DataFrame, spec: WorkloadSpec, one_in: int) -> DataFrame:
    """Distinct values from a hash sample of the values: kept ones times ``one_in``."""
    kept = df.where(hash_slice(F.concat(F.lit("v|"), F.col(spec.metric).cast("string"))) % one_in == 0)
    return pair_counts(kept, spec).groupBy("subpop_key").agg((F.count(F.lit(1)) * one_in).alias("card"))


def with_record_id(df: DataFrame, id_text: Column) -> DataFrame:
    return df.withColumn("_id", id_text)


def uniform_sample(df: DataFrame, id_text: Column, one_in: int) -> DataFrame:
    """A Bernoulli sample by a hash of the record's own text: the same rows in any engine and partitioning."""
    return df.where(hash_slice(F.concat(F.lit("u|"), id_text)) % one_in == 0)


def sample_stats(sample: DataFrame, spec: WorkloadSpec, one_in: int, with_entropy: bool = True) -> DataFrame:
    """L1 times 1/p; L2 corrected to be unbiased, (sum f^2 - (1-p) sum f) / p^2; cardinality and entropy as they stand."""
    out = scaled(truth(pair_counts(sample, spec), ["subpop_key"]), one_in)
    return out if with_entropy else out.drop("entropy")


def scaled(s: DataFrame, one_in: int) -> DataFrame:
    """A uniform sample's statistics as those of all records."""
    p = 1.0 / one_in
    return s.select("subpop_key", (F.col("l1") * one_in).alias("l1"), ((F.col("l2") - (1 - p) * F.col("l1")) / (p * p)).alias("l2"), "card", (F.col("card") * one_in).alias("card_scaled"), "entropy")


def sketches_build(df: DataFrame, spec: WorkloadSpec, cfg: GridConfig) -> DataFrame:
    """Heaps of one universal sketch for every subpopulation: exact separation, state that grows with their number."""
    one = cfg.but(r=1)
    pairs = pair_counts(df, spec).select("subpop_key", "m", "f").withColumn("grid_row", F.lit(0)).withColumn("grid_col", hash_slice(F.col("subpop_key")))
    cells = add_fields(pairs, one).select(*U.CELL, "subpop_key", "m", "f", "x", "depth")
    return U.heaps(cells, U.counters(cells, one) if one.heap_value == "estimate" else None, one)


def sketches_query(heap: DataFrame, cfg: GridConfig) -> DataFrame:
    one = cfg.but(r=1)
    sums = U.gsums(U.nested_view(heap, one), one, {"l1": F.col("f"), "l2": F.col("f") * F.col("f"), "card": F.lit(1).cast("long"), "flogf": F.col("f") * F.log(F.col("f").cast("double"))}, ["subpop_key"])
    return sums.withColumn("entropy", entropy(F.col("l1"), F.col("flogf"), F.col("card"))).drop("flogf")


def sketch_per_subpop(df: DataFrame, spec: WorkloadSpec, cfg: GridConfig) -> DataFrame:
    return sketches_query(sketches_build(df, spec, cfg), cfg)


def stat_sketch_per_subpop(df: DataFrame, spec: WorkloadSpec) -> DataFrame:
    """A cardinality sketch for every subpopulation."""
    return fan_out(df, spec).groupBy("subpop_key").agg(F.hll_sketch_estimate(F.hll_sketch_agg("m", 12)).alias("card"))


def grid_of_hll(df: DataFrame, spec: WorkloadSpec, cfg: GridConfig) -> DataFrame:
    """A grid whose cells hold one cardinality sketch: (grid_row, grid_col, card)."""
    from ..functions.hashing import add_cells

    keyed = add_cells(pair_counts(df, spec), cfg)
    return keyed.groupBy(*U.CELL).agg(F.hll_sketch_estimate(F.hll_sketch_agg(F.concat_ws("|", "subpop_key", F.col("m").cast("string")), 12)).alias("card"))


def hll_grid_estimates(df: DataFrame, spec: WorkloadSpec, cfg: GridConfig) -> DataFrame:
    """(subpop_key, card): a subpopulation's cardinality from a grid of cardinality sketches of pairs.

    A cell counts the pairs of all subpopulations in it, so no estimate is too small but for the sketch's own error: the
    least over the rows is taken.
    """
    from ..functions.hashing import add_cells

    keys = pair_counts(df, spec).select("subpop_key").distinct()
    return add_cells(keys, cfg).join(grid_of_hll(df, spec, cfg), list(U.CELL)).groupBy("subpop_key").agg(F.min("card").alias("card"))


def countmin_points(pairs: DataFrame, cfg: GridConfig) -> DataFrame:
    """(subpop_key, m, f): every pair's frequency from a grid of unsigned counters, the least over grid and sketch rows."""
    from ..functions.hashing import bucket

    cells = U.to_cells(pairs, cfg)
    probes = F.array(*(bucket(F.col("x"), j, cfg) for j in range(cfg.r_cs)))
    rows = cells.select(*U.CELL, "subpop_key", "m", "f", F.posexplode(probes).alias("j", "cs_col"))
    sums = rows.groupBy(*U.CELL, "j", "cs_col").agg(F.sum("f").alias("c"))
    return rows.join(sums, [*U.CELL, "j", "cs_col"]).groupBy("subpop_key", "m").agg(F.min("c").alias("f"))


def grid_of_countmin(df: DataFrame, spec: WorkloadSpec, cfg: GridConfig, eps: float = 0.01, confidence: float = 0.95, seed: int = 1) -> DataFrame:
    """A grid whose cells hold a count-min sketch of their pairs (one row a record and cell): (grid_row, grid_col, bytes)."""
    from ..functions.hashing import add_cells

    keyed = add_cells(fan_out(df, spec).withColumn("f", F.col("wgt")), cfg)
    return keyed.groupBy(*U.CELL).agg(F.length(F.count_min_sketch(F.concat_ws("|", "subpop_key", F.col("m").cast("string")), F.lit(eps), F.lit(confidence), F.lit(seed))).alias("bytes"))
