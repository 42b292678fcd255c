"""Accuracy and cost measures over estimates and truth."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..plans.config import bound
from ..schema import GridConfig

STATS = ("l1", "l2", "card", "entropy")


def long_form(df: DataFrame, stats: tuple[str, ...] = STATS, value: str = "value") -> DataFrame:
    return df.select("subpop_key", *(F.col(s).cast("double").alias(s) for s in stats)).unpivot("subpop_key", list(stats), "stat", value)


def relative_error(est: DataFrame, true: DataFrame, stats: tuple[str, ...] = STATS) -> DataFrame:
    """(subpop_key, stat, truth, est, err): signed, misses count as estimate 0; only where truth is not 0."""
    e, t = long_form(est, stats, "est"), long_form(true, stats, "truth")
    both = t.join(e, ["subpop_key", "stat"], "left").withColumn("est", F.coalesce("est", F.lit(0.0)))
    return both.where("truth != 0").withColumn("err", (F.col("est") - F.col("truth")) / F.col("truth"))


def qualifying(errors: DataFrame, share: float) -> DataFrame:
    """Only subpopulations whose statistic is at least ``share`` of its sum over all subpopulations.

    The sum is one row a statistic, attached by a join.
    """
    gs = errors.groupBy("stat").agg(F.sum("truth").alias("gs"))
    return errors.join(F.broadcast(gs), "stat").where(F.col("truth") >= share * F.col("gs"))


def boxplot(errors: DataFrame) -> DataFrame:
    """Least, quartiles, greatest and whiskers (last values within 1.5 quartile ranges) of each statistic's errors."""
    q = errors.groupBy("stat").agg(F.min("err").alias("low"), *(F.expr(f"percentile(err, {p})").alias(n) for p, n in ((0.25, "q1"), (0.5, "median"), (0.75, "q3"))), F.max("err").alias("high"), F.count(F.lit(1)).alias("n"))
    iqr = F.col("q3") - F.col("q1")
    inside = errors.join(F.broadcast(q), "stat").where((F.col("err") >= F.col("q1") - 1.5 * iqr) & (F.col("err") <= F.col("q3") + 1.5 * iqr))
    return inside.groupBy("stat", "low", "q1", "median", "q3", "high", "n").agg(F.min("err").alias("whisker_low"), F.max("err").alias("whisker_high"))


def mean_error(errors: DataFrame) -> DataFrame:
    """Mean absolute error over a subpopulation's statistics."""
    return errors.groupBy("subpop_key").agg(F.avg(F.abs("err")).alias("mean_err"))


def within(errors: DataFrame, threshold: float) -> DataFrame:
    return errors.groupBy("stat").agg(F.avg((F.abs("err") <= threshold).cast("double")).alias("share"), F.count(F.lit(1)).alias("n"))


def error_by_size(errors: DataFrame) -> DataFrame:
    """Mean, median and variance of the error in decades of the normalised sum."""
    gs = errors.groupBy("stat").agg(F.sum("truth").alias("gs"))
    sized = errors.join(F.broadcast(gs), "stat").withColumn("decade", F.floor(F.log10(F.col("truth") / F.col("gs"))).cast("int"))
    return sized.groupBy("stat", "decade").agg(F.count(F.lit(1)).alias("n"), F.avg(F.abs("err")).alias("mean_abs"), F.expr("percentile(err, 0.5)").alias("median"), F.var_samp("err").alias("variance"))


def bound_coverage(errors: DataFrame, cfg: GridConfig, inner: float | None = None) -> DataFrame:
    """Share of estimates inside the theoretical interval, by statistic."""
    gs = errors.groupBy("stat").agg(F.sum("truth").alias("gs"))
    lo, hi = bound(F.col("truth"), F.col("gs"), cfg, inner)
    inside = ((F.col("est") >= lo) & (F.col("est") <= hi)).cast("double")
    return errors.join(F.broadcast(gs), "stat").groupBy("stat").agg(F.avg(inside).alias("coverage"), F.count(F.lit(1)).alias("n"))


def pareto(df: DataFrame, cost: str, error: str) -> DataFrame:
    """Add ``on_frontier``: nothing cheaper (or as cheap and earlier) is at least as good. ``df`` is a sweep's few rows."""
    line = W.orderBy(cost, error).rowsBetween(W.unboundedPreceding, -1)
    best = F.min(error).over(line)
    return df.withColumn("on_frontier", best.isNull() | (F.col(error) < best))


def timed(action: Callable[[], object]) -> tuple[object, float]:
    at = time.perf_counter()
    out = action()
    return out, time.perf_counter() - at


def normalised(seconds: dict[str, float], base: str) -> dict[str, float]:
    return {k: v / seconds[base] for k, v in seconds.items()}


def cost(seconds: float, cores: int) -> float:
    """Core seconds stand in for money."""
    return seconds * cores


def state_bytes(heaps: DataFrame, counters: DataFrame | None = None) -> DataFrame:
    """Bytes of a stored state: 4 a counter, 16 a heap entry."""
    h = heaps.agg((F.count(F.lit(1)) * 16).alias("heap_bytes"))
    if counters is None:
        return h.withColumn("counter_bytes", F.lit(0).cast("long"))
    return h.crossJoin(counters.agg((F.count(F.lit(1)) * 4).alias("counter_bytes")))  # one row each


def errors_as_columns(errors: DataFrame) -> DataFrame:
    """Statistics as columns."""
    return errors.groupBy("subpop_key").pivot("stat", list(STATS)).agg(F.first("err"))


def rounded(col: Column, digits: int = 6) -> Column:
    return F.round(col, digits)
