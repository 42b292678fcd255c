"""Statistics of frequencies: exact forms, the sums they derive from, and checks of user functions."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Sums of g(f) (and of h(m, f)) that all built-in statistics derive from.
SUMS = ("l1", "l2", "card", "flogf", "mf", "mmf")
STATISTICS = ("l1", "l2", "card", "entropy")


def sum_exprs(f: str = "f", m: str = "m") -> dict[str, Column]:
    x, v = F.col(f), F.col(m)
    return {"l1": x, "l2": x * x, "card": F.lit(1).cast("long"), "flogf": x * F.log(x.cast("double")), "mf": v * x, "mmf": v * v * x}


def entropy(l1: Column, flogf: Column, card: Column | None = None, base: float = math.e) -> Column:
    """From two sums; null for nothing. Clamped to [0, log card] where card is known."""
    h = F.log(l1) - flogf / l1
    h = F.greatest(h, F.lit(0.0))
    if card is not None:
        h = F.least(h, F.log(F.greatest(card, F.lit(1))))
    return F.when(l1 > 0, h / math.log(base))


def mean(l1: Column, mf: Column) -> Column:
    return F.when(l1 > 0, mf / l1)


def deviation(l1: Column, mf: Column, mmf: Column) -> Column:
    return F.when(l1 > 0, F.sqrt(F.greatest(mmf / l1 - (mf / l1) * (mf / l1), F.lit(0.0))))


@dataclass(frozen=True)
class GSum:
    """A user statistic: the sum of g over frequencies, ``expr`` in SQL over ``f``."""

    name: str
    expr: str

    def column(self) -> Column:
        return F.expr(self.expr)

    def check(self, spark, top: int = 1 << 20) -> None:
        """Refuses g that falls, is negative, or grows faster than the square, on a grid of frequencies."""
        fs = sorted({1, 2, 3, 5, 7, *(1 << k for k in range(1, top.bit_length()))})
        rows = spark.createDataFrame([(x,) for x in fs], "f long").select("f", F.expr(self.expr).cast("double").alias("g")).orderBy("f").collect()
        values = [r["g"] for r in rows]
        if min(values) < 0 or any(b < a for a, b in zip(values, values[1:], strict=False)):
            raise ValueError(f"{self.name}: g must be monotone and not negative")
        scale = max(values[0], 1e-12)
        if any(v > 4 * scale * x * x for v, x in zip(values, fs, strict=True)):
            raise ValueError(f"{self.name}: g grows faster than the square")


def moment(p: float) -> GSum:
    if not 0 <= p <= 2:
        raise ValueError("moments of order 0 to 2 only")
    return GSum(f"f{p:g}".replace(".", "_"), f"pow(f, {p})")


def quantile(*_) -> None:
    raise NotImplementedError("quantiles are not sums of g over frequencies; use the exact or quantile-sketch baselines")


def truth(pairs: DataFrame, by: list[str]) -> DataFrame:
    """Exact statistics of each subpopulation from its pair counts."""
    s = pairs.groupBy(*by).agg(*(F.sum(c).alias(k) for k, c in sum_exprs().items()))
    l1 = F.col("l1")
    return s.withColumn("entropy", entropy(l1, F.col("flogf"))).withColumn("mean", mean(l1, F.col("mf"))).withColumn("std", deviation(l1, F.col("mf"), F.col("mmf")))
