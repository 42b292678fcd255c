"""Configuration from targets, error bounds, and models of memory, operations and complexity."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators.fanout import pair_counts
from ..schema import GridConfig, WorkloadSpec

CHOSEN_C = 4  # collisions may exceed their mean by this factor


def rows_for(delta: float) -> int:
    """About ln(1/delta) rows, made odd: 3 at 90 %."""
    n = math.ceil(math.log(1 / delta) - 1e-12)
    return n if n % 2 else n + 1


def strict_rows(delta: float, inner_failure: float = 0.1, c: float = CHOSEN_C) -> int:
    """Odd rows whose median fails with at most ``delta`` if each fails with ``inner_failure + 1/c``."""
    p = 1 - inner_failure - 1 / c
    if p <= 0.5:
        raise ValueError("a single row must succeed with more than one half")
    r = 1
    while sum(math.comb(r, i) * p**i * (1 - p) ** (r - i) for i in range(r // 2 + 1)) > delta:
        r += 2
    return r


def optimal_inner(memory: float, ratio: float, printed_root: bool = False) -> tuple[float, int]:
    """Inner error and width that minimise x + A / (M x^2), A = G_S / G_min: the cube root of 2A/M, width 1/x^2.

    ``printed_root``: the square root in its place, kept for comparison.
    """
    x = (2 * ratio / memory) ** (1 / 2 if printed_root else 1 / 3)
    return x, round(1 / (x * x))


def optimal_outer(memory: float, ratio: float) -> tuple[float, int]:
    """Outer error and number of columns for the counters that remain: w = M x^2, eps = 1/w."""
    x, _ = optimal_inner(memory, ratio)
    w = memory * x * x
    return 1 / w, round(w)


def layers_for(distinct: float) -> int:
    """Halvings until few keys are left."""
    return max(1, math.ceil(math.log2(max(2.0, distinct))))


def heap_for(inner: float) -> int:
    return max(1, math.ceil(1 / (inner * inner) - 1e-9))


def model_bytes(cfg: GridConfig, counter: int = 4, entry: int = 16) -> int:
    """Bytes of a dense grid: counters and full heaps."""
    return cfg.r * cfg.w * cfg.layers * (cfg.r_cs * cfg.w_cs * counter + cfg.k * entry)


def recommend(relative_error: float, delta: float, gmin_ratio: float, distinct: float, memory: int | None = None, mode: str = "paper") -> GridConfig:
    """A grid for the wanted relative error at G_min = gmin_ratio * G_S with probability 1 - delta.

    At the optimum the outer error is half the inner one: x = error / 1.5, counters M = 2A / x^3. ``strict`` sizes rows
    by the binomial tail and columns by the collision factor, ``paper`` by orders of magnitude. ``memory`` caps
    bytes: the columns shrink to fit.
    """
    ratio, x = 1 / gmin_ratio, relative_error / 1.5
    r = rows_for(delta) if mode == "paper" else strict_rows(delta)
    w_u = 1 << max(4, math.ceil(math.log2(1 / (x * x))))
    w = max(1, round(2 * ratio / x * (1 if mode == "paper" else CHOSEN_C * (1 + x) / 2)))
    layers = layers_for(max(2.0, distinct / max(1, w * heap_for(x)) * 4))
    cfg = GridConfig(r=r, w=w, layers=layers, r_cs=rows_for(delta), w_cs=w_u, k=heap_for(x))
    while memory and model_bytes(cfg) > memory and cfg.w > 1:
        cfg = cfg.but(w=max(1, cfg.w * memory // model_bytes(cfg)) if cfg.w * memory // model_bytes(cfg) < cfg.w else cfg.w - 1)
    return cfg


def predicted_error(cfg: GridConfig, ratio: float) -> float:
    return 1 / math.sqrt(cfg.w_cs) + ratio / cfg.w


def bound(gi: Column, gs: Column | float, cfg: GridConfig, inner: float | None = None) -> tuple[Column, Column]:
    """Lower and upper end for a subpopulation's statistic: G_i(1-e) and G_i(1+e) + eps G_S, eps = c(1+e)/w."""
    e = inner if inner is not None else 1 / math.sqrt(min(cfg.w_cs, cfg.k))
    eps = CHOSEN_C * (1 + e) / cfg.w
    gs = gs if isinstance(gs, Column) else F.lit(gs)
    return gi * (1 - e), gi * (1 + e) + gs * eps


def cost_model(design: str, n: int, d: int, q: int, s: int, cfg: GridConfig) -> tuple[int, int]:
    """(time, space) in updates and in counters of the four designs, for n records, d dimensions, q subpopulations, s statistics."""
    cell = cfg.r_cs * cfg.w_cs
    fan = n * 2**d
    return {
        "per_key_state": (fan, q * n),
        "sketch_per_subpop_and_stat": (fan * s * cfg.r_cs, q * s * cell),
        "grid_per_stat": (fan * s * cfg.r * cfg.r_cs, cfg.r * cfg.w * s * cell),
        "universal_grid": (fan * cfg.r * cfg.r_cs, cfg.r * cfg.w * cfg.layers * cell),
    }[design]


def op_counts(cfg: GridConfig, pairs: int, parts: int) -> dict[str, float]:
    """Hash evaluations, layer updates and merged entries of a build, by configuration."""
    touched = 1.0 if cfg.layer_mode == "deepest" else sum(2.0**-j for j in range(cfg.layers))
    hashes = 2 if cfg.hash_mode == "one" else cfg.r * (1 + (cfg.layers - 1) + 2 * cfg.r_cs)
    cells = cfg.r * cfg.w * cfg.layers
    return {"hashes": float(pairs * hashes), "layer_updates": pairs * cfg.r * touched, "merged": float(parts * cells * (cfg.k + (cfg.r_cs * cfg.w_cs if cfg.merge_mode == "full" else 0)))}


def profile(df: DataFrame, spec: WorkloadSpec, fraction: float = 0.01, seed: int = 7) -> dict[str, float]:
    """G_S of L1 and L2 and counts of subpopulations and pairs, estimated from one pass over a sample."""
    pairs = pair_counts(df.sample(fraction, seed), spec)
    r = pairs.agg(F.count(F.lit(1)).alias("pairs"), F.approx_count_distinct("subpop_key").alias("subpops"), F.sum("f").alias("l1"), F.sum(F.col("f") * (F.col("f") - 1)).alias("l2")).first()
    return {"pairs": r["pairs"], "subpops": r["subpops"], "gs_l1": (r["l1"] or 0) / fraction, "gs_l2": (r["l2"] or 0) / fraction**2 + (r["l1"] or 0) / fraction}
