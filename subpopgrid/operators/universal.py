"""Universal sketches in grid cells: layered Count-Sketches, heaps, and sums of g over frequencies.

State in long form: ``counters`` (grid_row, grid_col, layer, cs_row, cs_col, c) and ``heaps`` (grid_row, grid_col,
layer, subpop_key, m, f, depth). Estimating sum g(f) from layered samples folds the layers from the deepest up, each
step doubling what is below and correcting by the layer's own heap. The fold is linear, so every heap entry has a
fixed weight: 2^j for an entry of layer j that goes no deeper, -2^j for one that does, 2^(L-1) in the last layer. All
statistics are one grouped aggregation over the heaps.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.hashing import add_cells, add_fields, bucket, sign
from ..schema import GridConfig

CELL = ("grid_row", "grid_col")
#: Dense counters of a whole grid up to this size are sent to every task.
BROADCAST_BYTES = 64 << 20


def to_cells(pairs: DataFrame, cfg: GridConfig) -> DataFrame:
    """(grid_row, grid_col, subpop_key, m, f, x, depth): every pair in its r cells.

    With bare metric keys the pairs of one cell and value are one key, whose counts add up.
    """
    rows = add_fields(add_cells(pairs.select("subpop_key", "m", "f"), cfg), cfg)
    if cfg.key_mode == "metric":
        rows = rows.groupBy(*CELL, "m", "x", "depth").agg(F.sum("f").alias("f")).withColumn("subpop_key", F.lit(""))
    return rows.select(*CELL, "subpop_key", "m", "f", "x", "depth")


def layered(cells: DataFrame, cfg: GridConfig) -> DataFrame:
    """Add ``layer``: the deepest only, or each one the key is sampled into."""
    if cfg.layer_mode == "deepest":
        return cells.withColumn("layer", F.col("depth"))
    return cells.withColumn("layer", F.explode(F.sequence(F.lit(0), F.col("depth"))))


def counters(cells: DataFrame, cfg: GridConfig) -> DataFrame:
    """Signed counters of every touched (cell, layer); at most r w layers r_cs w_cs rows, whatever the data."""
    probes = F.array(*(F.struct(bucket(F.col("x"), j, cfg).alias("cs_col"), sign(F.col("x"), j, cfg).alias("s")) for j in range(cfg.r_cs)))
    rows = layered(cells, cfg).select(*CELL, "layer", "f", F.posexplode(probes).alias("cs_row", "p"))
    return rows.groupBy(*CELL, "layer", "cs_row", F.col("p.cs_col").alias("cs_col")).agg(F.sum(F.col("p.s") * F.col("f")).alias("c"))


def estimated(cells: DataFrame, state: DataFrame, cfg: GridConfig) -> DataFrame:
    """Layered keys with ``f`` replaced by the median of their signed counters (left alone when heaps track values)."""
    keys = layered(cells, cfg)
    if cfg.heap_value == "tracked":
        return keys
    sparse = F.map_from_entries(F.collect_list(F.struct((F.col("cs_row") * cfg.w_cs + F.col("cs_col")).alias("k"), F.col("c").alias("v"))))
    # one dense array a (cell, layer): its keys then read counters by position
    dense = F.transform(F.sequence(F.lit(0), F.lit(cfg.r_cs * cfg.w_cs - 1)), lambda i: F.coalesce(F.try_element_at(F.col("_cs"), i), F.lit(0).cast("long")))
    cs = state.groupBy(*CELL, "layer").agg(sparse.alias("_cs")).withColumn("_cs", dense)
    # the configuration bounds the counters' size; a grid beyond the limit is joined by shuffle
    small = cfg.r * cfg.w * cfg.layers * cfg.r_cs * cfg.w_cs * 8 <= BROADCAST_BYTES
    joined = keys.join(F.broadcast(cs) if small else cs, [*CELL, "layer"])
    reads = F.array(*(sign(F.col("x"), j, cfg) * F.get("_cs", F.lit(j * cfg.w_cs) + bucket(F.col("x"), j, cfg)) for j in range(cfg.r_cs)))
    return joined.withColumn("f", F.sort_array(reads)[cfg.r_cs // 2]).drop("_cs")


def top_k(keys: DataFrame, k: int) -> DataFrame:
    """The k largest keys of each (cell, layer), total order; Spark keeps k a task before the shuffle."""
    line = W.partitionBy(*CELL, "layer").orderBy(F.desc("f"), "subpop_key", "m")
    return keys.withColumn("_n", F.row_number().over(line)).where(F.col("_n") <= k).drop("_n")


def heaps(cells: DataFrame, state: DataFrame | None, cfg: GridConfig) -> DataFrame:
    """(cell, layer, subpop_key, m, f, depth) of the heaps; entries without a positive value are none."""
    kept = top_k(estimated(cells, state, cfg).where("f > 0"), cfg.k)
    return kept.select(*CELL, "layer", "subpop_key", "m", "f", "depth")


def nested_view(heap: DataFrame, cfg: GridConfig) -> DataFrame:
    """Heaps of all layers: entries kept in their deepest layer only are candidates of every layer above it."""
    if cfg.layer_mode == "nested":
        return heap
    every = heap.drop("layer").withColumn("layer", F.explode(F.sequence(F.lit(0), F.col("depth"))))
    return top_k(every, cfg.k)


def entry_weight(cfg: GridConfig) -> Column:
    one = F.call_function("shiftleft", F.lit(1).cast("long"), F.col("layer"))
    return F.when(F.col("layer") == cfg.layers - 1, one).when(F.col("depth") > F.col("layer"), -one).otherwise(one)


def gsums(nested: DataFrame, cfg: GridConfig, gs: dict[str, Column], by: list[str]) -> DataFrame:
    """Per ``by`` group: the weighted sum of every g over the nested heaps."""
    return nested.withColumn("_w", entry_weight(cfg)).groupBy(*by).agg(*(F.sum(F.col("_w") * g).alias(name) for name, g in gs.items()))
