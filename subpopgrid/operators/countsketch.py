"""Counter sketches: one hashed row, several rows, and the signed Count-Sketch with its top keys."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.hashing import HEX


def _field(key: Column, row: int, what: str, salt: int = 0) -> Column:
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{what}{salt}.{row}|"), key)), 1, HEX), 16, 10).cast("long")


def hash_counter(keys: DataFrame, key: str, width: int, rows: int = 1) -> DataFrame:
    """(row, col, c): plain counters; ``keys`` has the key and its weight ``f``."""
    cols = F.posexplode(F.array(*(_field(F.col(key), r, "c") % width for r in range(rows)))).alias("row", "col")
    return keys.select("f", cols).groupBy("row", "col").agg(F.sum("f").alias("c"))


def counter_estimate(keys: DataFrame, key: str, counters: DataFrame, width: int, rows: int, summary: str = "min") -> DataFrame:
    """Key and its estimate: the least, or the median, of its counters."""
    cols = F.posexplode(F.array(*(_field(F.col(key), r, "c") % width for r in range(rows)))).alias("row", "col")
    probed = keys.select(key, cols).join(F.broadcast(counters), ["row", "col"])  # rows x width counters: fixed by configuration
    both = F.min("c") if summary == "min" else F.sort_array(F.collect_list("c"))[rows // 2]
    return probed.groupBy(key).agg(both.alias("estimate"))


def _probes(keys: DataFrame, key: str, width: int, rows: int, *more: str) -> DataFrame:
    probes = F.array(*(F.struct((_field(F.col(key), r, "b") % width).alias("col"), (_field(F.col(key), r, "s") % 2 * 2 - 1).alias("sign")) for r in range(rows)))
    return keys.select(key, *more, F.posexplode(probes).alias("row", "p")).select(key, *more, "row", "p.col", "p.sign")


def count_sketch(keys: DataFrame, key: str, width: int, rows: int) -> DataFrame:
    """(row, col, c): signed counters; linear, so sketches of parts add up to that of the whole."""
    return _probes(keys, key, width, rows, "f").groupBy("row", "col").agg(F.sum(F.col("sign") * F.col("f")).alias("c"))


def cs_estimate(keys: DataFrame, key: str, counters: DataFrame, width: int, rows: int) -> DataFrame:
    """Key and the median of its signed counters."""
    probed = _probes(keys, key, width, rows).join(F.broadcast(counters), ["row", "col"])  # rows x width counters
    return probed.groupBy(key).agg(F.sort_array(F.collect_list(F.col("sign") * F.col("c")))[rows // 2].alias("estimate"))


def cs_topk(keys: DataFrame, key: str, counters: DataFrame, width: int, rows: int, k: int) -> DataFrame:
    """The k keys of largest estimate, ties by key; each task keeps k before the last step."""
    return cs_estimate(keys, key, counters, width, rows).orderBy(F.desc("estimate"), key).limit(k).withColumn("place", F.row_number().over(W.orderBy(F.desc("estimate"), key)))
