"""Connected components of a link table, in distributed rounds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import staged


def _mark(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count(F.lit(1)), F.sum(F.pmod(F.xxhash64("u", "v"), F.lit(1 << 40)))).first())


def _least(edges: DataFrame) -> DataFrame:
    return staged(edges.groupBy("u").agg(F.min("v").alias("m")), "least").withColumnRenamed("u", "_u")


def components(links: DataFrame, a: str, b: str) -> DataFrame:
    """(id, component): the smallest id each linked id can reach. Ids without links are not listed.

    Alternates two star steps: every node hands its larger neighbours its least one, then its smaller ones; chains
    halve, stars stand still. Hubs are joins on the node, which Spark splits when skewed, never one group in a task.
    """
    edges = staged(links.where(F.col(a) != F.col(b)).select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).distinct(), "edges")
    before = _mark(edges)
    while True:
        both = staged(edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v"))), "both")
        large = both.where("v > u").join(_least(both), F.col("u") == F.col("_u")).select(F.col("v").alias("u"), F.least("m", "u").alias("v"))
        large = staged(large.where("u != v").distinct(), "large")
        least = _least(large)
        small = large.join(least, F.col("u") == F.col("_u"))
        small = small.where("v != m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(least.select(F.col("_u").alias("u"), F.col("m").alias("v")))
        edges = staged(small.distinct(), "edges")
        after = _mark(edges)
        if after == before:
            break
        before = after
    return edges.select(F.col("u").alias("id"), F.col("v").alias("component")).unionByName(edges.select(F.col("v").alias("id"), F.col("v").alias("component")).distinct())
