"""Periodic estimation over streams: windows of grids, late records, and a store that batches merge into."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import canonical_key
from ..operators import universal as U
from ..schema import GridConfig, WorkloadSpec

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, path: str) -> DataFrame:
    """``events`` as a stream of files; the time becomes a zoned timestamp, which watermarks ask for."""
    folder, _, name = path.rpartition("/")
    stream = spark.readStream.schema(EVENTS).option("pathGlobFilter", name).parquet(folder)
    return stream.withColumn("ts", F.expr("timestamp_micros(timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', ts))"))


def utc_text(column: str) -> Column:
    """The wall clock in UTC as text, to the second, whatever the session's time zone."""
    return F.expr(f"substring(CAST(timestampadd(MICROSECOND, unix_micros({column}), TIMESTAMP_NTZ'1970-01-01 00:00:00') AS STRING), 1, 19)")


def window_estimates(pairs: DataFrame, cfg: GridConfig) -> DataFrame:
    """(win, subpop_key, found_rows, l1, l2, card): every window has a grid of its own, its heaps cut to k (tracked values)."""
    from pyspark.sql import Window as W

    line = W.partitionBy("win", *U.CELL, "layer").orderBy(F.desc("f"), "subpop_key", "m")
    cut = lambda rows: rows.withColumn("_n", F.row_number().over(line)).where(F.col("_n") <= cfg.k).drop("_n")
    heaps = cut(window_cells(pairs, cfg.but(layer_mode="deepest")).select("win", *U.CELL, "layer", "subpop_key", "m", "f", "depth"))
    nested = cut(heaps.drop("layer").withColumn("layer", F.explode(F.sequence(F.lit(0), F.col("depth"))))).withColumn("_w", U.entry_weight(cfg))
    gs = {"l1": F.col("f"), "l2": F.col("f") * F.col("f"), "card": F.lit(1).cast("long")}
    rows = nested.groupBy("win", "subpop_key", "grid_row").agg(*(F.sum(F.col("_w") * g).alias(n) for n, g in gs.items()))
    missing = F.expr(f"{cfg.r} - count(1)").cast("int")
    med = [F.sort_array(F.concat(F.collect_list(F.col(n).cast("double")), F.array_repeat(F.lit(0.0), missing)))[cfg.r // 2].alias(n) for n in gs]
    return rows.groupBy("win", "subpop_key").agg(F.count(F.lit(1)).cast("int").alias("found_rows"), *med)


def drain(df: DataFrame, mode: str, folder: str) -> DataFrame:
    """Run the query over all there is and return its output table; the result outlives the query."""
    spark = df.sparkSession
    if mode == "append":
        q = df.writeStream.format("parquet").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(df.schema).parquet(f"{folder}/out")

    def keep(batch: DataFrame, n: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/out")

    q = df.writeStream.outputMode("complete").foreachBatch(keep).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{folder}/out")


def window_pairs(stream: DataFrame, spec: WorkloadSpec, window: Column) -> DataFrame:
    """(win, gid, subpop_key, m, f): pair counts of every window, fanned out by an explode (streams have no grouping sets)."""
    gids = F.array(*(F.lit(spec.gid(c)).cast("long") for c in spec.sets()))
    rows = stream.select(window.alias("win"), *spec.dims, F.col(spec.metric).cast("long").alias("m"), F.explode(gids).alias("gid"))
    keyed = rows.withColumn("subpop_key", canonical_key(spec))
    return keyed.groupBy("win", "gid", "subpop_key", "m").agg(F.count(F.lit(1)).alias("f"))


def window_cells(pairs: DataFrame, cfg: GridConfig) -> DataFrame:
    """Heap candidates of every window's grid: the window is part of the key, so cells of different windows never mix."""
    from ..functions.hashing import add_cells, add_fields

    cells = add_fields(add_cells(pairs, cfg), cfg)
    return U.layered(cells, cfg)


def merge_into_store(stream: DataFrame, spec: WorkloadSpec, seconds: int, folder: str) -> DataFrame:
    """Each micro-batch writes its own pair counts below its number (a retry overwrites them); reading merges.

    Counts add, so a late record merges into its window wherever it arrives.
    """

    def save(batch: DataFrame, n: int) -> None:
        win = F.window("ts", f"{seconds} seconds")["start"]
        window_pairs(batch, spec, win).write.mode("overwrite").parquet(f"{folder}/store/batch={n}")

    q = stream.writeStream.foreachBatch(save).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    spark = stream.sparkSession
    stored = spark.read.schema("win timestamp, gid long, subpop_key string, m long, f long").parquet(f"{folder}/store/batch=*")
    return stored.groupBy("win", "gid", "subpop_key", "m").agg(F.sum("f").alias("f"))
