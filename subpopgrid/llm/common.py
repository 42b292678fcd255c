"""Shared folder, staged tables and distributed ranks for the training-data operators."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from contextvars import ContextVar

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..session import on_workers

# Broadcast variables hold at most this many bytes; larger inputs are joined instead.
BROADCAST_LIMIT = 8 << 20


#: Rows and bytes of an Arrow batch: texts are long, and a batch is held by the executor and its worker at once.
BATCH_ROWS, BATCH_BYTES = 1_000, 4 << 20

_HOLDS: dict[str, Callable[[], None]] = {}
_LEAN: list[bool] = []


def prepare(spark: SparkSession) -> None:
    """Module path of the workers, and batches that suit long texts."""
    on_workers(spark)
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))


def hold(owner: str, clear: Callable[[], None]) -> None:
    """In a worker: ``owner`` has caches, which ``clear`` drops."""
    _HOLDS[owner] = clear


def lean() -> None:
    """In a worker: large blocks that are freed go back to the system at once, so the batch at hand bounds the process."""
    if not _LEAN:
        import ctypes

        import pyarrow as pa

        _LEAN.append(True)
        pa.set_memory_pool(pa.system_memory_pool())
        try:
            libc = ctypes.CDLL("libc.so.6")
            libc.mallopt(-3, 1 << 20)  # blocks from this size on are mapped
            libc.mallopt(-1, 1 << 20)  # so much free memory may stay at the heap's end
        except (OSError, AttributeError):  # another C library
            pass


def take_over(owner: str) -> None:
    """In a worker, as a task begins: caches that other operators left in this process give way."""
    lean()
    others = [k for k in _HOLDS if k != owner]
    for k in others:
        _HOLDS.pop(k)()
    if others:
        import ctypes
        import gc

        import pyarrow as pa

        gc.collect()
        pa.default_memory_pool().release_unused()
        try:
            ctypes.CDLL("libc.so.6").malloc_trim(0)
        except OSError:  # another C library
            pass


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir`` of the session.

    Only where the session names none (tests on one machine) a temporary folder is made and set.
    """
    path = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not path:
        own = tempfile.mkdtemp(prefix="subpopgrid-")
        atexit.register(shutil.rmtree, own, ignore_errors=True)
        path = f"file://{own}"
        spark.conf.set("spark.checkpoint.dir", path)
    return path


_MADE: ContextVar[list[str] | None] = ContextVar("made", default=None)


def new_path(spark: SparkSession, name: str) -> str:
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    if _MADE.get() is not None:
        _MADE.get().append(path)
    return path


@contextmanager
def noted() -> Iterator[list[str]]:
    """The paths of all tables that are staged within, in order."""
    made: list[str] = []
    token = _MADE.set(made)
    try:
        yield made
    finally:
        _MADE.reset(token)


def discard(spark: SparkSession, paths: list[str]) -> None:
    """Delete staged tables. Nothing may be computed from them any more, nor from lost parts of what was."""
    for p in paths:
        at = spark._jvm.org.apache.hadoop.fs.Path(p)
        at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def staged(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` as Parquet to the shared folder and read it back: cuts the lineage, survives lost executors."""
    spark = df.sparkSession
    path = new_path(spark, name)
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def merged_scan(df: DataFrame, by: int = 8) -> DataFrame:
    """A scan in fewer, longer tasks, for steps that make a narrow row of a wide one: else they leave many tiny files.

    ``df`` is a table as read, as its plan is asked for its tasks. Tasks stream, so their memory does not grow; there
    are at least two tasks a core.
    """
    now = df.rdd.getNumPartitions()
    return df.coalesce(max(2 * df.sparkSession.sparkContext.defaultParallelism, now // by)) if now > 1 else df


def extended(schema: T.StructType, **fields: T.DataType) -> T.StructType:
    return T.StructType([*schema.fields, *(T.StructField(k, v) for k, v in fields.items())])


def exclusive_sums(groups: np.ndarray, weights: np.ndarray, carry: tuple[int | None, int]) -> tuple[np.ndarray, tuple[int | None, int]]:
    """Running sums of the weights before each row, restarted where the group changes.

    Rows arrive sorted by group; ``carry`` is (group, sum) at the end of the rows seen before.
    """
    if not len(groups):
        return weights.astype(np.int64), carry
    first = np.r_[True, groups[1:] != groups[:-1]]
    run = np.cumsum(first) - 1
    before = np.cumsum(weights) - weights
    before = before - before[first][run]
    if carry[0] is not None and groups[0] == carry[0]:
        before[run == 0] += carry[1]
    return before, (int(groups[-1]), int(before[-1] + weights[-1]))


def with_prefix_sums(df: DataFrame, group: str, order: list, weight: str, out: str) -> DataFrame:
    """Add ``out``: the sum of ``weight`` over the rows before this one in its group, in ``order``.

    Range-sorts by (group, order), so a group that holds a third of all rows spreads over many tasks. Each task
    sums locally; one row a task and group goes through the driver (groups must be few: shards or lengths).
    ``group`` and ``weight`` must be BIGINT without nulls.
    """
    spark = df.sparkSession
    cols = [F.col(group), *order]
    schema = extended(df.schema, _part=T.IntegerType(), _before=T.LongType())

    def local(batches):
        import pyarrow as pa
        from pyspark import TaskContext

        part, carry = TaskContext.get().partitionId(), (None, 0)
        for b in batches:
            g = b.column(group).to_numpy(zero_copy_only=False)
            w = b.column(weight).to_numpy(zero_copy_only=False)
            before, carry = exclusive_sums(g, w, carry)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(np.full(len(g), part, np.int32)), pa.array(before, pa.int64())], names=[*b.schema.names, "_part", "_before"])

    local_sums = staged(df.repartitionByRange(*cols).sortWithinPartitions(*cols).mapInArrow(local, schema), "prefix")
    totals = local_sums.groupBy("_part", group).agg(F.sum(weight).alias("t")).collect()
    bases, running = [], {}
    for r in sorted(totals, key=lambda r: (r[group], r["_part"])):
        bases.append((r["_part"], r[group], running.get(r[group], 0)))
        running[r[group]] = running.get(r[group], 0) + r["t"]
    base = spark.createDataFrame(bases, f"_part int, `{group}` long, _base long")
    return local_sums.join(F.broadcast(base), ["_part", group]).withColumn(out, F.col("_before") + F.col("_base")).select(*df.columns, out)


def fresh(name: str, taken: list[str]) -> str:
    """``name``, or with underscores added until no column is called so (Spark ignores case)."""
    used = {c.lower() for c in taken}
    while name.lower() in used:
        name += "_"
    return name


def with_row_ids(docs: DataFrame, id_col: str = "doc_id") -> tuple[DataFrame, str]:
    """The rows and a column that tells them apart: ``id_col`` if it does, else a stored row number."""
    r = docs.agg(F.count(F.lit(1)), F.count_distinct(id_col)).first()
    if r[0] == r[1]:
        return docs, id_col
    key = fresh("_row", docs.columns)
    return staged(docs.withColumn(key, F.monotonically_increasing_id()), "rows"), key


def without(rows: DataFrame, key: str, gone: DataFrame, columns: list[str]) -> DataFrame:
    """``columns`` of the rows whose ``key`` is not in the one column of ``gone``."""
    other = fresh("_gone", rows.columns)
    return rows.join(gone.toDF(other), F.col(f"`{key}`") == F.col(other), "left_anti").select(*(F.col(f"`{c}`") for c in columns))
