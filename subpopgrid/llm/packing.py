"""Best-fit packing of tokenized documents into sequences of fixed capacity, in bulk-synchronous sweeps.

1. Texts become pieces: a document of more ids than the capacity is cut so that only its first piece is short.
2. Pieces shorter than the capacity are range-sorted by length; each gets its rank among equal lengths
   (local positions plus one total a task and length, so a length that a third of all pieces share is no hot task).
3. Equal lengths, and equal gaps, are interchangeable. So documents and open gaps are held as runs: (length, ranks
   from..to) and (gap, sequences from..to). A superstep takes the runs of the longest unplaced length
   and sweeps the gap runs for the successor (the smallest gap that holds it); where many documents want the same
   gaps, ranks decide: the first ranks get the first gaps, the rest sweep on to the next larger gap, and to
   new sequences at last. Then the gaps are updated and the next sweep begins. The runs are bounded by the
   capacity, never by the number of documents.
4. Every piece finds its place from its (length, rank) in the resulting table of runs, in parallel.

The result equals that of sequential best-fit decreasing. Ids of sequences are dense from 0.

Defined cases: null or empty text is the end id alone (a piece of length 1); repeated rows are packed each; an empty
table gives an empty table; extra columns are ignored.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left, insort

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import BROADCAST_LIMIT, extended, merged_scan, staged, with_prefix_sums
from .tokens import encoder

PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


def pieces(docs: DataFrame, capacity: int, vocabulary: str = "byte_bpe_50k.json", spaced: bool = True, end_id: int = 2, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """The pieces of every document with the crc32 (and, if asked, the bytes) of their ids."""

    def cut(batches):
        import pyarrow as pa

        enc = encoder(vocabulary, spaced)
        for b in batches:
            out: tuple[list, ...] = ([], [], [], [], [], [])
            docs_ = b.column("doc_id").to_pylist()
            for lo, hi, flat, counts in enc.slices(b.column("text"), end_id):
                data, ends = memoryview(np.ascontiguousarray(flat)).cast("B"), np.cumsum(counts)
                for doc, n, end in zip(docs_[lo:hi], counts.tolist(), ends.tolist(), strict=True):
                    ids, at = data[4 * (end - n) : 4 * end], 0
                    for k in range(-(-n // capacity)):
                        size = ((n - 1) % capacity + 1) if k == 0 else capacity
                        part = ids[4 * at : 4 * (at + size)]
                        for column, v in zip(out, (doc, k, at, size, zlib.crc32(part), bytes(part) if with_ids else None), strict=True):
                            column.append(v)
                        at += size
            kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.binary())
            names = ["doc_id", "piece", "start", "length", "ids_crc32", "ids"]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, kinds, strict=True)][: 5 + with_ids], names=names[: 5 + with_ids])

    texts = docs if with_ids else merged_scan(docs)
    texts = texts.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    return texts.mapInArrow(cut, PIECES + ", ids binary" * with_ids)


def sweep(counts: dict[int, int], capacity: int) -> tuple[list[tuple[int, int, int, int]], int]:
    """Places runs of documents into runs of gaps; (length, first rank, first sequence, offset) runs and the number of sequences.

    A run covers the ranks up to the next run of its length, one sequence each.
    """
    gaps: dict[int, list[tuple[int, int]]] = {}  # gap -> runs of (first sequence, count)
    order: list[int] = []  # gaps that have runs, ascending
    placed, opened = [], 0

    def put(gap: int, run: tuple[int, int]) -> None:
        if gap:
            if gap not in gaps:
                gaps[gap] = []
                insort(order, gap)
            gaps[gap].append(run)

    for length in sorted(counts, reverse=True):
        rank, left = 0, counts[length]
        while left:
            at = bisect_left(order, length)
            if at == len(order):  # no gap holds it: a new sequence takes what it can before the next is opened
                each = capacity // length
                full, rest = divmod(left, each)
                for first, n, times in ((opened, full, each), (opened + full, 1, rest)):
                    if n and times:
                        for k in range(times):
                            placed.append((length, rank, first, k * length))
                            rank += n
                        put(capacity - times * length, (first, n))
                opened += full + (rest > 0)
                break
            gap = order[at]
            first, n = gaps[gap].pop()
            if not gaps[gap]:
                del gaps[gap]
                order.pop(at)
            took = min(n, left)
            placed.append((length, rank, first, capacity - gap))
            if n > took:
                put(gap, (first + took, n - took))
            put(gap - length, (first, took))
            rank, left = rank + took, left - took
    return placed, opened


def place_by_join(short: DataFrame, runs: list[tuple[int, int, int, int]], names: list[str]) -> DataFrame:
    """As ``pack`` places them, with the runs as a table joined by length and block of ranks."""
    spark, width = short.sparkSession, 1 << 16
    ends = {}
    rows = []
    for length, rank, first, offset in sorted(runs, reverse=True):
        rows.append((length, rank, ends.get(length, 1 << 62), first, offset))
        ends[length] = rank
    last = {r["length"]: r["m"] for r in short.groupBy("length").agg(F.max("_rank").alias("m")).collect()}  # at most a row a length
    cut = [(n, a, b, first, offset, k) for n, a, b, first, offset in rows for k in range(a // width, min(b - 1, last[n]) // width + 1)]
    table = spark.createDataFrame(cut, "_l long, _a long, _b long, _first long, _off long, _k long")
    found = short.join(table, (F.col("length") == F.col("_l")) & (F.expr(f"_rank div {width}") == F.col("_k"))).where("_rank >= _a AND _rank < _b")
    return found.select(*names, (F.col("_first") + F.col("_rank") - F.col("_a")).alias("sequence_id"), F.col("_off").alias("offset"))


def pack(parts: DataFrame, capacity: int) -> DataFrame:
    """Add ``sequence_id`` and ``offset`` to rows that have ``length`` (1 to capacity) and stand for one piece each."""
    spark = parts.sparkSession
    parts = staged(parts, "pieces")
    short = with_prefix_sums(parts.withColumn("_one", F.lit(1).cast("long")), "length", ["doc_id", "piece"], "_one", "_rank").drop("_one")
    counts = {r["length"]: r["count"] for r in parts.groupBy("length").count().collect()}  # at most a row a length
    runs, opened = sweep(counts, capacity)
    by_length: dict[int, list] = {}
    for length, rank, first, offset in runs:
        by_length.setdefault(length, []).append((rank, first, offset))
    table = {k: np.array(sorted(v), dtype=np.int64).T for k, v in by_length.items()}
    if sum(t.nbytes for t in table.values()) > BROADCAST_LIMIT:  # about 24 bytes a run: capacities beyond a hundred thousand
        return place_by_join(short, runs, parts.columns)
    held, names = spark.sparkContext.broadcast(table), parts.columns
    schema = extended(parts.schema, sequence_id=T.LongType(), offset=T.LongType())

    def place(batches):
        import pyarrow as pa

        for b in batches:
            length, rank = (b.column(c).to_numpy(zero_copy_only=False) for c in ("length", "_rank"))
            seq, off = np.empty(len(rank), np.int64), np.empty(len(rank), np.int64)
            for k in np.unique(length):
                at = np.flatnonzero(length == k)
                ranks, first, offset = held.value[int(k)]
                i = np.searchsorted(ranks, rank[at], side="right") - 1
                seq[at], off[at] = first[i] + rank[at] - ranks[i], offset[i]
            kept = [b.column(c) for c in names]
            yield pa.RecordBatch.from_arrays([*kept, pa.array(seq), pa.array(off)], names=[*names, "sequence_id", "offset"])

    return short.mapInArrow(place, schema)


CAPACITY = 1024


def op10_best_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents packed into sequences of at most 1024 ids."""
    return pack(pieces(spark.read.parquet(f"{sf_dir}/documents.parquet"), CAPACITY), CAPACITY)
