"""Token-id files: ORC stripes of run-length encoded ids with row indexes and Bloom filters on document ids.

Layout of a token table (a folder of ORC files, one a range of document ids, ascending):
``doc_id`` BIGINT, ``part`` INT (the file's number), ``start_in_part`` BIGINT (ids before the row in its file),
``n_tokens`` BIGINT, ``ids`` ARRAY<INT>. ORC encodes the integers by run-length encoding version 2, keeps minimum
and maximum of every row group of ``row_group`` rows, and a Bloom filter on ``doc_id``; so a range or point
lookup on ids prunes stripes by their metadata, and readers split files at stripes.

Defined cases: null or empty text gives the end id alone; null doc_id sorts first; equal doc_ids keep any
order among themselves; an empty table gives an empty table; extra columns are ignored.
"""

from __future__ import annotations

import zlib

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import BROADCAST_LIMIT, new_path
from .tokens import encoder

SCHEMA = "doc_id long, part int, start_in_part long, n_tokens long, ids array<int>"


def write_tokens(docs: DataFrame, path: str, vocabulary: str = "word_bpe_49k.json", spaced: bool = False, end_id: int = 2, id_col: str = "doc_id", text_col: str = "text", row_group: int = 2_000) -> None:
    """Encode the whole texts and write them as a token table in ascending order of ids."""

    def encode(batches):
        import pyarrow as pa
        from pyspark import TaskContext

        enc, part, start = encoder(vocabulary, spaced), TaskContext.get().partitionId(), 0
        for b in batches:
            for lo, hi, flat, n in enc.slices(b.column("text"), end_id):
                before = start + np.cumsum(n) - n
                start += len(flat)
                ids = pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum(n)], pa.int32()), pa.array(flat.view("<i4")))
                yield pa.RecordBatch.from_arrays([b.column("doc_id").slice(lo, hi - lo), pa.array(np.full(hi - lo, part, np.int32)), pa.array(before), pa.array(n), ids], names=["doc_id", "part", "start_in_part", "n_tokens", "ids"])

    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    rows = texts.repartitionByRange("doc_id").sortWithinPartitions("doc_id").mapInArrow(encode, SCHEMA)
    rows.write.option("compression", "zstd").option("orc.bloom.filter.columns", "doc_id").option("orc.row.index.stride", str(row_group)).orc(path)


def read_tokens(spark: SparkSession, path: str) -> DataFrame:
    """The token table with ``start``: all ids before the row. File totals come from two narrow columns."""
    table = spark.read.schema(SCHEMA).orc(path)
    totals = table.groupBy("part").agg(F.sum("n_tokens").alias("n")).orderBy("part")
    bases, at = [], 0
    for part, n in totals.toLocalIterator():  # a row a file
        bases.append((part, at))
        at += n
    base = spark.createDataFrame(bases, "part int, base long")
    base = F.broadcast(base) if 16 * len(bases) < BROADCAST_LIMIT else base
    return table.join(base, "part", "left").withColumn("start", F.col("start_in_part") + F.col("base")).drop("base")


def lookup(spark: SparkSession, path: str, doc_ids: list[int]) -> DataFrame:
    """Rows of the given documents; the filter reaches the ORC reader, which prunes by Bloom filter and statistics."""
    return spark.read.schema(SCHEMA).orc(path).where(F.col("doc_id").isin(doc_ids))


def digest(tokens: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens and the crc32 of the ids as little-endian unsigned 32-bit integers."""

    def crc(batches):
        import pyarrow as pa

        for b in batches:
            ids = b.column("ids")
            flat, at = ids.values.to_numpy(zero_copy_only=False).astype("<u4", copy=False), ids.offsets.to_numpy()
            out = [zlib.crc32(flat[i:j].tobytes()) for i, j in zip(at[:-1], at[1:], strict=True)]
            yield pa.RecordBatch.from_arrays([b.column(c) for c in ("doc_id", "start", "n_tokens")] + [pa.array(out, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    return tokens.select("doc_id", "start", "n_tokens", "ids").mapInArrow(crc, "doc_id long, start long, n_tokens long, ids_crc32 long")


def op7_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents through the ORC token table and back."""
    path = new_path(spark, "tokens")
    write_tokens(spark.read.parquet(f"{sf_dir}/documents.parquet"), path)
    return digest(read_tokens(spark, path))
