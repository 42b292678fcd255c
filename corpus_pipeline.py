"""The corpus pipeline: five stages over ``documents``, each written as Parquet and read again for the next.

Language ID, quality rules and decontamination drop what they reject; of each class of near duplicates the document
with the smallest id stays; the rest is packed into training sequences.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subpopgrid.llm import decontaminate, language, packing, quality, set_join
from subpopgrid.llm.common import discard, noted, prepare, staged, with_row_ids, without

#: Near duplicates: word n-grams and the least similarity (a fraction).
NEAR_WORDS, NEAR_NUM, NEAR_DEN = 5, 80, 100


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in a known language; ``lang`` is the declared one, the source stands for the host."""
    prepare(spark)
    return language.accepted(docs, language.fit(docs, F.col("lang")), declared=F.col("lang"), host=F.col("source"))


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    prepare(spark)
    return quality.passed(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class stays: the first by id. Rows without a usable id are told apart by row numbers."""
    prepare(spark)
    rows, key = with_row_ids(docs)
    found = set_join.classes(rows, NEAR_WORDS, NEAR_NUM, NEAR_DEN, id_col=key)
    return without(rows, key, staged(found.where("doc_id != component_id").select("doc_id"), "copies"), docs.columns)


def benchmark_decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    prepare(spark)
    rows, key = with_row_ids(docs)
    found = decontaminate.contaminated(rows, spark.read.parquet(f"{sf_dir}/benchmark.parquet"), id_col=key)
    return without(rows, key, staged(found.select("doc_id").distinct(), "contaminated"), docs.columns)


def best_fit_packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    prepare(spark)
    return packing.pack(packing.pieces(docs, packing.CAPACITY), packing.CAPACITY)


STAGES = [
    ("language_id", language_id),
    ("quality_rules", quality_rules),
    ("near_duplicates", near_duplicates),
    ("benchmark_decontamination", benchmark_decontamination),
    ("best_fit_packing", best_fit_packing),
]

#: Trained, iterative and tokenizing stages: SQL can't express them; the tests hold the run against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last stage's table. A stage's own tables, and its input if a stage wrote it, go once its output is written."""
    docs, done = spark.read.parquet(f"{sf_dir}/documents.parquet"), []
    for name, stage in STAGES:
        with noted() as made:
            docs = staged(stage(spark, docs, sf_dir), name)
        discard(spark, done + made[:-1])
        done = made[-1:]
    return docs
