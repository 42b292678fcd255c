"""The corpus pipeline against brute force over the small documents table."""

from __future__ import annotations

from pathlib import Path

import pytest
from pyspark.sql import functions as F

from subpopgrid.llm import decontaminate
from tests.conftest import SF
from tests.llm.test_operators import ODD, brute_classes, brute_measure, docs_of, plain_smith_waterman, sequential_best_fit

corpus_pipeline = pytest.importorskip("corpus_pipeline")


def test_stages_and_columns(spark):
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["language_id", "quality_rules", "near_duplicates", "benchmark_decontamination", "best_fit_packing"]
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    for _, stage in corpus_pipeline.STAGES[:-1]:
        before, docs = docs, stage(spark, docs, SF)
        assert docs.columns == before.columns and docs.exceptAll(before).count() == 0


def test_run_equals_brute_force(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    items = spark.read.parquet(f"{SF}/benchmark.parquet").collect()
    kept = corpus_pipeline.quality_rules(spark, corpus_pipeline.language_id(spark, docs, SF), SF).orderBy("doc_id").collect()
    assert all((n := brute_measure(r["text"]))[0] >= 50 and 2 * n[4] <= n[0] for r in kept)
    near = brute_classes([r["text"] for r in kept], corpus_pipeline.NEAR_WORDS, corpus_pipeline.NEAR_NUM, corpus_pipeline.NEAR_DEN)
    firsts = [r for i, r in enumerate(kept) if near[i][1] == i]

    def leaks(text):
        words = decontaminate.words_of(text)
        grams = set(zip(words, words[1:], words[2:], strict=False))
        for r in items:
            item = decontaminate.words_of(r["text"])
            if grams & set(zip(item, item[1:], item[2:], strict=False)):
                if decontaminate.matches(plain_smith_waterman(item, words), len(item)):
                    return True
        return False

    left = [r["doc_id"] for r in firsts if not leaks(r["text"])]
    packed = corpus_pipeline.run(spark, SF).toPandas()
    assert sorted(packed.doc_id.unique()) == sorted(left)
    assert packed.sequence_id.nunique() == sequential_best_fit(packed.length.tolist(), 1024)


def test_run_leaves_only_its_result(spark):
    folder = Path(spark.conf.get("spark.checkpoint.dir").removeprefix("file://"))
    before = set(folder.iterdir())
    rows = corpus_pipeline.run(spark, SF).count()
    left = {p for p in set(folder.iterdir()) - before if p.is_dir()}
    assert rows > 0 and [p.name.rsplit("-", 1)[0] for p in left] == ["best_fit_packing"]


def test_near_duplicates_without_usable_ids(spark):
    rows = [(None, "a b c d e f g"), (3, "a b c d e f g"), (3, "a b c d e f g"), (4, "p q r s t u v"), (None, None)]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("lang", F.lit("en"))
    assert sorted(r["text"] or "" for r in corpus_pipeline.near_duplicates(spark, df, SF).collect()) == ["", "a b c d e f g", "p q r s t u v"]


def test_odd_and_empty_documents(spark):
    df = docs_of(spark, ODD)
    empty = df.limit(0)
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, empty, SF).count() == 0
        stage(spark, df, SF).count()
    assert corpus_pipeline.benchmark_decontamination(spark, df, SF).count() == len(ODD)


def test_columns_named_like_the_stages_own(spark):
    rows = [(1, "a b c d e f g", "en", "s"), (1, "a b c d e f g", "en", "s"), (2, "p q r s t u v", "en", "s")]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string").withColumn("_row", F.lit("kept")).withColumn("_gone", F.lit("too")).withColumn("_c0", F.lit("and this"))
    for stage in (corpus_pipeline.near_duplicates, corpus_pipeline.benchmark_decontamination):
        got = stage(spark, df, SF).toPandas()
        assert list(got.columns) == df.columns and set(got._row) == {"kept"} and set(got._gone) == {"too"}
    assert corpus_pipeline.language_id(spark, df, SF).columns == df.columns == corpus_pipeline.quality_rules(spark, df, SF).columns
