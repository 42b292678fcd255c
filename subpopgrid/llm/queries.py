"""The queries of the training-data operators, and their SQL where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import chat, decontaminate, language, packing, quality, resharding, set_join, token_files, url_filter, wrappers
from .common import prepare, staged


def _prepared(query: Callable[[SparkSession, str], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        prepare(spark)
        return query(spark, sf_dir)

    return run


def pages_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The language of every page from its main text, markup language, address and host, each a witness of its own.

    The model is fitted on ``documents``; no label of a judged page takes part.
    """
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").withColumn("markup", language.markup_language(F.col("html")))
    texts = staged(wrappers.extract(pages, keep=("markup",)), "page-texts")
    model = language.fit(spark.read.parquet(f"{sf_dir}/documents.parquet"), F.col("lang"))
    host = url_filter.host_and_path(F.col("url"))[0]
    return language.identify(texts, model, id_col="page_id", declared=F.col("markup"), suffix=language.address_language(F.col("url")), host=F.nullif(host, F.lit("")))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    own = {
        "op1_decontamination": decontaminate.op1_decontamination,
        "op2_html_text": wrappers.op2_html_text,
        "op5_ngram_jaccard": set_join.op5_ngram_jaccard,
        "op4_url_filter": url_filter.op4_url_filter,
        "op6_quality_rules": quality.op6_quality_rules,
        "op8_preference_format": chat.op8_preference_format,
        "op9_language_id": language.op9_language_id,
        "op3_flow_resharding": resharding.op3_flow_resharding,
        "op7_token_files": token_files.op7_token_files,
        "op10_best_fit": packing.op10_best_fit,
    }
    more = {"preference_other_replies": chat.preference_other_replies, "pages_language": pages_language, "quality_two_sided": quality.quality_two_sided}
    return {k: _prepared(f) for k, f in (own | more).items()}


def oracle_sql() -> dict[str, str]:
    return {"op5_ngram_jaccard": set_join.op5_sql(), "op6_quality_rules": quality.op6_sql(), "quality_two_sided": quality.two_sided_sql(), "op8_preference_format": chat.op8_sql(), "preference_other_replies": chat.other_replies_sql()}
