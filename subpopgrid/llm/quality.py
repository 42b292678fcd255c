"""Quality rules whose thresholds adapt to each language and source, from mergeable quantile sketches.

A sketch is a table of counts in buckets of known width (exact below 8, then eight buckets a power of two, so a
value is known within an eighth); sketches of tasks, sources and languages merge by adding counts, which the grouped
aggregation does. Limits come from a group's median and quartiles; a source with under ``SUPPORT`` documents takes
those of its language, a language with too few those of the whole table. ``two_sided`` limits have no floors: the
quartiles decide in both directions, within half and twice the level above, so that a source that is mostly junk can't
loosen its own limit far. All arithmetic is in integers, so any engine
and any partitioning give the same verdicts.

Defined cases: null text counts as empty (no words, base rule fails); null language or source is a group of its own;
repeated rows are judged each; an empty table gives an empty table; extra columns are ignored.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import merged_scan, staged, take_over

BLANKS, SYMBOLS = " \t\n\v\f\r", "#*$%&|<>"
BASE = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
#: Metric -> (expression in per mille or tenths, least upper limit). A limit is never below the least one.
METRICS = {
    "symbols": ("1000 * n_symbols div n_words", 100),
    "dup_lines": ("1000 * n_dup_lines div n_lines", 300),
    "repeats": ("1000 * n_repeat_words div n_words", 400),
    "word_length": ("10 * word_chars div n_words", 120),
}
SUPPORT, SPREAD, MIN_WORDS = 30, 4, 50
#: Least spread of a metric where limits are two-sided: half of a group may share one value.
STEP = {"symbols": 5, "dup_lines": 25, "repeats": 25, "word_length": 5}


def measure(text: str | None) -> tuple[int, int, int, int, int, int]:
    """The base counts of one text, then its number of lines that have a word."""
    if not text:
        return 0, 0, 0, 0, 0, 0
    words = text.encode().split()  # of bytes: splits at exactly these six blanks
    n = len(words)
    lines = [x for x in text.split("\n") if x.strip(BLANKS)]
    windows = list(zip(words, words[1:], words[2:], strict=False))
    repeated = 0
    if len(set(windows)) < len(windows):
        times, end = Counter(windows), 0
        for i, w in enumerate(windows):
            if times[w] > 1:
                repeated += i + 3 - max(i, end)
                end = i + 3
    return n, len(text) - sum(map(text.count, BLANKS)), sum(map(text.count, SYMBOLS)), len(lines) - len(set(lines)), repeated, len(lines)


def base_counts(docs: DataFrame, text_col: str = "text", keep: tuple[str, ...] = ("doc_id", "lang", "source")) -> DataFrame:
    """``keep`` columns with the base counts of every whole text and ``n_lines``."""

    def count(batches):
        import pyarrow as pa

        take_over("quality")
        for b in batches:
            rows = [measure(t.as_py()) for t in b.column(text_col)]
            cols = list(zip(*rows, strict=True)) if rows else [()] * 6
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in keep), *(pa.array(c, pa.int64()) for c in cols)], names=[*keep, *BASE, "n_lines"])

    kinds = dict(docs.dtypes)
    return docs.select(*dict.fromkeys([*keep, text_col])).mapInArrow(count, ", ".join([*(f"`{c}` {kinds[c]}" for c in keep), *(f"{c} long" for c in (*BASE, "n_lines"))]))


def bucket(value: str) -> str:
    """SQL: the sketch bucket of a count, named by its lowest value. Runs in Spark and DuckDB alike."""
    high = f"length(bin({value})) - 4"
    return f"CASE WHEN {value} < 8 THEN {value} ELSE ({value} >> CAST({high} AS INT)) << CAST({high} AS INT) END"


def sketches(counts: DataFrame) -> DataFrame:
    """(lang, source, metric, bucket, n): one mergeable sketch a group and metric, of documents that have words."""
    values = F.array(*(F.struct(F.lit(k).alias("metric"), F.expr(e).cast("long").alias("v")) for k, (e, _) in METRICS.items()))
    rows = counts.where("n_words > 0").select("lang", "source", F.explode(values).alias("x")).select("lang", "source", "x.metric", F.expr(bucket("x.v")).alias("bucket"))
    return rows.groupBy("lang", "source", "metric", "bucket").agg(F.count(F.lit(1)).alias("n"))


def quartiles(sketch: DataFrame) -> DataFrame:
    """(level, lang, source, metric, docs, q50, q75) at the levels source (2), language (1), all (0)."""
    key = ("level", "lang", "source")
    none = F.lit(None).cast("string")
    group = lambda level, lang, source: F.struct(F.lit(level).alias("level"), lang.alias("lang"), source.alias("source"))
    levels = F.explode(F.array(group(2, F.col("lang"), F.col("source")), group(1, F.col("lang"), none), group(0, none, none))).alias("g")
    merged = sketch.select(levels, "metric", "bucket", "n").groupBy("g.level", "g.lang", "g.source", "metric", "bucket").agg(F.sum("n").alias("n"))
    line = W.partitionBy(*key, "metric").orderBy("bucket")
    ranked = merged.withColumn("upto", F.sum("n").over(line)).withColumn("docs", F.sum("n").over(W.partitionBy(*key, "metric")))
    return ranked.groupBy(*key, "metric").agg(F.max("docs").alias("docs"), F.min(F.expr("CASE WHEN 2 * upto >= docs THEN bucket END")).alias("q50"), F.min(F.expr("CASE WHEN 4 * upto >= 3 * docs THEN bucket END")).alias("q75"))


def _tops(quartile: DataFrame, top: dict[str, Column]) -> DataFrame:
    return quartile.groupBy("level", "lang", "source").agg(F.max("docs").alias("docs"), *(F.max(F.when(F.col("metric") == k, v)).alias(f"max_{k}") for k, v in top.items()))


def limits(sketch: DataFrame) -> DataFrame:
    """(level, lang, source, docs, one column a metric): upper limits, none below its floor."""
    raw = F.col("q50") + SPREAD * (F.col("q75") - F.col("q50"))
    return _tops(quartiles(sketch), {k: F.greatest(raw, F.lit(least)) for k, (_, least) in METRICS.items()})


def two_sided(sketch: DataFrame) -> DataFrame:
    """As ``limits``, without floors; a language lies within half and twice the limit of all, a source of its language's."""
    raw = staged(_tops(quartiles(sketch), {k: F.col("q75") + SPREAD * F.greatest(F.col("q75") - F.col("q50"), F.lit(step)) for k, step in STEP.items()}), "quality-raw")
    whole = raw.where("level = 0")

    def within(rows: DataFrame, above: DataFrame, on: Column) -> DataFrame:
        tops = (F.greatest(F.least(f"r.max_{k}", 2 * F.col(f"u.max_{k}")), F.expr(f"u.max_{k} div 2")).alias(f"max_{k}") for k in STEP)
        return rows.alias("r").join(above.alias("u"), on).select("r.level", "r.lang", "r.source", "r.docs", *tops)

    by_lang = within(raw.where("level = 1"), whole, F.col("r.level") == F.col("u.level") + 1)
    by_source = within(raw.where("level = 2"), by_lang, F.col("r.lang").eqNullSafe(F.col("u.lang")))
    return whole.unionByName(by_lang).unionByName(by_source)


def judge(counts: DataFrame, bounds: DataFrame) -> DataFrame:
    """Add ``base_failed`` and ``kept``. ``bounds`` is a small staged table: Spark broadcasts it only below its size limit."""
    tops = [f"max_{k}" for k in METRICS]
    whole = bounds.where("level = 0").select(*(F.col(t).alias(f"all_{t}") for t in tops))
    by_lang = bounds.where(f"level = 1 AND docs >= {SUPPORT}").select(F.col("lang").alias("_l1"), *(F.col(t).alias(f"lang_{t}") for t in tops))
    by_source = bounds.where(f"level = 2 AND docs >= {SUPPORT}").select(F.col("lang").alias("_l2"), F.col("source").alias("_s2"), *tops)
    first = whole.take(1)  # one row
    joined = counts.join(by_lang, F.col("lang").eqNullSafe(F.col("_l1")), "left").join(by_source, F.col("lang").eqNullSafe(F.col("_l2")) & F.col("source").eqNullSafe(F.col("_s2")), "left")
    failed = F.expr(f"n_words < {MIN_WORDS} OR 100 * n_repeat_words > 50 * n_words")
    over = F.lit(False)
    for k, (e, _) in METRICS.items():
        top = F.coalesce(F.col(f"max_{k}"), F.col(f"lang_max_{k}"), F.lit(first[0][f"all_max_{k}"] if first else 0))
        over = over | (F.expr(e) > top)
    return joined.withColumn("base_failed", failed).withColumn("kept", ~F.col("base_failed") & ~F.coalesce(over, F.lit(False)))


def quality(docs: DataFrame, rule: Callable[[DataFrame], DataFrame] = limits) -> DataFrame:
    """doc_id, the base counts, base_failed and kept of every row; ``rule`` makes limits of sketches."""
    counts = staged(base_counts(merged_scan(docs)), "quality-counts")
    bounds = staged(rule(sketches(counts)), "quality-limits")
    return judge(counts, bounds).select("doc_id", *BASE, "base_failed", "kept")


def passed(docs: DataFrame) -> DataFrame:
    """The rows that are kept, all columns as they were. Rows are measured twice (limits, verdict) rather than shuffled."""
    names = docs.columns
    bounds = staged(limits(sketches(base_counts(merged_scan(docs)))), "quality-limits")
    carried = docs.select(*(F.col(f"`{c}`").alias(f"_c{i}") for i, c in enumerate(names)), F.col("lang"), F.col("source"))
    counts = base_counts(carried, f"_c{names.index('text')}", tuple(carried.columns))
    return judge(counts, bounds).where("kept").select(*(F.col(f"_c{i}").alias(c) for i, c in enumerate(names)))


def op6_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality(spark.read.parquet(f"{sf_dir}/documents.parquet"))


def quality_two_sided(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality(spark.read.parquet(f"{sf_dir}/documents.parquet"), two_sided)


def _floored_sql() -> str:
    tops = ", ".join(f"max(CASE WHEN metric = '{k}' THEN greatest(q50 + {SPREAD} * (q75 - q50), {least}) END) AS max_{k}" for k, (_, least) in METRICS.items())
    return f"""bounds AS (
  SELECT level, lang, source, max(docs) AS docs, {tops} FROM quantiles GROUP BY ALL
)"""


def _two_sided_sql() -> str:
    tops = ", ".join(f"max(CASE WHEN metric = '{k}' THEN q75 + {SPREAD} * greatest(q75 - q50, {step}) END) AS max_{k}" for k, step in STEP.items())
    within = ", ".join(f"greatest(least(r.max_{k}, 2 * u.max_{k}), u.max_{k} // 2) AS max_{k}" for k in STEP)
    return f"""raws AS (
  SELECT level, lang, source, max(docs) AS docs, {tops} FROM quantiles GROUP BY ALL
), langs AS (
  SELECT r.level, r.lang, r.source, r.docs, {within} FROM raws r JOIN raws u ON u.level = 0 WHERE r.level = 1
), sources AS (
  SELECT r.level, r.lang, r.source, r.docs, {within} FROM raws r JOIN langs u ON r.lang IS NOT DISTINCT FROM u.lang WHERE r.level = 2
), bounds AS (
  SELECT * FROM raws WHERE level = 0 UNION ALL SELECT * FROM langs UNION ALL SELECT * FROM sources
)"""


def two_sided_sql() -> str:
    return _verdict_sql(_two_sided_sql())


def op6_sql() -> str:
    """The same verdicts in DuckDB SQL."""
    return _verdict_sql(_floored_sql())


def _verdict_sql(bounds: str) -> str:
    word = r"[^\x20\x09-\x0D]+"
    values = " UNION ALL ".join(f"SELECT lang, source, '{k}' AS metric, {e.replace(' div ', ' // ')} AS v FROM counts WHERE n_words > 0" for k, (e, _) in METRICS.items())
    over = " OR ".join(f"{e.replace(' div ', ' // ')} > coalesce(s.max_{k}, l.max_{k}, a.max_{k})" for k, (e, _) in METRICS.items())
    return rf"""
WITH texts AS (
  SELECT row_number() OVER () AS rid, doc_id, lang, source, coalesce(text, '') AS text FROM documents
), split AS (
  SELECT *, regexp_extract_all(text, '{word}') AS words, list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '{word}')) AS lines FROM texts
), grams AS (
  SELECT rid, i, words[i] || ' ' || words[i + 1] || ' ' || words[i + 2] AS gram FROM (SELECT rid, words, unnest(range(1, len(words) - 1)) AS i FROM split)
), twice AS (
  SELECT rid, i FROM grams QUALIFY count(*) OVER (PARTITION BY rid, gram) > 1
), repeated AS (
  SELECT rid, count(DISTINCT i + k) AS n FROM twice, (SELECT unnest([0, 1, 2]) AS k) GROUP BY rid
), counts AS (
  SELECT rid, doc_id, lang, source, CAST(len(words) AS BIGINT) AS n_words,
    CAST(coalesce(list_sum(list_transform(words, lambda x: length(x))), 0) AS BIGINT) AS word_chars,
    CAST(length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
    CAST(len(lines) - len(list_distinct(lines)) AS BIGINT) AS n_dup_lines,
    CAST(coalesce(n, 0) AS BIGINT) AS n_repeat_words, CAST(len(lines) AS BIGINT) AS n_lines
  FROM split LEFT JOIN repeated USING (rid)
), vals AS ({values}
), sketch AS (
  SELECT lang, source, metric, {bucket("v")} AS bucket, count(*) AS n FROM vals GROUP BY ALL
), merged AS (
  SELECT 2 AS level, lang, source, metric, bucket, sum(n) AS n FROM sketch GROUP BY ALL
  UNION ALL SELECT 1, lang, NULL, metric, bucket, sum(n) FROM sketch GROUP BY lang, metric, bucket
  UNION ALL SELECT 0, NULL, NULL, metric, bucket, sum(n) FROM sketch GROUP BY metric, bucket
), ranked AS (
  SELECT *, sum(n) OVER (PARTITION BY level, lang, source, metric ORDER BY bucket) AS upto, sum(n) OVER (PARTITION BY level, lang, source, metric) AS docs FROM merged
), quantiles AS (
  SELECT level, lang, source, metric, max(docs) AS docs, min(CASE WHEN 2 * upto >= docs THEN bucket END) AS q50, min(CASE WHEN 4 * upto >= 3 * docs THEN bucket END) AS q75 FROM ranked GROUP BY ALL
), {bounds}
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND NOT coalesce(over_limit, false) AS kept
FROM (
  SELECT c.*, n_words < {MIN_WORDS} OR 100 * n_repeat_words > 50 * n_words AS base_failed, CASE WHEN n_words > 0 THEN {over} END AS over_limit
  FROM counts c
  LEFT JOIN bounds a ON a.level = 0
  LEFT JOIN bounds l ON l.level = 1 AND l.docs >= {SUPPORT} AND c.lang IS NOT DISTINCT FROM l.lang
  LEFT JOIN bounds s ON s.level = 2 AND s.docs >= {SUPPORT} AND c.lang IS NOT DISTINCT FROM s.lang AND c.source IS NOT DISTINCT FROM s.source
)"""
