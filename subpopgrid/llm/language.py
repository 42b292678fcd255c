"""Language identification by Bayesian fusion of text, declared language, address suffix and host prior.

* Text: byte trigrams hashed to ``BUCKETS`` classes, multinomial likelihoods learnt from a sample of labelled rows
  that is bounded for each label: all rows of a label up to ``SAMPLE_DOCS``, of a more frequent one a share chosen by
  a hash of id and text, at least one row. So every label is a language of the model, however large the table.
  Trigrams overlap, so the log likelihood is tempered: a text counts as at most ``TEXT_TRIALS`` independent draws.
* Declared markup language and the language an address suffix hints at: each a noisy witness with a known hit rate.
* Host prior: sums of text posteriors a host by grouped aggregation, smoothed towards its domain's, which is
  smoothed towards that of the whole table.

A text is rejected if no language is likely enough after fusion, if it has no letters, or if it is far less
likely under its best language than the labelled texts are.

Defined cases: null or empty text has no text evidence and is rejected; null declared language, address or host is no
evidence; repeated rows are judged each; an empty table gives an empty table; extra columns are ignored.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import fresh, merged_scan, staged, take_over

BUCKETS, SAMPLE_DOCS, TEXT_TRIALS = 8192, 4000, 60
DECLARED_HIT, SUFFIX_HIT, HOST_WEIGHT, MIN_POSTERIOR = 0.9, 0.8, 20, 0.5
#: A text's mean log likelihood may lie so many standard deviations of the labelled texts' below theirs.
FLOOR_DEVIATIONS = 16.0


def _trigrams(text: str) -> np.ndarray:
    b = np.frombuffer(text.lower().encode("utf-8", "replace"), np.uint8).astype(np.uint32)
    return ((b[:-2] * 40503 + b[1:-1] * 1021 + b[2:]) * np.uint32(2654435761) >> np.uint32(19)).astype(np.int64) if len(b) > 2 else np.empty(0, np.int64)


def fit(docs: DataFrame, label: Column, id_col: str = "doc_id", text_col: str = "text", sample_docs: int = SAMPLE_DOCS) -> dict:
    """Languages, log likelihoods a bucket, and the floor on the mean log likelihood. Gathers BUCKETS rows a language.

    ``sample_docs`` bounds the sample of each label: one with fewer than twice as many rows is read whole.
    """
    labelled = docs.select(label.alias("label"), F.col(text_col).alias("text"), F.xxhash64(id_col, text_col).alias("mark")).where("label IS NOT NULL AND text IS NOT NULL")
    counts = labelled.groupBy("label").agg(F.count(F.lit(1)).alias("n"), F.min("mark").alias("least")).collect()
    shares = docs.sparkSession.createDataFrame([(r["label"], max(1, r["n"] // sample_docs), r["least"]) for r in counts], "label string, every long, least long")
    # equal rows are in or out together: the least mark is always in, so no label is left without a row
    sample = labelled.join(F.broadcast(shares), "label").where((F.pmod("mark", "every") == 0) | (F.col("mark") == F.col("least")))

    def count(batches):
        import pyarrow as pa

        total: dict[str, np.ndarray] = {}
        for b in batches:
            for lang, text in zip(b.column("label").to_pylist(), b.column("text"), strict=True):
                if lang not in total:
                    total[lang] = np.zeros(BUCKETS, np.int64)
                total[lang] += np.bincount(_trigrams(text.as_py()), minlength=BUCKETS)
        for lang, n in total.items():
            at = np.flatnonzero(n)
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(at), pa.string()), pa.array(at), pa.array(n[at])], names=["label", "bucket", "n"])

    rows = sample.select("label", "text").mapInArrow(count, "label string, bucket long, n long").groupBy("label", "bucket").agg(F.sum("n").alias("n")).collect()
    langs = sorted({r["label"] for r in rows})
    table = np.full((len(langs), BUCKETS), 0.5)
    for r in rows:
        table[langs.index(r["label"]), r["bucket"]] += r["n"]
    logs = np.log(table / table.sum(axis=1, keepdims=True)) if langs else table
    # the labelled texts' mean and spread under their own language, from its bucket counts
    means = [float((t * g).sum() / t.sum()) for t, g in zip(table, logs, strict=True)]
    spreads = [float(math.sqrt((t * (g - m) ** 2).sum() / t.sum())) for t, g, m in zip(table, logs, means, strict=True)]
    return {"langs": langs, "logs": logs, "mean": means, "spread": spreads}


def score(docs: DataFrame, model: dict, keep: dict[str, Column], text_col: str = "text", text_in: str | None = None) -> DataFrame:
    """``keep`` columns (one of them may hold the text: ``text_in``), ``n`` trigrams, ``fits`` and ``t_<k>``, the tempered log likelihood of language k."""
    langs, logs, L = model["langs"], model["logs"], len(model["langs"])
    held = docs.sparkSession.sparkContext.broadcast((np.ascontiguousarray(logs.T), np.array(model["mean"]), np.array(model["spread"])))
    names, source = list(keep), text_in or "_text"

    def rate(batches):
        import pyarrow as pa

        take_over("language")
        table, mean, spread = held.value
        for b in batches:
            n, fits, out = [], [], np.zeros((b.num_rows, L))
            for i, t in enumerate(b.column(source)):
                text = t.as_py() or ""
                grams = _trigrams(text)
                n.append(len(grams))
                fits.append(False)
                if len(grams) and L:
                    each = np.bincount(grams, minlength=BUCKETS)
                    at = np.flatnonzero(each)
                    avg = each[at] @ table[at] / len(grams)
                    out[i] = avg * min(len(grams), TEXT_TRIALS)
                    k = int(avg.argmax())
                    fits[-1] = bool(avg[k] >= mean[k] - FLOOR_DEVIATIONS * spread[k] / math.sqrt(min(len(grams), TEXT_TRIALS)) and any(map(str.isalpha, text)))
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in names), pa.array(n, pa.int64()), pa.array(fits), *(pa.array(out[:, k]) for k in range(L))], names=[*names, "n", "fits", *(f"t_{k}" for k in range(L))])

    rows = docs.select(*(v.alias(k) for k, v in keep.items()), *([] if text_in else [F.col(text_col).alias("_text")]))
    kinds = dict(rows.dtypes)
    return rows.mapInArrow(rate, ", ".join([*(f"`{c}` {kinds[c]}" for c in names), "n long", "fits boolean", *(f"t_{k} double" for k in range(len(langs)))]))


def _softmax(rows: DataFrame, parts: list[Column]) -> tuple[DataFrame, str]:
    """``rows`` and the name of a new array column of the posteriors of ``parts``, their logarithms up to a summand.

    Arrays in steps: written out, every posterior would repeat all parts, and the generated code outgrows a method.
    """
    logs, top, odds, out = (fresh(c, rows.columns) for c in ("_logs", "_top", "_odds", "_posteriors"))
    each = rows.withColumn(logs, F.array(*parts)).withColumn(top, F.array_max(logs)).withColumn(odds, F.transform(logs, lambda x: F.exp(x - F.col(top))))
    whole = F.aggregate(odds, F.lit(0.0), lambda a, x: a + x)
    return each.withColumn(top, whole).withColumn(out, F.transform(odds, lambda x: x / F.col(top))).drop(logs, top, odds), out


def host_sums(scores: DataFrame, langs: list[str]) -> DataFrame:
    """(host, s_<k>): text posteriors summed as whole thousandths, so any order sums alike."""
    rated, post = _softmax(scores, [F.col(f"t_{k}") for k in range(len(langs))])
    sums = [F.sum(F.when(F.col("n") > 0, F.round(1000 * F.col(post)[k])).otherwise(0).cast("long")).alias(f"s_{k}") for k in range(len(langs))]
    return rated.groupBy("host").agg(*sums)


def host_priors(sums: DataFrame, langs: list[str]) -> DataFrame:
    """(host, h_<k>): log prior of each language, smoothed host -> domain -> all."""
    by_host = sums.withColumn("domain", F.substring_index("host", ".", -2))
    again = [F.sum(f"s_{k}").alias(f"d_{k}") for k in range(len(langs))]
    by_domain = by_host.groupBy("domain").agg(*again)
    whole = by_domain.agg(*(F.sum(f"d_{k}").alias(f"d_{k}") for k in range(len(langs)))).take(1)[0]
    total = sum(int(x or 0) for x in whole) + len(langs)
    out = by_host.join(by_domain, F.col("host").isNotNull() & by_host["domain"].eqNullSafe(by_domain["domain"]), "left").drop("domain")
    n_host = sum((F.col(f"s_{k}") for k in range(len(langs))), F.lit(0)) / 1000
    n_domain = sum((F.coalesce(F.col(f"d_{k}"), F.lit(0)) for k in range(len(langs))), F.lit(0)) / 1000
    priors = []
    for k in range(len(langs)):
        p = (int(whole[k] or 0) + 1) / total
        domain = (F.coalesce(F.col(f"d_{k}"), F.lit(0)) / 1000 + HOST_WEIGHT * p) / (n_domain + HOST_WEIGHT)
        priors.append(F.log((F.when(F.col("host").isNull(), 0).otherwise(F.col(f"s_{k}") / 1000) + HOST_WEIGHT * domain) / (F.when(F.col("host").isNull(), 0).otherwise(n_host) + HOST_WEIGHT)).alias(f"h_{k}"))
    return out.select(F.col("host").alias("_host"), *priors)


def _witness(said: Column, lang: str, langs: list[str], hit: float) -> Column:
    """Log chance that the witness says this if the language is ``lang``; nothing, or an unknown language, is no evidence."""
    miss = (1 - hit) / max(1, len(langs) - 1)
    return F.when(said.isin(langs), F.when(said == lang, math.log(hit)).otherwise(math.log(miss))).otherwise(0.0)


def _inputs(docs: DataFrame, declared: Column | None, suffix: Column | None, host: Column | None) -> dict[str, Column]:
    none = F.lit(None).cast("string")
    short = lambda c: none if c is None else F.lower(F.substring(c, 1, 2))
    return {"declared": short(declared), "suffix": short(suffix), "host": none if host is None else host.cast("string")}


def fuse(scores: DataFrame, priors: DataFrame, langs: list[str]) -> DataFrame:
    """Add ``lang_pred`` (null without text), ``posterior`` and ``kept``. Priors broadcast only below Spark's size limit."""
    joined = scores.join(priors, F.col("host").eqNullSafe(F.col("_host")), "left")
    parts = [F.col(f"t_{k}") + F.coalesce(F.col(f"h_{k}"), F.lit(0.0)) + _witness(F.col("declared"), x, langs, DECLARED_HIT) + _witness(F.col("suffix"), x, langs, SUFFIX_HIT) for k, x in enumerate(langs)]
    rated, post = _softmax(joined, parts)
    names = F.array(*(F.lit(x) for x in langs))
    best = rated.withColumn("best", F.array_max(F.transform(post, lambda p, k: F.struct(F.round(p, 6).alias("p"), F.get(names, k).alias("x")))))
    return best.withColumn("lang_pred", F.when(F.col("n") > 0, F.col("best.x"))).withColumn("posterior", F.col("best.p")).withColumn("kept", F.col("fits") & (F.col("best.p") >= MIN_POSTERIOR))


def identify(docs: DataFrame, model: dict, id_col: str = "doc_id", text_col: str = "text", declared: Column | None = None, suffix: Column | None = None, host: Column | None = None) -> DataFrame:
    """id, ``lang_pred``, ``posterior`` and ``kept`` for every row.

    ``declared``: markup language; ``suffix``: language an address hints at; ``host``: the host or source.
    """
    langs = model["langs"]
    scores = staged(score(merged_scan(docs), model, {id_col: F.col(id_col)} | _inputs(docs, declared, suffix, host), text_col), "language-scores")
    if not langs:
        return scores.select(id_col, F.lit(None).cast("string").alias("lang_pred"), F.lit(0.0).alias("posterior"), F.lit(False).alias("kept"))
    priors = staged(host_priors(staged(host_sums(scores, langs), "host-sums"), langs), "host-priors")  # a row a host
    return fuse(scores, priors, langs).select(id_col, "lang_pred", "posterior", "kept")


def accepted(docs: DataFrame, model: dict, text_col: str = "text", declared: Column | None = None, suffix: Column | None = None, host: Column | None = None) -> DataFrame:
    """The rows that are not rejected, all columns as they were. Rows are rated twice (priors, verdict) rather than shuffled."""
    langs, names = model["langs"], docs.columns
    if not langs:
        return docs.limit(0)
    inputs = _inputs(docs, declared, suffix, host)
    sums = staged(host_sums(score(merged_scan(docs), model, inputs, text_col), langs), "host-sums")  # a row a host
    priors = staged(host_priors(sums, langs), "host-priors")
    carried = {f"_c{i}": F.col(f"`{c}`") for i, c in enumerate(names)}
    verdicts = fuse(score(docs, model, carried | inputs, text_in=f"_c{names.index(text_col)}"), priors, langs).where("kept")
    return verdicts.select(*(F.col(f"_c{i}").alias(c) for i, c in enumerate(names)))


def address_language(url: Column) -> Column:
    """Two letters from the first path segment (``/fr/``) or the country suffix of the host; null if neither."""
    path = F.regexp_extract(url, r"^[^:]*://[^/?#]*/([a-z]{2})(?:/|$)", 1)
    country = F.regexp_extract(url, r"^[^:]*://[^/?#]*\.([a-z]{2})(?:[:/?#]|$)", 1)
    return F.when(path != "", path).when(country != "", country)


def markup_language(html: Column) -> Column:
    said = F.lower(F.regexp_extract(html, r"(?i)<html[^>]*?\slang\s*=\s*[\"']?([a-zA-Z]{2})", 1))
    return F.when(said != "", said)


def op9_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents; their ``lang`` is the declared language, their source the host."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return identify(docs, fit(docs, F.col("lang")), declared=F.col("lang"), host=F.col("source"))
