"""URL filter: allow and block rules, then logistic regression on hashed character n-grams of host and path.

The model is trained from a small table of labelled URLs (in the driver's session, a few hundred rows whatever the
data). Everything runs as DataFrame expressions in the JVM: parsing, n-grams, hashing, training and scoring.

Defined cases: a null URL, or one without ``://``, has an empty host and path and gets the model's verdict for an
address without n-grams, which is allow; repeated rows are judged each; an empty table gives an empty table; extra
columns are ignored. Very long URLs are scored whole (their n-grams are one array of the row, so time grows with the square of the length, as
substrings count characters from the start). A column of the input that is named like an output is replaced.
"""

from __future__ import annotations

from pyspark.ml.classification import LogisticRegression, LogisticRegressionModel
from pyspark.ml.feature import HashingTF
from pyspark.ml.functions import vector_to_array
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
SIZES, FEATURES = (3, 4, 5), 1 << 14

#: Fixed values of the query: (verdict, host and path).
RULES = (("allow", "org/"), ("block", "example.org/es/"), ("block", "example.org/en/1"), ("allow", "com/fr/"), ("block", "com/de/"))

#: The labelled table, from general knowledge: subjects of unwanted and of ordinary sites, and the ways sites are named.
#: None is a host of the given tables.
UNWANTED = (
    "adult", "porn", "xxx", "sex", "escort", "webcam", "casino", "poker", "slots", "betting", "bet", "gambling", "jackpot", "win-money",
    "pills", "viagra", "pharmacy", "spam", "linkfarm", "malware", "phishing", "warez", "crack", "advert", "adserver", "popups", "tracker", "tracking",
)
ORDINARY = (
    "news", "university", "library", "weather", "recipes", "history", "science", "council", "museum", "gardening", "software", "travel", "books", "health",
    "music", "maps", "encyclopedia", "sports", "radio", "school", "village", "garden", "river", "theatre", "cooking", "mathematics", "railway", "forest", "painting", "reading", "hiking", "building",
)
FORMS = ("{}", "{}s", "my{}", "{}-online", "the-{}", "{}-club", "{}24", "best-{}", "{}-shop", "{}-world", "super-{}", "{}-now", "e-{}")
#: Names that say nothing, spelt from consonants and vowels by rule: most sites are called like that.
CONSONANTS, VOWELS = "bcdfghklmnprstvwz", "aeiou"


def plain_names(n: int) -> list[str]:
    """n different pronounceable names of two to four syllables."""
    out = []
    for i in range(n):
        x, name = i * 2654435761 % (1 << 32), ""
        for _ in range(2 + i % 3):
            x = (x * 1103515245 + 12345) % (1 << 31)
            name += CONSONANTS[x // 65536 % len(CONSONANTS)] + VOWELS[x // 4096 % len(VOWELS)] + (CONSONANTS[x // 512 % len(CONSONANTS)] if x // 128 % 2 else "")
        out.append(name)
    return out


def labelled(spark: SparkSession) -> DataFrame:
    """(url, label): 1 for unwanted; built from the names above by rule. Both kinds use the same forms, fronts and paths."""
    fronts, ends = ("", "www.", "blog.", "m."), ("example.com/en/{}", "example.net/{}.html", "org/fr/{}/", "example.org/de/{}?page=2")
    names = [(1.0, f.format(x)) for x in UNWANTED for f in FORMS] + [(0.0, f.format(x)) for x in ORDINARY for f in FORMS] + [(0.0, x) for x in plain_names(600)]
    rows = [(f"https://{fronts[i % 4]}{name}.{ends[(i // 4 + i) % 4].format(17 * i + 3)}", label) for i, (label, name) in enumerate(names)]
    quoted = ", ".join(f"('{u}', {y}D)" for u, y in rows)
    return spark.sql(f"SELECT * FROM VALUES {quoted} AS t(url, label)")


def host_and_path(url: Column) -> tuple[Column, Column]:
    shape = r"(?s)^.*?://([^/?#]*)([^?#]*)"
    url = F.coalesce(url, F.lit(""))
    return F.translate(F.regexp_extract(url, shape, 1), UPPER, LOWER), F.regexp_extract(url, shape, 2)


def rule_of(host: Column, path: Column, rules=RULES) -> tuple[Column, Column]:
    """The longest rule that fits, and its verdict; null if none does. A rule list is configuration, not data."""
    rule = verdict = F.lit(None).cast("string")
    for said, text in sorted(rules, key=lambda r: (len(r[1]), r[1])):
        name, _, tail = text.partition("/")
        fits = ((host == name) | host.endswith("." + name)) & path.startswith("/" + tail)
        rule, verdict = F.when(fits, text).otherwise(rule), F.when(fits, said).otherwise(verdict)
    return rule, verdict


def _slice(mark: str, text: Column, n: int):
    return lambda i: F.concat(F.lit(mark), F.substring(text, i, F.lit(n)))


def grams(host: Column, path: Column) -> Column:
    """Character n-grams of ``^host$`` (marked) and of the path in lower case with digits made alike."""
    out = []
    for mark, text in (("h", F.concat(F.lit("^"), host, F.lit("$"))), ("p", F.regexp_replace(F.translate(path, UPPER, LOWER), "[0-9]+", "0"))):
        for n in SIZES:
            places = F.when(F.length(text) >= n, F.sequence(F.lit(1), F.length(text) - n + 1)).otherwise(F.array().cast("array<int>"))
            out.append(F.transform(places, _slice(mark, text, n)))
    return F.concat(*out)


def _features(urls: DataFrame) -> DataFrame:
    host, path = host_and_path(F.col("url"))
    parsed = urls.withColumn("host", host).withColumn("path", path)
    return HashingTF(numFeatures=FEATURES, binary=True, inputCol="_grams", outputCol="features").transform(parsed.withColumn("_grams", grams(F.col("host"), F.col("path"))))


def train(table: DataFrame) -> LogisticRegressionModel:
    """Deterministic for a given table: one partition, no sampling."""
    return LogisticRegression(maxIter=30, regParam=0.01, featuresCol="features", labelCol="label").fit(_features(table.coalesce(1)))


def judge(urls: DataFrame, model: LogisticRegressionModel, rules=RULES) -> DataFrame:
    """Add host, path, rule, ``p_block`` and verdict to rows that have ``url``."""
    own = ("host", "path", "rule", "verdict", "p_block", "_grams", "features", "rawPrediction", "probability", "prediction")
    scored = model.transform(_features(urls.drop(*own))).withColumn("p_block", F.when((F.col("host") == "") & (F.col("path") == ""), 0.0).otherwise(vector_to_array("probability")[1]))
    rule, verdict = rule_of(F.col("host"), F.col("path"), rules)
    by_model = F.when(F.col("p_block") > 0.5, "block").otherwise("allow")
    return scored.withColumn("rule", rule).withColumn("verdict", F.coalesce(verdict, by_model)).drop("_grams", "features", "rawPrediction", "probability", "prediction")


def op4_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url")
    return judge(pages, train(labelled(spark))).select("page_id", "host", "path", "rule", "verdict")
