"""Given tables, the workload views over them, and round trips through other formats."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..schema import WorkloadSpec

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")

_LINES = "FROM {lineitem} l JOIN {orders} o ON l.l_orderkey = o.o_orderkey"
#: Bit length minus one: the whole part of the binary logarithm, the same in every engine.
_LOG2 = "CAST(length(bin({0})) - 1 AS BIGINT)"

#: View -> (dimensions, SQL). ``$dow`` is the weekday 0-6 of ts; names in braces are tables.
VIEWS: dict[str, tuple[tuple[str, ...], str]] = {
    "flow": (
        ("l_returnflag", "l_linestatus", "l_linenumber", "o_orderpriority", "p_brand"),
        f"SELECT l_returnflag, l_linestatus, l_linenumber, o_orderpriority, p_brand, CAST(l_quantity AS BIGINT) AS m, CAST(1 AS BIGINT) AS wgt {_LINES} JOIN {{part}} p ON l.l_partkey = p.p_partkey",
    ),
    "flow_sum": (
        ("l_returnflag", "l_linestatus", "l_linenumber", "o_orderpriority", "p_brand"),
        f"SELECT l_returnflag, l_linestatus, l_linenumber, o_orderpriority, p_brand, CAST(l_quantity AS BIGINT) AS m, CAST(round(l_extendedprice * 100) AS BIGINT) AS wgt {_LINES} JOIN {{part}} p ON l.l_partkey = p.p_partkey",
    ),
    "flow_card": (
        ("l_returnflag", "l_linestatus", "l_linenumber", "o_orderpriority"),
        f"SELECT l_returnflag, l_linestatus, l_linenumber, o_orderpriority, CAST(l_suppkey AS BIGINT) AS m, CAST(1 AS BIGINT) AS wgt {_LINES}",
    ),
    "flow_wide": (
        ("l_returnflag", "l_linestatus", "l_linenumber", "o_orderpriority", "p_brand", "c_mktsegment", "r_name"),
        f"SELECT l_returnflag, l_linestatus, l_linenumber, o_orderpriority, p_brand, c_mktsegment, r_name, CAST(l_partkey AS BIGINT) AS m, CAST(1 AS BIGINT) AS wgt {_LINES} "
        "JOIN {part} p ON l.l_partkey = p.p_partkey JOIN {customer} c ON o.o_custkey = c.c_custkey JOIN {nation} n ON c.c_nationkey = n.n_nationkey JOIN {region} g ON n.n_regionkey = g.r_regionkey",
    ),
    "video": (
        ("event_type", "dow", "hod", "user10"),
        "SELECT event_type, $dow AS dow, CAST(hour(ts) AS INT) AS hod, CAST(user_id % 10 AS INT) AS user10, CAST(floor(value / 10) AS BIGINT) AS m, CAST(1 AS BIGINT) AS wgt FROM {events}",
    ),
    "video_json": (
        ("event_type", "dow", "hod", "user10"),
        "SELECT event_type, $dow AS dow, CAST(hour(ts) AS INT) AS hod, CAST(user_id % 10 AS INT) AS user10, CAST($json AS BIGINT) AS m, CAST(1 AS BIGINT) AS wgt FROM {events}",
    ),
    "docs": (
        ("lang", "source", "quality", "toxic"),
        f"SELECT d.lang, d.source, coalesce(quality, -1) AS quality, coalesce(toxic, -1) AS toxic, {_LOG2.format('d.n_chars')} AS m, CAST(1 AS BIGINT) AS wgt FROM {{documents}} d LEFT JOIN {{labels}} l ON d.doc_id = l.doc_id",
    ),
    "docs_null": (
        ("lang", "source", "quality", "toxic"),
        f"SELECT d.lang, d.source, quality, toxic, {_LOG2.format('d.n_chars')} AS m, CAST(1 AS BIGINT) AS wgt FROM {{documents}} d LEFT JOIN {{labels}} l ON d.doc_id = l.doc_id",
    ),
    "conv": (("role", "turn"), f"SELECT role, turn, {_LOG2.format('length(text) + 1')} AS m, CAST(1 AS BIGINT) AS wgt FROM {{conversations}}"),
    "web": (
        ("host", "lang"),
        f"SELECT regexp_extract(url, '://([^/]*)', 1) AS host, regexp_extract(url, '://[^/]*/([a-z]+)/', 1) AS lang, {_LOG2.format('length(html) + 1')} AS m, CAST(1 AS BIGINT) AS wgt FROM {{pages}}",
    ),
    "vec": (("label", "pos8"), "SELECT label, CAST(pos % 8 AS INT) AS pos8, CAST(floor(x * 10) AS BIGINT) AS m, CAST(1 AS BIGINT) AS wgt FROM $vec"),
}

DIALECT = {
    "spark": {"$dow": "CAST(dayofweek(ts) - 1 AS INT)", "$json": "get_json_object(props, '$.k')", "$vec": "(SELECT label, pos, x FROM {embeddings} LATERAL VIEW posexplode(embedding) t AS pos, x)"},
    "duckdb": {"$dow": "CAST(dayofweek(ts) AS INT)", "$json": "json_extract(props, '$.k')", "$vec": "(SELECT label, unnest(range(len(embedding))) AS pos, unnest(embedding) AS x FROM {embeddings})"},
}


def _in(dialect: str, sql: str) -> str:
    for name, text in DIALECT[dialect].items():
        sql = sql.replace(name, text)
    return sql


def spec_of(view: str, **more) -> WorkloadSpec:
    return WorkloadSpec(dims=VIEWS[view][0], weight="wgt", **more)


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def sql(spark: SparkSession, sf_dir: str, text: str, **frames: DataFrame) -> DataFrame:
    """Run SQL whose names in braces are given tables or frames; no temporary views are left behind."""
    text = _in("spark", text)
    known = {t: load(spark, sf_dir, t) for t in TABLES if "{" + t + "}" in text and t not in frames}
    return spark.sql(text, **known, **frames)


def view(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return sql(spark, sf_dir, VIEWS[name][1])


def view_sql(name: str) -> str:
    """The view as DuckDB SQL over the registered tables."""
    return _in("duckdb", VIEWS[name][1]).format_map({t: t for t in TABLES})


# --- generated skew: the same integer rows in every engine ---

SCALE = 1 << 60


def zipf_thresholds(alpha: float, groups: int) -> list[int]:
    """Ends of the groups' intervals on the scale 2^60, weights 1 / rank^alpha."""
    weights = [1.0 / (i + 1) ** alpha for i in range(groups)]
    total, at, out = sum(weights), 0.0, []
    for x in weights:
        at += x
        out.append(int(at / total * SCALE))
    out[-1] = SCALE
    return out


def zipf(spark: SparkSession, alpha: float, rows: int, groups: int = 64, values: int = 50) -> DataFrame:
    """One dimension ``g`` with Zipf-distributed sizes and a metric; a range join finds the group of a row's hash."""
    ends = zipf_thresholds(alpha, groups)
    bounds = spark.createDataFrame([(i, lo, hi) for i, (lo, hi) in enumerate(zip([0, *ends], ends, strict=False))], "g int, lo long, hi long")
    slice_ = lambda mark: F.expr(f"CAST(conv(substring(md5(concat('{mark}|', id)), 1, 15), 16, 10) AS BIGINT)")
    ids = spark.range(rows).select(slice_("g").alias("x"), (slice_("m") % values).alias("m"))
    return ids.join(F.broadcast(bounds), (F.col("x") >= F.col("lo")) & (F.col("x") < F.col("hi"))).select("g", "m", F.lit(1).cast("long").alias("wgt"))


def zipf_sql(alpha: float, rows: str, groups: int = 64, values: int = 50) -> str:
    ends = zipf_thresholds(alpha, groups)
    cases = ", ".join(f"({i}, {lo}, {hi})" for i, (lo, hi) in enumerate(zip([0, *ends], ends, strict=False)))
    return (
        f"SELECT g, m, CAST(1 AS BIGINT) AS wgt FROM (SELECT CAST('0x' || substr(md5('g|' || i), 1, 15) AS BIGINT) AS x, CAST('0x' || substr(md5('m|' || i), 1, 15) AS BIGINT) % {values} AS m "
        f"FROM (SELECT unnest(range({rows})) AS i)) JOIN (VALUES {cases}) t(g, lo, hi) ON x >= lo AND x < hi"
    )


ZIPF_SPEC = WorkloadSpec(dims=("g",), weight="wgt")


def round_trip(df: DataFrame, path: str, kind: str) -> DataFrame:
    """Write ``df`` as csv, json or orc with its explicit schema and read it back (no inference)."""
    options = {"header": "true"} if kind == "csv" else {}
    df.write.mode("overwrite").options(**options).format(kind).save(path)
    return df.sparkSession.read.schema(df.schema).options(**options).format(kind).load(path)


def scratch(spark: SparkSession, name: str) -> str:
    """A new folder below the session's shared one; where none is set (tests), below a temporary one that goes at exit."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not root:
        own = tempfile.mkdtemp(prefix="subpopgrid-")
        atexit.register(shutil.rmtree, own, ignore_errors=True)
        root = f"file://{own}"
    return f"{root}/{name}-{uuid.uuid4().hex}"
