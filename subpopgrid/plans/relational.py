"""Queries of the operators around the methods: scans, joins, aggregation, windows, functions, user functions."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions import udfs
from ..operators import baselines as B
from ..operators import fanout
from ..sources.tables import load, round_trip, scratch, spec_of, view, view_sql
from . import oracle as O
from .registry import query

_PAIRS = O.pairs_ctes(view_sql("docs"), spec_of("docs", max_order=2)) + ", " + O.TRUTH


def _docs(spark, sf_dir):
    return fanout.pair_counts(view(spark, sf_dir, "docs"), spec_of("docs", max_order=2))


def _truth(spark, sf_dir):
    return B.ground_truth(view(spark, sf_dir, "docs"), spec_of("docs", max_order=2))


#: Seconds of a time without zone, whatever the session's zone.
_SECONDS = "timestampdiff(SECOND, TIMESTAMP_NTZ '1970-01-01 00:00:00', ts)"


# --- scans and sinks ---


@query("op_scan_pushdown", "l_orderkey:l l_quantity:d", "@@ SELECT l_orderkey, l_quantity FROM lineitem WHERE l_shipdate >= TIMESTAMP '1997-01-01' AND l_quantity > 45")
def _scan(spark, sf_dir):
    return load(spark, sf_dir, "lineitem").where("l_shipdate >= TIMESTAMP_NTZ '1997-01-01' AND l_quantity > 45").select("l_orderkey", "l_quantity")


for _kind in ("csv", "json", "orc"):

    @query(f"op_round_trip_{_kind}", "event_type:s n:l ids:l", "@@ SELECT event_type, count(*) AS n, sum(event_id) AS ids FROM events GROUP BY event_type")
    def _trip(spark, sf_dir, kind=_kind):
        df = load(spark, sf_dir, "events").select("event_id", "event_type", "value", "props")
        return round_trip(df, scratch(spark, f"trip-{kind}"), kind).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("event_id").alias("ids"))


@query("op_round_trip_text", "n:l chars:l", "@@ SELECT count(*) AS n, sum(length(props)) AS chars FROM events")
def _text(spark, sf_dir):
    path = scratch(spark, "trip-text")
    load(spark, sf_dir, "events").select("props").write.text(path)
    return spark.read.text(path).agg(F.count(F.lit(1)).alias("n"), F.sum(F.length("value")).alias("chars"))


#: Bytes of a build's input split.
SPLIT_BYTES = 64 << 20


@query("op_scan_splits", "splits:l rows:l")
def _splits(spark, sf_dir):
    """A scan in splits of 64 MB; the setting is that of a session of its own."""
    own = spark.newSession()
    own.conf.set("spark.sql.files.maxPartitionBytes", str(SPLIT_BYTES))
    df = load(own, sf_dir, "lineitem").select(F.spark_partition_id().alias("p"))
    return df.agg(F.count_distinct("p").alias("splits"), F.count(F.lit(1)).alias("rows"))


@query("op_sink_partitioned", "l_returnflag:s l_linestatus:s n:l", "@@ SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem WHERE l_returnflag = 'R' GROUP BY ALL")
def _sink(spark, sf_dir):
    path = scratch(spark, "sink")
    load(spark, sf_dir, "lineitem").select("l_returnflag", "l_linestatus", "l_orderkey").repartition("l_returnflag").write.partitionBy("l_returnflag").parquet(path)
    return spark.read.parquet(path).where("l_returnflag = 'R'").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"))


# --- filters and joins ---


@query(
    "op_filter_forms",
    "event_id:l event_type:s",
    "@@ SELECT event_id, event_type FROM events WHERE event_type LIKE 'c%' AND value BETWEEN 100 AND 200 AND user_id IN (1, 2, 3, 5, 8, 13) AND props IS NOT DISTINCT FROM props",
)
def _filters(spark, sf_dir):
    e = load(spark, sf_dir, "events")
    return e.where(F.col("event_type").like("c%") & F.col("value").between(100, 200) & F.col("user_id").isin(1, 2, 3, 5, 8, 13) & F.col("props").eqNullSafe(F.col("props"))).select("event_id", "event_type")


_JOINED = "SELECT p.subpop_key, p.m, p.f, t.l1 FROM pairs p JOIN truth t ON p.subpop_key = t.subpop_key"
for _hint in ("broadcast", "merge", "shuffle_hash"):

    @query(f"op_join_{_hint}", "subpop_key:s m:l f:l l1:l", _PAIRS + "@@ " + _JOINED)
    def _join(spark, sf_dir, hint=_hint):
        return _docs(spark, sf_dir).join(_truth(spark, sf_dir).select("subpop_key", "l1").hint(hint), "subpop_key")


@query("op_join_range", "bin:l n:l", "@@ SELECT bin, count(*) AS n FROM events JOIN (SELECT unnest(range(10)) AS bin) ON value >= 50 * bin AND value < 50 * bin + 50 GROUP BY bin")
def _range_join(spark, sf_dir):
    bins = spark.range(10).select(F.col("id").alias("bin"))
    e = load(spark, sf_dir, "events")
    return e.join(F.broadcast(bins), (F.col("value") >= 50 * F.col("bin")) & (F.col("value") < 50 * F.col("bin") + 50)).groupBy("bin").agg(F.count(F.lit(1)).alias("n"))  # ten rows


for _how, _sql in (("left_semi", "EXISTS"), ("left_anti", "NOT EXISTS")):

    @query(f"op_join_{_how}", "doc_id:l", f"@@ SELECT doc_id FROM documents d WHERE {_sql} (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id AND quality = 1)")
    def _semi(spark, sf_dir, how=_how):
        return load(spark, sf_dir, "documents").select("doc_id").join(load(spark, sf_dir, "labels").where("quality = 1"), "doc_id", how)


@query("op_join_left_missed", "doc_id:l quality:l", "@@ SELECT d.doc_id, coalesce(quality, 0) AS quality FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")
def _left(spark, sf_dir):
    return load(spark, sf_dir, "documents").select("doc_id").join(load(spark, sf_dir, "labels"), "doc_id", "left").select("doc_id", F.coalesce("quality", F.lit(0)).alias("quality"))


_DOC_NULL = "SELECT source, quality, count(*) AS n FROM (" + view_sql("docs_null") + ") GROUP BY ALL"


@query("op_join_full_null_safe", "source:s quality:l a:l b:l", f"@@ SELECT coalesce(x.source, y.source) AS source, coalesce(x.quality, y.quality, -9) AS quality, coalesce(x.n, 0) AS a, coalesce(y.n, 0) AS b FROM (SELECT * FROM ({_DOC_NULL}) WHERE n > 10) x FULL JOIN (SELECT * FROM ({_DOC_NULL}) WHERE n < 20) y ON x.source IS NOT DISTINCT FROM y.source AND x.quality IS NOT DISTINCT FROM y.quality")
def _full(spark, sf_dir):
    n = view(spark, sf_dir, "docs_null").groupBy("source", "quality").agg(F.count(F.lit(1)).alias("n"))
    x, y = n.where("n > 10").alias("x"), n.where("n < 20").alias("y")
    on = F.col("x.source").eqNullSafe(F.col("y.source")) & F.col("x.quality").eqNullSafe(F.col("y.quality"))
    return x.join(y, on, "full").select(F.coalesce("x.source", "y.source").alias("source"), F.coalesce("x.quality", "y.quality", F.lit(-9)).alias("quality"), F.coalesce("x.n", F.lit(0)).alias("a"), F.coalesce("y.n", F.lit(0)).alias("b"))


@query(
    "op_join_star",
    "r_name:s c_mktsegment:s n:l",
    "@@ SELECT r_name, c_mktsegment, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey "
    "JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey WHERE p_size > 10 GROUP BY ALL",
)
def _star(spark, sf_dir):
    t = lambda n: load(spark, sf_dir, n)
    line = t("lineitem").join(t("part").where("p_size > 10"), F.col("l_partkey") == F.col("p_partkey")).join(t("supplier"), F.col("l_suppkey") == F.col("s_suppkey"))
    place = t("customer").join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t("region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return line.join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(place, F.col("o_custkey") == F.col("c_custkey")).groupBy("r_name", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


@query("op_rows_of_grid", "subpop_key:s grid_row:l", _PAIRS + "@@ SELECT subpop_key, r AS grid_row FROM truth, (SELECT unnest(range(3)) AS r)")
def _cross(spark, sf_dir):
    return _truth(spark, sf_dir).select("subpop_key", F.explode(F.sequence(F.lit(0), F.lit(2))).alias("grid_row"))


@query(
    "op_join_as_of",
    "event_id:l state:l",
    "@@ SELECT event_id, max(s) AS state FROM (SELECT event_id, epoch(ts) AS t FROM events WHERE event_type = 'purchase') e JOIN (SELECT DISTINCT CAST(floor(epoch(ts) / 3600) AS BIGINT) AS s FROM events) w ON CAST(floor(t / 3600) AS BIGINT) - 24 <= s AND s < CAST(floor(t / 3600) AS BIGINT) GROUP BY event_id",
)
def _as_of(spark, sf_dir):
    """The latest hour with any event, before the event's own and within a day: windows are probed by equal keys."""
    e = load(spark, sf_dir, "events").withColumn("h", F.floor(F.expr(_SECONDS) / 3600))
    hours = e.select(F.col("h").alias("s")).distinct()
    asked = e.where("event_type = 'purchase'").select("event_id", F.explode(F.sequence(F.col("h") - 24, F.col("h") - 1)).alias("s"))
    return asked.join(hours, "s").groupBy("event_id").agg(F.max("s").alias("state"))


# --- aggregation ---


@query("op_agg_sort_based", "source:s langs:s", "@@ SELECT source, array_to_string(list_sort(list(DISTINCT lang)), ',') AS langs FROM documents GROUP BY source")
def _sort_agg(spark, sf_dir):
    return load(spark, sf_dir, "documents").groupBy("source").agg(F.array_join(F.sort_array(F.collect_set("lang")), ",").alias("langs"))


@query(
    "op_agg_distinct_conditional",
    "l_returnflag:s parts:l big:l",
    "@@ SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(*) FILTER (WHERE l_quantity > 40) AS big FROM lineitem GROUP BY l_returnflag",
)
def _distinct(spark, sf_dir):
    return load(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.expr("count(1) FILTER (WHERE l_quantity > 40)").alias("big"))


for _name, _sql in (("cube", "CUBE (lang, source)"), ("rollup", "ROLLUP (lang, source)"), ("grouping_sets", "GROUPING SETS ((lang), (source))")):

    @query(f"op_agg_{_name}", "lang:s source:s g:l n:l", f"@@ SELECT lang, source, grouping(lang, source) AS g, count(*) AS n FROM documents GROUP BY {_sql}")
    def _sets(spark, sf_dir, how=_name):
        d = load(spark, sf_dir, "documents")
        grouped = {"cube": lambda: d.cube("lang", "source"), "rollup": lambda: d.rollup("lang", "source"), "grouping_sets": lambda: d.groupingSets([[F.col("lang")], [F.col("source")]], "lang", "source")}[how]()
        return grouped.agg(F.grouping_id().alias("g"), F.count(F.lit(1)).alias("n"))


@query("op_agg_sketches", "l_returnflag:s approx:l hll:l theta:l median:d kll:l")
def _sketches(spark, sf_dir):
    return load(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(
        F.approx_count_distinct("l_partkey").alias("approx"),
        F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey", 12)).alias("hll"),
        F.expr("theta_sketch_estimate(theta_sketch_agg(l_partkey))").alias("theta"),
        F.expr("approx_percentile(l_quantity, 0.5)").alias("median"),
        F.expr("kll_sketch_get_quantile_bigint(kll_sketch_agg_bigint(l_partkey), 0.5D)").alias("kll"),
    )


@query("op_agg_percentiles", "event_type:s q1:d q2:d q3:d", "@@ SELECT event_type, quantile_cont(value, 0.25) AS q1, quantile_cont(value, 0.5) AS q2, quantile_cont(value, 0.75) AS q3 FROM events GROUP BY event_type")
def _percentiles(spark, sf_dir):
    return load(spark, sf_dir, "events").groupBy("event_type").agg(*(F.expr(f"percentile(value, {p})").alias(f"q{i}") for i, p in ((1, 0.25), (2, 0.5), (3, 0.75))))


@query(
    "op_agg_moments",
    "l_returnflag:s sd:d vs:d r:d top:l low:l",
    "@@ SELECT l_returnflag, stddev_samp(l_quantity) AS sd, var_samp(l_quantity) AS vs, corr(l_quantity, l_discount) AS r, max_by(l_orderkey, l_orderkey * 10 + l_linenumber) AS top, min_by(l_orderkey, l_orderkey * 10 + l_linenumber) AS low FROM lineitem GROUP BY l_returnflag",
)
def _moments(spark, sf_dir):
    at = F.col("l_orderkey") * 10 + F.col("l_linenumber")
    return load(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.stddev_samp("l_quantity").alias("sd"), F.var_samp("l_quantity").alias("vs"), F.corr("l_quantity", "l_discount").alias("r"), F.max_by("l_orderkey", at).alias("top"), F.min_by("l_orderkey", at).alias("low"))


# --- windows ---

_RANKED = "rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER (ORDER BY l1 DESC, subpop_key) AS nt, percent_rank() OVER w AS pr, cume_dist() OVER w AS cd"


@query("op_window_ranks", "subpop_key:s rk:l dr:l nt:l pr:d cd:d", _PAIRS + f"@@ SELECT subpop_key, {_RANKED} FROM truth WINDOW w AS (ORDER BY l1 DESC)")
def _ranks(spark, sf_dir):
    w, total = W.orderBy(F.desc("l1")), W.orderBy(F.desc("l1"), "subpop_key")  # a report over one row a subpopulation
    return _truth(spark, sf_dir).select("subpop_key", F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(total).alias("nt"), F.percent_rank().over(w).alias("pr"), F.cume_dist().over(w).alias("cd"))


@query(
    "op_window_running",
    "source:s m:l f:l least:l share:d before:l after:l",
    "recs AS (" + view_sql("docs") + "), by_m AS (SELECT source, m, count(*) AS f FROM recs GROUP BY ALL)"
    "@@ SELECT source, m, f, min(f) OVER (w ROWS UNBOUNDED PRECEDING) AS least, sum(f) OVER (w ROWS UNBOUNDED PRECEDING) / sum(f) OVER (PARTITION BY source) AS share, lag(f, 1, 0) OVER w AS before, lead(f, 1, 0) OVER w AS after FROM by_m WINDOW w AS (PARTITION BY source ORDER BY m)",
)
def _running(spark, sf_dir):
    by_m = view(spark, sf_dir, "docs").groupBy("source", "m").agg(F.count(F.lit(1)).alias("f"))
    w = W.partitionBy("source").orderBy("m")
    upto = w.rowsBetween(W.unboundedPreceding, 0)
    return by_m.select("source", "m", "f", F.min("f").over(upto).alias("least"), (F.sum("f").over(upto) / F.sum("f").over(W.partitionBy("source"))).alias("share"), F.lag("f", 1, 0).over(w).alias("before"), F.lead("f", 1, 0).over(w).alias("after"))


@query(
    "op_window_range_frame",
    "event_id:l recent:l",
    "@@ SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY CAST(floor(epoch(ts)) AS BIGINT) RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS recent FROM events",
)
def _frame(spark, sf_dir):
    e = load(spark, sf_dir, "events").withColumn("t", F.expr(_SECONDS))
    return e.select("event_id", F.count(F.lit(1)).over(W.partitionBy("user_id").orderBy("t").rangeBetween(-3600, 0)).alias("recent"))


@query("op_top_without_sort", "subpop_key:s l1:l", _PAIRS + "@@ SELECT subpop_key, l1 FROM truth ORDER BY l1 DESC, subpop_key LIMIT 20")
def _top(spark, sf_dir):
    return _truth(spark, sf_dir).select("subpop_key", "l1").orderBy(F.desc("l1"), "subpop_key").limit(20)


for _name, _set in (("intersect", "INTERSECT"), ("except", "EXCEPT")):

    @query(f"op_set_{_name}", "user_id:l", f"@@ SELECT user_id FROM events WHERE event_type = 'purchase' AND value > 400 {_set} SELECT user_id FROM events WHERE event_type = 'click' AND value > 400")
    def _sets2(spark, sf_dir, how=_name):
        e = load(spark, sf_dir, "events").where("value > 400")
        a, b = (e.where(F.col("event_type") == t).select("user_id") for t in ("purchase", "click"))
        return a.intersect(b) if how == "intersect" else a.subtract(b)


@query("op_set_union", "k:s n:l", "@@ SELECT k, sum(n) AS n FROM (SELECT lang AS k, count(*) AS n FROM documents GROUP BY lang UNION ALL SELECT role, count(*) FROM conversations GROUP BY role) GROUP BY k")
def _union_all(spark, sf_dir):
    a = load(spark, sf_dir, "documents").groupBy(F.col("lang").alias("k")).agg(F.count(F.lit(1)).alias("n"))
    return a.unionByName(load(spark, sf_dir, "conversations").groupBy(F.col("role").alias("k")).agg(F.count(F.lit(1)).alias("n"))).groupBy("k").agg(F.sum("n").alias("n"))


# --- scalar functions ---


@query(
    "op_scalar_string",
    "page_id:l host:s up:s cut:s h:s n:l",
    "@@ SELECT page_id, regexp_extract(url, '://([^/]+)', 1) AS host, upper(substr(url, 1, 12)) AS up, replace(url, 'example', 'e') AS cut, md5(url) AS h, length(concat_ws('-', url, 'x')) AS n FROM pages",
)
def _strings(spark, sf_dir):
    return load(spark, sf_dir, "pages").select("page_id", F.regexp_extract("url", "://([^/]+)", 1).alias("host"), F.upper(F.substring("url", 1, 12)).alias("up"), F.expr("replace(url, 'example', 'e')").alias("cut"), F.md5("url").alias("h"), F.length(F.concat_ws("-", "url", F.lit("x"))).alias("n"))


@query(
    "op_scalar_bits_math",
    "l_orderkey:l bits:l x:l a:l sh:l md:l lg:d pw:d g:l",
    "@@ SELECT DISTINCT l_orderkey, bit_count(l_orderkey) AS bits, xor(l_orderkey, 5) AS x, l_orderkey & 12 AS a, l_orderkey >> 2 AS sh, l_orderkey % 7 AS md, log2(l_orderkey + 1) AS lg, pow(l_orderkey, 0.5) AS pw, greatest(l_orderkey, 100) AS g FROM lineitem",
)
def _bits(spark, sf_dir):
    k = F.col("l_orderkey")
    return load(spark, sf_dir, "lineitem").select(k, F.bit_count(k).alias("bits"), k.bitwiseXOR(5).alias("x"), k.bitwiseAND(12).alias("a"), F.shiftright(k, 2).alias("sh"), F.pmod(k, F.lit(7)).alias("md"), F.log2(k + 1).alias("lg"), F.pow(k, F.lit(0.5)).alias("pw"), F.greatest(k, F.lit(100)).alias("g")).distinct()


@query("op_scalar_date", "day:s h:l dow:l n:l", "@@ SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, hour(ts) AS h, dayofweek(ts) AS dow, count(*) AS n FROM events GROUP BY ALL")
def _dates(spark, sf_dir):
    return load(spark, sf_dir, "events").groupBy(F.date_format(F.date_trunc("day", "ts"), "yyyy-MM-dd").alias("day"), F.hour("ts").alias("h"), (F.dayofweek("ts") - 1).alias("dow")).agg(F.count(F.lit(1)).alias("n"))


@query(
    "op_scalar_arrays",
    "vec_id:l n:l big:l mid:d total:d",
    "@@ SELECT vec_id, len(embedding) AS n, len(list_filter(embedding, lambda x: x > 0)) AS big, list_sort(embedding[1:5])[3] AS mid, list_sum(list_transform(embedding, lambda x: CAST(floor(x * 1000) AS BIGINT))) AS total FROM embeddings",
)
def _arrays(spark, sf_dir):
    """Products stay single, as the elements are; short, empty and missing arrays and elements give nulls."""
    e = F.col("embedding")
    whole = F.filter(F.transform(e, lambda x: F.floor(x * F.lit(1000).cast("float"))), lambda x: x.isNotNull())
    total = F.when(F.array_size(whole) > 0, F.aggregate(whole, F.lit(0).cast("long"), lambda a, x: a + x))
    return load(spark, sf_dir, "embeddings").select("vec_id", F.array_size(e).alias("n"), F.array_size(F.filter(e, lambda x: x > 0)).alias("big"), F.try_element_at(F.array_sort(F.slice(e, 1, 5)), F.lit(3)).alias("mid"), total.alias("total"))


@query("op_scalar_maps", "source:s en:l other:l", "@@ SELECT source, count(*) FILTER (WHERE lang = 'en') AS en, count(*) FILTER (WHERE lang != 'en') AS other FROM documents GROUP BY source")
def _maps(spark, sf_dir):
    """Heaps held as maps: built from entries, merged by key."""
    n = load(spark, sf_dir, "documents").groupBy("source", "lang").agg(F.count(F.lit(1)).alias("n")).groupBy("source").agg(F.map_from_entries(F.collect_list(F.struct("lang", "n"))).alias("h"))
    both = n.withColumn("h", F.map_zip_with("h", F.map_filter("h", lambda k, v: k == "en"), lambda k, a, b: F.coalesce(a, F.lit(0)) + F.coalesce(b, F.lit(0)) * 0))
    return both.select("source", F.coalesce(F.try_element_at("h", F.lit("en")), F.lit(0)).alias("en"), F.aggregate(F.map_values(F.map_filter("h", lambda k, v: k != "en")), F.lit(0).cast("long"), lambda a, x: a + x).alias("other"))


@query("op_scalar_json", "event_id:l k:l again:s", "@@ SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k, '{\"k\":' || CAST(json_extract(props, '$.k') AS BIGINT) || '}' AS again FROM events")
def _json(spark, sf_dir):
    return load(spark, sf_dir, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"), F.to_json(F.from_json("props", "k long")).alias("again"))


@query("op_pivot", "source:s de:l en:l es:l fr:l", "@@ SELECT source, " + ", ".join(f"count(*) FILTER (WHERE lang = '{x}') AS {x}" for x in ("de", "en", "es", "fr")) + " FROM documents GROUP BY source")
def _pivot(spark, sf_dir):
    return load(spark, sf_dir, "documents").groupBy("source").pivot("lang", ["de", "en", "es", "fr"]).count().fillna(0)


@query("op_unpivot", "subpop_key:s stat:s value:d", _PAIRS + "@@ " + " UNION ALL ".join(f"SELECT subpop_key, '{s}' AS stat, CAST({s} AS DOUBLE) AS value FROM truth" for s in ("l1", "l2", "card")))
def _unpivot(spark, sf_dir):
    from ..operators.measures import long_form

    return long_form(_truth(spark, sf_dir), ("l1", "l2", "card"))


@query("op_sample_hash", "event_id:l", "@@ SELECT event_id FROM events WHERE CAST('0x' || substr(md5('u|' || event_id), 1, 15) AS BIGINT) % 20 = 0")
def _sample(spark, sf_dir):
    return B.uniform_sample(load(spark, sf_dir, "events"), F.col("event_id").cast("string"), 20).select("event_id")


@query("op_sample_by", "lang:s n:l")
def _sample_by(spark, sf_dir):
    return load(spark, sf_dir, "documents").sampleBy("lang", {"en": 0.1, "fr": 0.5}, 3).groupBy("lang").agg(F.count(F.lit(1)).alias("n"))


# --- user functions ---

_BY_SOURCE = "by_m AS (SELECT source, m, count(*) AS f FROM (" + view_sql("docs") + ") GROUP BY ALL)"


def _by_source(spark, sf_dir):
    return view(spark, sf_dir, "docs").groupBy("source", "m").agg(F.count(F.lit(1)).alias("f"))


@query("op_udf_custom_g", "source:s g:d", _BY_SOURCE + "@@ SELECT source, sum(sqrt(f)) AS g FROM by_m GROUP BY source")
def _udf_g(spark, sf_dir):
    return _by_source(spark, sf_dir).withColumn("g", udfs.sqrt_g("f")).groupBy("source").agg(F.sum("g").alias("g"))


@query("op_udf_entropy_sql", "source:s h:d", _BY_SOURCE + "@@ SELECT source, ln(sum(f)) - sum(f * ln(f)) / sum(f) AS h FROM by_m GROUP BY source")
def _udf_entropy(spark, sf_dir):
    udfs.register(spark)
    return spark.sql("SELECT source, entropy_of(f) AS h FROM {by_m} GROUP BY source", by_m=_by_source(spark, sf_dir))


@query("op_udf_apply_in_pandas", "source:s m:l f:l", _BY_SOURCE + "@@ SELECT * FROM by_m QUALIFY row_number() OVER (PARTITION BY source ORDER BY f DESC, m) <= 3")
def _apply(spark, sf_dir):
    """Top entries of each group in Python: groups are value histograms, bounded by the metric's few values."""
    return _by_source(spark, sf_dir).groupBy("source").applyInPandas(lambda p: p.sort_values(["f", "m"], ascending=[False, True]).head(3), "source string, m long, f long")


@query("op_udtf_cuboids", "l_linenumber:l gid:l kept:l n:l", "@@ SELECT l_linenumber, gid, l_linenumber - bit_count(gid) AS kept, n FROM (SELECT l_linenumber, n, unnest(range(CAST(pow(2, l_linenumber) AS BIGINT))) AS gid FROM (SELECT l_linenumber, count(*) AS n FROM lineitem GROUP BY l_linenumber))")
def _udtf(spark, sf_dir):
    """Cuboids of as many dimensions as a line's number, for the lines of ``lineitem``: their counts fan out."""
    udfs.register(spark)
    lines = load(spark, sf_dir, "lineitem").groupBy("l_linenumber").agg(F.count(F.lit(1)).alias("n"))
    return spark.sql("SELECT l.l_linenumber, c.gid, c.kept, l.n FROM {lines} l, LATERAL explode_cuboids(CAST(l.l_linenumber AS INT)) c", lines=lines)


@query(
    "op_sql_functions",
    "quantity:l grid_row:l grid_col:l b:l n:l",
    "@@ SELECT quantity, r AS grid_row, c AS grid_col, length(bin(quantity * 24 + r * 8 + c + 1)) - 1 AS b, n FROM (SELECT CAST(l_quantity AS BIGINT) AS quantity, count(*) AS n FROM lineitem GROUP BY ALL), (SELECT unnest(range(3)) AS r), (SELECT unnest(range(8)) AS c)",
)
def _sql_functions(spark, sf_dir):
    """The quantities of ``lineitem``, with their lines, in each cell of a small grid: bit lengths of their places."""
    udfs.register(spark)
    lines = load(spark, sf_dir, "lineitem").groupBy(F.col("l_quantity").cast("long").alias("quantity")).agg(F.count(F.lit(1)).alias("n"))
    return spark.sql("SELECT quantity, grid_row, grid_col, bit_length_of(quantity * 24 + grid_row * 8 + grid_col + 1) AS b, n FROM {lines}, cells_of(3, 8)", lines=lines)
