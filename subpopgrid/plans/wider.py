"""Workloads over more views, parameters, engines and sizes than the short forms beside them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import udfs
from ..operators import baselines as B
from ..operators import bounded, fanout, grid
from ..operators import measures as M
from ..operators import universal as U
from ..schema import TIGHT, TINY, GridConfig, WorkloadSpec
from ..sources.tables import VIEWS, ZIPF_SPEC, load, scratch, spec_of, sql, view, view_sql, zipf, zipf_sql
from ..streaming import windows as SW
from . import config as C
from . import oracle as O
from .comparisons import _BASIC, _BY_SIZE, _KEY_CFGS, _SIZED, _coverage, _err_sql, _union
from .registry import query
from .streams import _SPEC, _pairs_sql, _stream, _text, _windowed

_MEAN = "SELECT stat, avg(abs(err)) AS mean_abs, count(*) AS n FROM big GROUP BY stat"


def _mean(errors: DataFrame, share: float) -> DataFrame:
    return M.qualifying(errors, share).groupBy("stat").agg(F.avg(F.abs("err")).alias("mean_abs"), F.count(F.lit(1)).alias("n"))


def _errors(df: DataFrame, s: WorkloadSpec, cfg: GridConfig) -> DataFrame:
    return M.relative_error(grid.estimate(grid.build_grid(df, s, cfg)), B.ground_truth(df, s))


# --- W1 by two dimensions ---


@query(
    "w_W1_hourly",
    "event_type:s hod:l entropy:d l1:d entropy_true:d l1_true:l",
    O.grid_ctes("video", TIGHT) + "@@ SELECT k.event_type, k.hod, e.entropy, e.l1, t.entropy AS entropy_true, t.l1 AS l1_true FROM (SELECT DISTINCT subpop_key, event_type, hod FROM pairs WHERE gid = 5) k JOIN estimates e ON k.subpop_key = e.subpop_key JOIN truth t ON k.subpop_key = t.subpop_key",
)
def _w1_hourly(spark, sf_dir):
    """The first example query by event type and hour."""
    df, s = view(spark, sf_dir, "video"), spec_of("video")
    keys = grid.StatQuery(("event_type", "hod"), ()).subpops(df, s)
    t = B.ground_truth(df, s).select("subpop_key", F.col("entropy").alias("entropy_true"), F.col("l1").alias("l1_true"))
    return keys.join(grid.estimate(grid.build_grid(df, s, TIGHT), keys), "subpop_key").join(t, "subpop_key")


# --- W2 by brand ---

_BRAND_VIEW = "SELECT p_brand, CAST(l_suppkey AS BIGINT) AS m, CAST(1 AS BIGINT) AS wgt FROM {lineitem} l JOIN {part} p ON l.l_partkey = p.p_partkey"
_BRAND = WorkloadSpec(dims=("p_brand",), weight="wgt", include_total=False)


@query(
    "w_W2_brand",
    "p_brand:s card:d card_true:l",
    O.grid_ctes((_BRAND_VIEW.format(lineitem="lineitem", part="part"), _BRAND), TIGHT) + "@@ SELECT k.p_brand, e.card, t.card AS card_true FROM (SELECT DISTINCT subpop_key, p_brand FROM pairs) k JOIN estimates e ON k.subpop_key = e.subpop_key JOIN truth t ON k.subpop_key = t.subpop_key",
)
def _w2_brand(spark, sf_dir):
    """The second example query by brand."""
    df = sql(spark, sf_dir, _BRAND_VIEW)
    keys = grid.StatQuery(("p_brand",), ()).subpops(df, _BRAND)
    t = B.ground_truth(df, _BRAND).select("subpop_key", F.col("card").alias("card_true"))
    return keys.join(grid.estimate(grid.build_grid(df, _BRAND, TIGHT), keys), "subpop_key").join(t, "subpop_key")


# --- offline samples at one in a hundred ---

_RARE = 100
_LINE_TEXT = "l_orderkey || '-' || l_linenumber || '-' || l_partkey"


def _hash_sql(one_in: int) -> str:
    return f"SELECT * FROM ({view_sql('flow_card')}) WHERE CAST('0x' || substr(md5('v|' || m), 1, 15) AS BIGINT) % {one_in} = 0"


@query("base_hash_sample_1pct", "subpop_key:s card:l", O.pairs_ctes(_hash_sql(_RARE), spec_of("flow_card")) + f"@@ SELECT subpop_key, count(*) * {_RARE} AS card FROM pairs GROUP BY subpop_key")
def _hash_rare(spark, sf_dir):
    """Cardinality from a hash sample of one value in a hundred."""
    return B.hash_sample_card(view(spark, sf_dir, "flow_card"), spec_of("flow_card"), _RARE)


def _sampled_view_sql(name: str, one_in: int) -> str:
    kept = f"(SELECT * FROM lineitem WHERE CAST('0x' || substr(md5('u|' || {_LINE_TEXT}), 1, 15) AS BIGINT) % {one_in} = 0)"
    return view_sql(name).replace("FROM lineitem l", f"FROM {kept} l")


def _sampled_view(spark, sf_dir, name: str, one_in: int) -> DataFrame:
    text = F.concat_ws("-", *(F.col(c).cast("string") for c in ("l_orderkey", "l_linenumber", "l_partkey")))
    return sql(spark, sf_dir, VIEWS[name][1], lineitem=B.uniform_sample(load(spark, sf_dir, "lineitem"), text, one_in))


def _scaled(one_in: int) -> str:
    p = 1 / one_in
    return f"SELECT subpop_key, l1 * {one_in} AS l1, (l2 - (1 - {p}) * l1) / ({p} * {p}) AS l2, card, card * {one_in} AS card_scaled, entropy FROM truth"


@query("base_uniform_sample_1pct", "subpop_key:s l1:l l2:d card:l card_scaled:l entropy:d", O.pairs_ctes(_sampled_view_sql("flow_card", _RARE), spec_of("flow_card")) + ", " + O.TRUTH + "@@ " + _scaled(_RARE))
def _uniform_rare(spark, sf_dir):
    """L1, L2 and entropy from a uniform sample of one record in a hundred."""
    return B.sample_stats(_sampled_view(spark, sf_dir, "flow_card", _RARE), spec_of("flow_card"), _RARE)


# --- statistic-specific grids that answer queries ---

_OWN = TIGHT.but(layers=1, w=64)


def _point_sql(cfg: GridConfig) -> str:
    at = f"({cfg.layers - 1} + j * {cfg.cs_bits + 1})"
    probes = f"probes AS MATERIALIZED (SELECT *, (x >> CAST({at} AS INT)) & {cfg.w_cs - 1} AS cs_col FROM cells, (SELECT unnest(range({cfg.r_cs})) AS j))"
    sums = "sums_of AS MATERIALIZED (SELECT grid_row, grid_col, j, cs_col, sum(f) AS c FROM probes GROUP BY ALL)"
    least = "least_of AS (SELECT p.subpop_key, p.m, p.grid_row, min(c) AS c FROM probes p JOIN sums_of q ON p.grid_row = q.grid_row AND p.grid_col = q.grid_col AND p.j = q.j AND p.cs_col = q.cs_col GROUP BY ALL)"
    return ", ".join([probes, sums, least])


@query(
    "grid_cell_countmin_points",
    "subpop_key:s m:l f:l",
    O.pairs_ctes(view_sql("docs"), spec_of("docs", max_order=2)) + ", " + O.cells_ctes(_OWN) + ", " + _point_sql(_OWN) + "@@ SELECT subpop_key, m, min(c) AS f FROM least_of GROUP BY subpop_key, m",
)
def _countmin_points(spark, sf_dir):
    """Frequencies of all pairs from a grid of unsigned counters: the least counter over cells and rows, never too small."""
    pairs = fanout.pair_counts(view(spark, sf_dir, "docs"), spec_of("docs", max_order=2))
    return B.countmin_points(pairs, _OWN)


@query("grid_cell_hll_estimates", "subpop_key:s card:l truth:l")
def _hll_estimates(spark, sf_dir):
    """Cardinalities of subpopulations from a grid of cardinality sketches of pairs: the least cell, less what others bring."""
    df, s = view(spark, sf_dir, "flow_card"), spec_of("flow_card", max_order=1)
    est = B.hll_grid_estimates(df, s, TIGHT.but(w=512, hash_fn="xxhash64"))
    return est.join(B.ground_truth(df, s).select("subpop_key", F.col("card").alias("truth")), "subpop_key")


# --- W6 on the network views ---


def _w6_sql(name: str, **spec) -> str:
    s = spec_of(name, **spec)
    sampled = ", ".join([O.pairs_ctes(_sampled_view_sql(name, 10), s), O.TRUTH])
    return (
        f"SELECT '{name}' AS view, 'grid' AS engine, * FROM (WITH {_err_sql(name, TIGHT, **spec)} {_BY_SIZE}) UNION ALL "
        f"SELECT '{name}' AS view, 'sample' AS engine, * FROM (WITH sampled AS (WITH {sampled} {_scaled(10)}), {O.pairs_ctes(view_sql(name), s)}, {O.TRUTH}, {O.error_ctes(est='sampled')} {_BY_SIZE})"
    )


_W6 = (("flow", {"max_order": 2}), ("flow_card", {}))


@query("w_W6_flow", "view:s engine:s " + _SIZED, "@@ " + " UNION ALL ".join(_w6_sql(n, **m) for n, m in _W6))
def _w6_flow(spark, sf_dir):
    """Error against the normalised sum on both network views: grid and a 10 % sample."""
    parts = []
    for name, more in _W6:
        df, s = view(spark, sf_dir, name), spec_of(name, **more)
        true = B.ground_truth(df, s)
        for engine, est in (("grid", grid.estimate(grid.build_grid(df, s, TIGHT))), ("sample", B.sample_stats(_sampled_view(spark, sf_dir, name, 10), s, 10))):
            parts.append(M.error_by_size(M.relative_error(est, true)).withColumn("engine", F.lit(engine)).withColumn("view", F.lit(name)))
    return _union(parts)


# --- W8: state of six engines, two sizes, one to five dimensions ---

_STATE_CFG = TINY.but(heap_value="tracked")
_OWN_K = 20
_FLOW = VIEWS["flow"][0]
_PART = {"quarter": " WHERE l.l_orderkey % 4 = 0", "all": ""}


def _w8_spec(d: int) -> WorkloadSpec:
    return WorkloadSpec(dims=_FLOW[:d], weight="wgt")


def _w8_sql(size: str, d: int) -> str:
    s = _w8_spec(d)
    chain = ", ".join([O.pairs_ctes(view_sql("flow") + _PART[size], s), O.cells_ctes(_STATE_CFG)])
    sample = O.pairs_ctes(_sampled_view_sql("flow", 10) + _PART[size], s)
    return (
        f"SELECT '{size}' AS size, {d} AS d, * FROM (WITH {chain} SELECT (SELECT count(DISTINCT subpop_key) FROM pairs) AS subpops, "
        f"(SELECT 16 * sum(least(n, {_STATE_CFG.k})) FROM (SELECT count(*) AS n FROM cells GROUP BY grid_row, grid_col, depth)) AS grid_bytes, "
        f"(SELECT count(*) * 24 FROM recs) AS raw_bytes, (SELECT count(*) * 24 FROM pairs) AS kv_bytes, (SELECT count(*) * 24 FROM pairs WHERE gid = 0) AS rollup_bytes, "
        f"(SELECT count(*) * 24 FROM (WITH {sample} SELECT * FROM pairs)) AS sample_bytes, "
        f"(SELECT 16 * sum(least(n, {_OWN_K})) FROM (SELECT count(*) AS n FROM cells WHERE grid_row = 0 GROUP BY subpop_key, depth)) AS own_bytes)"
    )


@query("w_W8_engines", "size:s d:l subpops:l grid_bytes:l raw_bytes:l kv_bytes:l rollup_bytes:l sample_bytes:l own_bytes:l", "@@ " + " UNION ALL ".join(_w8_sql(z, d) for z in _PART for d in range(1, 6)))
def _w8_engines(spark, sf_dir):
    """State of grid, raw rows, key-value store, roll-up, 10 % sample and a sketch per subpopulation; the grid's levels off."""
    parts = []
    for size, where in _PART.items():
        whole = sql(spark, sf_dir, VIEWS["flow"][1] + where)
        text = F.concat_ws("-", *(F.col(c).cast("string") for c in ("l_orderkey", "l_linenumber", "l_partkey")))
        sample = sql(spark, sf_dir, VIEWS["flow"][1] + where, lineitem=B.uniform_sample(load(spark, sf_dir, "lineitem"), text, 10))
        for d in range(1, 6):
            s = _w8_spec(d)
            pairs = fanout.pair_counts(whole, s)
            cells = U.to_cells(pairs, _STATE_CFG)
            capped = lambda rows, k: rows.agg(F.count(F.lit(1)).alias("n")).agg((16 * F.sum(F.least("n", F.lit(k)))).alias("b"))
            one = pairs.agg(F.count_distinct("subpop_key").alias("subpops"), (F.count(F.lit(1)) * 24).alias("kv_bytes"), (F.count(F.when(F.col("gid") == 0, 1)) * 24).alias("rollup_bytes"))
            for name, frame in (
                ("grid_bytes", capped(cells.groupBy(*U.CELL, "depth"), _STATE_CFG.k)),
                ("own_bytes", capped(cells.where("grid_row = 0").groupBy("subpop_key", "depth"), _OWN_K)),
                ("raw_bytes", whole.agg((F.count(F.lit(1)) * 24).alias("b"))),
                ("sample_bytes", fanout.pair_counts(sample, s).agg((F.count(F.lit(1)) * 24).alias("b"))),
            ):
                one = one.crossJoin(frame.withColumnRenamed("b", name))  # one row each
            parts.append(one.withColumn("size", F.lit(size)).withColumn("d", F.lit(d)))
    return _union(parts)


# --- W9: width, inner width, heap and layers, four statistics, the suggested point ---

_W9_BASE = TIGHT.but(w=16, w_cs=64, k=50, layers=8)
#: The wanted error, failure and least share; distinct pairs are those of the view at the smallest size, memory as the base has.
SUGGESTED = C.recommend(0.5, 0.1, 0.02, 20_000, memory=C.model_bytes(_W9_BASE)).but(hash_fn="md5")
_W9 = [("base", _W9_BASE), *((f"{p}={v}", _W9_BASE.but(**{p: v})) for p, vs in (("w", (4, 64)), ("w_cs", (16, 256)), ("k", (10, 200)), ("layers", (4, 10))) for v in vs), ("suggested", SUGGESTED)]
_W9_VIEW = ("flow_card", {"max_order": 2})
_W9_COLS = "point:s bytes:l stat:s mean_abs:d n:l on_frontier:b"
_FRONT_BY_STAT = "SELECT *, coalesce(mean_abs < min(mean_abs) OVER (PARTITION BY stat ORDER BY bytes, mean_abs, point ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), true) AS on_frontier FROM (SELECT * REPLACE (round(mean_abs, 9) AS mean_abs) FROM ({}))"


def _fronts(parts: list[DataFrame], by: tuple[str, ...]) -> DataFrame:
    """Frontiers of a sweep's few rows, one for each value of ``by``."""
    from pyspark.sql import Window as W

    rows = _union(parts).withColumn("mean_abs", F.round("mean_abs", 9))
    best = F.min("mean_abs").over(W.partitionBy(*by).orderBy("bytes", "mean_abs", "point").rowsBetween(W.unboundedPreceding, -1))
    return rows.withColumn("on_frontier", best.isNull() | (F.col("mean_abs") < best))


@query(
    "w_W9_statistics",
    _W9_COLS,
    "@@ " + _FRONT_BY_STAT.format(" UNION ALL ".join(f"SELECT '{n}' AS point, {C.model_bytes(c)} AS bytes, * FROM (WITH {_err_sql(_W9_VIEW[0], c, **_W9_VIEW[1])}, {O.qualifying_cte(0.002)} {_MEAN})" for n, c in _W9)),
)
def _w9_statistics(spark, sf_dir):
    """One parameter at a time around a base, for L1, L2, cardinality and entropy, beside the suggested configuration."""
    df, s = view(spark, sf_dir, _W9_VIEW[0]), spec_of(_W9_VIEW[0], **_W9_VIEW[1])
    return _fronts([_mean(_errors(df, s, c), 0.002).select(F.lit(n).alias("point"), F.lit(C.model_bytes(c)).alias("bytes"), "stat", "mean_abs", "n") for n, c in _W9], ("stat",))


# --- W11: seconds of the basic and the optimised build ---


@query("w_W11_runtime", "variant:s point:s bytes:l seconds:d mean_abs:d on_frontier:b")
def _w11_runtime(spark, sf_dir):
    """(runtime, error) of both variants of the bounded builder over four sizes."""
    df, s = view(spark, sf_dir, "flow"), spec_of("flow", max_order=2)
    true, rows = B.ground_truth(df, s), []
    for variant, changes in (("basic", {**_BASIC, "merge_mode": "full"}), ("optimised", {})):
        for w, k in ((8, 25), (32, 50), (64, 100), (128, 200)):
            cfg = TIGHT.but(w=w, k=k, hash_fn="xxhash64", heap_value="tracked", **changes)
            error, seconds = M.timed(lambda cfg=cfg: M.qualifying(M.relative_error(grid.estimate(bounded.build_bounded(df, s, cfg)), true), 0.002).agg(F.avg(F.abs("err"))).first()[0])
            rows.append((variant, f"w={w},k={k}", C.model_bytes(cfg), seconds, error))
    out = spark.createDataFrame(rows, "variant string, point string, bytes long, seconds double, mean_abs double")
    from pyspark.sql import Window as W

    best = F.min("mean_abs").over(W.partitionBy("variant").orderBy("seconds").rowsBetween(W.unboundedPreceding, -1))
    return out.withColumn("on_frontier", best.isNull() | (F.col("mean_abs") < best))


# --- W12: frontiers on skewed data ---

_W12_POINTS = [(f"w={w},k={k}", TIGHT.but(w=w, k=k, layers=8)) for w, k in ((2, 10), (4, 20), (8, 40), (16, 80))]
_W12_ALPHAS = (0.7, 0.99)


def _w12_sql(alpha: float, name: str, cfg: GridConfig) -> str:
    chain = O.grid_ctes((zipf_sql(alpha, "(SELECT count(*) FROM lineitem)"), ZIPF_SPEC), cfg)
    return f"SELECT {alpha} AS alpha, '{name}' AS point, {C.model_bytes(cfg)} AS bytes, * FROM (WITH {chain}, {O.error_ctes()}, {O.qualifying_cte(0.02)} {_MEAN})"


@query(
    "w_W12_frontier",
    "alpha:d " + _W9_COLS,
    "@@ " + _FRONT_BY_STAT.replace("PARTITION BY stat", "PARTITION BY alpha, stat").format(" UNION ALL ".join(_w12_sql(a, n, c) for a in _W12_ALPHAS for n, c in _W12_POINTS)),
)
def _w12_frontier(spark, sf_dir):
    """Memory against error for skews of 0.7 and 0.99."""
    n, parts = load(spark, sf_dir, "lineitem").count(), []
    for a in _W12_ALPHAS:
        df = zipf(spark, a, n)
        parts += [_mean(_errors(df, ZIPF_SPEC, c), 0.02).select(F.lit(a).alias("alpha"), F.lit(p).alias("point"), F.lit(C.model_bytes(c)).alias("bytes"), "stat", "mean_abs", "n") for p, c in _W12_POINTS]
    return _fronts(parts, ("alpha", "stat"))


# --- W13: grid beside the key-value store on small data ---


@query(
    "w_W13_kv",
    "view:s grid_bytes:l kv_bytes:l subpops:l",
    "@@ " + " UNION ALL ".join(f"SELECT '{v}' AS view, * FROM (WITH {O.pairs_ctes(view_sql(v), spec_of(v))}, {O.cells_ctes(_STATE_CFG)} SELECT (SELECT 16 * sum(least(n, {_STATE_CFG.k})) FROM (SELECT count(*) AS n FROM cells GROUP BY grid_row, grid_col, depth)) AS grid_bytes, (SELECT 24 * count(*) FROM pairs) AS kv_bytes, (SELECT count(DISTINCT subpop_key) FROM pairs) AS subpops)" for v in ("video", "conv", "docs")),
)
def _w13_kv(spark, sf_dir):
    """State on smaller data, where the key-value store competes."""
    parts = []
    for v in ("video", "conv", "docs"):
        pairs = fanout.pair_counts(view(spark, sf_dir, v), spec_of(v))
        heaps = U.to_cells(pairs, _STATE_CFG).groupBy(*U.CELL, "depth").agg(F.count(F.lit(1)).alias("n")).agg((16 * F.sum(F.least("n", F.lit(_STATE_CFG.k)))).alias("grid_bytes"))
        parts.append(pairs.agg((24 * F.count(F.lit(1))).alias("kv_bytes"), F.count_distinct("subpop_key").alias("subpops")).crossJoin(heaps).withColumn("view", F.lit(v)))  # one row each
    return _union(parts)


# --- W14: a grid each minute, heaps cut ---

_MINUTE_CFG = TINY.but(heap_value="tracked", k=3, layers=4)


def _minute_sql(cfg: GridConfig) -> str:
    cells = O.cells_ctes(cfg).replace("SELECT subpop_key, m, f, r AS grid_row", "SELECT w AS win, subpop_key, m, f, r AS grid_row")
    part = "PARTITION BY win, grid_row, grid_col, layer"
    heap = f"SELECT *, depth AS layer FROM cells QUALIFY row_number() OVER ({part} ORDER BY f DESC, subpop_key, m) <= {cfg.k}"
    every = f"SELECT * FROM (SELECT * EXCLUDE (layer), unnest(range(0, depth + 1)) AS layer FROM heaps) QUALIFY row_number() OVER ({part} ORDER BY f DESC, subpop_key, m) <= {cfg.k}"
    weight = f"CASE WHEN layer < {cfg.layers - 1} AND depth > layer THEN -1 ELSE 1 END * (1 << CAST(layer AS INT))"
    rows = f"SELECT win, subpop_key, grid_row, sum({weight} * f) AS l1, sum({weight} * f * f) AS l2, sum({weight}) AS card FROM nested GROUP BY ALL"
    med = ", ".join(f"list_sort(list_concat(list(CAST({n} AS DOUBLE)), list_transform(range({cfg.r} - count(*)), lambda i: CAST(0 AS DOUBLE))))[{cfg.r // 2 + 1}] AS {n}" for n in ("l1", "l2", "card"))
    return ", ".join([_pairs_sql(60), cells, f"heaps AS MATERIALIZED ({heap})", f"nested AS MATERIALIZED ({every})", f"sums AS ({rows})"]) + f"@@ {_windowed('win')}, subpop_key, count(*) AS found_rows, {med} FROM sums GROUP BY sums.win, subpop_key"


@query("w_W14_minutes", "win:s subpop_key:s found_rows:l l1:d l2:d card:d", _minute_sql(_MINUTE_CFG))
def _w14_minutes(spark, sf_dir):
    """Periodic estimation: a grid of cut heaps for every minute, from the store that micro-batches merge into."""
    pairs = SW.merge_into_store(_stream(spark, sf_dir), _SPEC, 60, scratch(spark, "minutes"))
    return SW.window_estimates(pairs.select("win", "subpop_key", "m", "f"), _MINUTE_CFG).select(_text(), "subpop_key", "found_rows", "l1", "l2", "card")


# --- W15, W16: key modes and rows on the network view, all cuboids ---


def _each_sql(column: str, cfgs, body: str) -> str:
    return "@@ " + " UNION ALL ".join(f"SELECT {label} AS {column}, * FROM (WITH {_err_sql('flow', cfg)}, {O.qualifying_cte(0.002)} {body})" for label, cfg in cfgs)


_ROWS = [(r, TIGHT.but(r=r)) for r in (1, 3, 5)]


@query("w_W15_flow", "key_mode:s stat:s mean_abs:d n:l", _each_sql("key_mode", [(f"'{k}'", c) for k, c in _KEY_CFGS], _MEAN))
def _w15_flow(spark, sf_dir):
    """Pair keys against bare values, over all cuboids of the network view."""
    df, s = view(spark, sf_dir, "flow"), spec_of("flow")
    true = B.ground_truth(df, s)
    est = lambda cfg: grid.estimate(grid.build_grid(df, s, cfg), true.select("subpop_key"))
    return _union([_mean(M.relative_error(est(cfg), true), 0.002).withColumn("key_mode", F.lit(k)) for k, cfg in _KEY_CFGS])


@query("w_W16_flow", "r:l stat:s share:d n:l", _each_sql("r", _ROWS, "SELECT stat, avg(CASE WHEN abs(err) <= 0.2 THEN 1.0 ELSE 0 END) AS share, count(*) AS n FROM big GROUP BY stat"))
def _w16_flow(spark, sf_dir):
    """More rows, steadier medians, over all cuboids of the network view."""
    df, s = view(spark, sf_dir, "flow"), spec_of("flow")
    return _union([M.within(M.qualifying(_errors(df, s, cfg), 0.002), 0.2).withColumn("r", F.lit(r)) for r, cfg in _ROWS])


# --- W17: coverage on the network view and on skewed data, over salts ---

_W17 = [(v, z) for v in ("flow", "zipf") for z in (1, 2, 3)]


def _w17_sql(name: str, salt: int) -> str:
    cfg = TIGHT.but(salt=salt)
    if name == "flow":
        return f"SELECT 'flow' AS view, {salt} AS salt, * FROM (WITH {_err_sql('flow', cfg, max_order=2)} {_coverage()})"
    chain = O.grid_ctes((zipf_sql(0.99, "(SELECT count(*) FROM lineitem)"), ZIPF_SPEC), cfg) + ", " + O.error_ctes()
    return f"SELECT 'zipf' AS view, {salt} AS salt, * FROM (WITH {chain} {_coverage()})"


@query("w_W17_flow_zipf", "view:s salt:l stat:s coverage:d n:l", "@@ " + " UNION ALL ".join(_w17_sql(v, z) for v, z in _W17))
def _w17_wide(spark, sf_dir):
    """Estimates inside the theoretical interval on the network view and on skewed data, over salts."""
    n, parts = load(spark, sf_dir, "lineitem").count(), []
    for v, z in _W17:
        df, s = (view(spark, sf_dir, "flow"), spec_of("flow", max_order=2)) if v == "flow" else (zipf(spark, 0.99, n), ZIPF_SPEC)
        cfg = TIGHT.but(salt=z)
        parts.append(M.bound_coverage(_errors(df, s, cfg), cfg, 0.1).withColumn("salt", F.lit(z)).withColumn("view", F.lit(v)))
    return _union(parts)


# --- sets and maps of heaps, cells of a key as a table function ---

_HH = {"cuboids": (("l_returnflag",), ("l_linestatus",), ("l_returnflag", "l_linenumber"))}
_HH_SQL = (
    O.grid_ctes("flow_card", TINY, **_HH)
    + ", hh AS (SELECT subpop_key, m, list_sort(list(f)) AS fs FROM nested WHERE layer = 0 GROUP BY ALL HAVING count(*) > 1), found_hh AS (SELECT h.subpop_key, m FROM hh h JOIN estimates e ON h.subpop_key = e.subpop_key WHERE fs[(len(fs) - 1) // 2 + 1] >= 0.011 * l1), "
    "true_hh AS (SELECT p.subpop_key, m FROM pairs p JOIN truth t ON p.subpop_key = t.subpop_key WHERE f >= 0.011 * l1)"
)
for _name, _how in (("both", "true_hh INTERSECT SELECT * FROM found_hh"), ("missed", "true_hh EXCEPT SELECT * FROM found_hh"), ("false", "found_hh EXCEPT SELECT * FROM true_hh")):

    @query(f"op_set_heavy_hitters_{_name}", "subpop_key:s m:l", _HH_SQL + f"@@ SELECT * FROM {_how}")
    def _hh_sets(spark, sf_dir, which=_name):
        """Heavy hitters of the grid and of the truth, compared as sets."""
        df, s = view(spark, sf_dir, "flow_card"), spec_of("flow_card", **_HH)
        found = grid.heavy_hitters(grid.build_grid(df, s, TINY), 0.011).select("subpop_key", "m")
        pairs = fanout.pair_counts(df, s)
        true = pairs.join(B.ground_truth(df, s).select("subpop_key", "l1"), "subpop_key").where("f >= 0.011 * l1").select("subpop_key", "m")
        return {"both": true.intersect(found), "missed": true.subtract(found), "false": found.subtract(true)}[which]


@query("op_map_merge_heaps", "event_type:s m:l f:l", "@@ SELECT event_type, CAST(floor(value / 10) AS BIGINT) AS m, count(*) AS f FROM events GROUP BY ALL")
def _map_merge(spark, sf_dir):
    """Two parts' heaps held as maps (value -> count) and merged by key, then taken apart again."""
    e = load(spark, sf_dir, "events").select("event_type", "event_id", F.floor(F.col("value") / 10).cast("long").alias("m"))
    held = lambda rows, name: rows.groupBy("event_type", "m").agg(F.count(F.lit(1)).alias("f")).groupBy("event_type").agg(F.map_from_entries(F.collect_list(F.struct("m", "f"))).alias(name))
    a, b = held(e.where("event_id % 2 = 0"), "a"), held(e.where("event_id % 2 = 1"), "b")
    none = F.create_map().cast("map<bigint,bigint>")
    both = a.join(b, "event_type", "full").select("event_type", F.map_zip_with(F.coalesce("a", none), F.coalesce("b", none), lambda k, x, y: F.coalesce(x, F.lit(0)) + F.coalesce(y, F.lit(0))).alias("h"))
    return both.select("event_type", F.explode("h").alias("m", "f"))


_CELL_CFG = TINY


@query(
    "op_udtf_subpop_cells",
    "subpop_key:s grid_row:l grid_col:l",
    O.pairs_ctes(view_sql("conv"), spec_of("conv")) + f"@@ SELECT subpop_key, r AS grid_row, CAST('0x' || substr(md5('s0|' || subpop_key), CAST(r * 10 + 1 AS INT), 10) AS BIGINT) % {_CELL_CFG.w} AS grid_col FROM (SELECT DISTINCT subpop_key FROM pairs), (SELECT unnest(range(3)) AS r)",
)
def _subpop_cells(spark, sf_dir):
    """The cells of every subpopulation by a table function, as SQL users ask for them."""
    udfs.register(spark)
    keys = fanout.pair_counts(view(spark, sf_dir, "conv"), spec_of("conv")).select("subpop_key").distinct()
    return spark.sql(f"SELECT k.subpop_key, c.grid_row, c.grid_col FROM {{keys}} k, LATERAL subpop_cells(k.subpop_key, {_CELL_CFG.r}, {_CELL_CFG.w}, 0) c", keys=keys)
