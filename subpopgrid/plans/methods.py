"""Queries of the methods and their variants: fan-out, hashing, sketches, grid, merges, configuration."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import statistics as S
from ..functions.hashing import add_cells
from ..operators import baselines as B
from ..operators import bounded, countsketch, fanout, grid, merge, store
from ..operators import universal as U
from ..schema import TIGHT, TINY, GridConfig
from ..sources.tables import load, scratch, spec_of, view, view_sql
from . import config as C
from . import oracle as O
from .registry import query

# --- fan-out ---

_FAN = "gid:l subpop_key:s m:l f:l"


def _pairs_sql(name: str, **spec) -> str:
    return O.pairs_ctes(view_sql(name), spec_of(name, **spec)) + "@@ SELECT * FROM pairs"


def _fan(name: str, view_name: str, pre: bool | None, **spec) -> None:
    @query(f"fanout_{name}", _FAN, _pairs_sql(view_name, **spec))
    def run(spark, sf_dir):
        df, s = view(spark, sf_dir, view_name), spec_of(view_name, **spec)
        if pre is None:
            return fanout.fan_out(df, s).groupBy("gid", "subpop_key", "m").agg(F.sum("wgt").alias("f"))
        return fanout.pair_counts(df, s, preaggregated=pre)


_fan("cube", "conv", None)
_fan("no_total", "docs", None, include_total=False)
_fan("max_order_2", "video", False, max_order=2)
_fan("listed", "flow_card", False, cuboids=(("l_returnflag", "l_linestatus"), ("l_linenumber",), ()))
_fan("preaggregated", "flow_card", True)
_fan("null_dims", "docs_null", True)
_fan("derived_dims", "web", True)
_fan("array_source", "vec", True)
_fan("json_metric", "video_json", True, max_order=1)
_fan("weighted", "flow_sum", True, max_order=1)


@query(
    "shape_of_views",
    "name:s subpops:l pairs:l gs_l1:l gs_l2:l",
    ", ".join(f"v_{v} AS (WITH {O.pairs_ctes(view_sql(v), spec_of(v))} SELECT '{v}' AS name, count(DISTINCT subpop_key) AS subpops, count(*) AS pairs, sum(f) AS gs_l1, sum(f * f) AS gs_l2 FROM pairs)" for v in ("video", "flow_card", "docs", "conv"))
    + "@@ " + " UNION ALL ".join(f"SELECT * FROM v_{v}" for v in ("video", "flow_card", "docs", "conv")),
)
def _shapes(spark, sf_dir):
    parts = [fanout.shape(view(spark, sf_dir, v), spec_of(v)).withColumn("name", F.lit(v)) for v in ("video", "flow_card", "docs", "conv")]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


# --- hashing ---


def _conv_pairs(spark, sf_dir):
    return fanout.pair_counts(view(spark, sf_dir, "conv"), spec_of("conv"))


def _cells_sql(cfg: GridConfig, name: str = "conv") -> str:
    return O.pairs_ctes(view_sql(name), spec_of(name)) + ", " + O.cells_ctes(cfg)


_MANY = TINY.but(hash_mode="many")
_SHARED = TINY.but(row_bits="shared")
_CELL = "grid_row:l grid_col:l subpop_key:s m:l f:l x:l depth:l"
for _name, _cfg in (("fields", TINY), ("many_mode", _MANY), ("shared_bits", _SHARED), ("metric_keys", TINY.but(key_mode="metric"))):

    @query(f"hash_{_name}", _CELL, _cells_sql(_cfg) + "@@ SELECT * FROM cells")
    def _fields(spark, sf_dir, cfg=_cfg):
        return U.to_cells(_conv_pairs(spark, sf_dir), cfg)


@query("hash_depth_histogram", "grid_row:l depth:l n:l", _cells_sql(TIGHT, "video") + "@@ SELECT grid_row, depth, count(*) AS n FROM cells GROUP BY ALL")
def _depths(spark, sf_dir):
    return U.to_cells(fanout.pair_counts(view(spark, sf_dir, "video"), spec_of("video")), TIGHT).groupBy("grid_row", "depth").agg(F.count(F.lit(1)).alias("n"))


@query("hash_cells_of_subpops", "subpop_key:s grid_row:l grid_col:l", _cells_sql(TINY, "docs") + "@@ SELECT DISTINCT subpop_key, grid_row, grid_col FROM cells")
def _cells(spark, sf_dir):
    keys = fanout.pair_counts(view(spark, sf_dir, "docs"), spec_of("docs")).select("subpop_key").distinct()
    return add_cells(keys, TINY)


# --- counter sketches over part keys ---

_WIDTH, _ROWS = 256, 3
_KEYS = "keys AS MATERIALIZED (SELECT CAST(l_partkey AS VARCHAR) AS k, count(*) AS f FROM lineitem GROUP BY l_partkey)"


def _keys(spark, sf_dir):
    return load(spark, sf_dir, "lineitem").groupBy(F.col("l_partkey").cast("string").alias("k")).agg(F.count(F.lit(1)).alias("f"))


def _field(what: str, r: str = "r") -> str:
    return f"CAST('0x' || substr(md5('{what}0.' || {r} || '|' || k), 1, 15) AS BIGINT)"


def _counter_sql(rows: int) -> str:
    return _KEYS + f", probes AS MATERIALIZED (SELECT k, f, r AS row, {_field('c')} % {_WIDTH} AS col FROM keys, (SELECT unnest(range({rows})) AS r)), counters AS MATERIALIZED (SELECT row, col, CAST(sum(f) AS BIGINT) AS c FROM probes GROUP BY ALL)"


_CS = (
    _KEYS + f", probes AS MATERIALIZED (SELECT k, f, r AS row, {_field('b')} % {_WIDTH} AS col, {_field('s')} % 2 * 2 - 1 AS s FROM keys, (SELECT unnest(range({_ROWS})) AS r)), "
    f"counters AS MATERIALIZED (SELECT row, col, CAST(sum(s * f) AS BIGINT) AS c FROM probes GROUP BY ALL), est AS MATERIALIZED (SELECT k, list_sort(list(s * c))[{_ROWS // 2 + 1}] AS estimate FROM probes JOIN counters USING (row, col) GROUP BY k)"
)


@query("counter_single_row", "row:l col:l c:l", _counter_sql(1) + "@@ SELECT * FROM counters")
def _counter1(spark, sf_dir):
    return countsketch.hash_counter(_keys(spark, sf_dir), "k", _WIDTH)


for _name, _agg in (("min", "min(c)"), ("median", f"list_sort(list(c))[{_ROWS // 2 + 1}]")):

    @query(f"counter_rows_{_name}", "k:s estimate:l", _counter_sql(_ROWS) + f"@@ SELECT k, {_agg} AS estimate FROM probes JOIN counters USING (row, col) GROUP BY k")
    def _counter_rows(spark, sf_dir, how=_name):
        keys = _keys(spark, sf_dir)
        return countsketch.counter_estimate(keys, "k", countsketch.hash_counter(keys, "k", _WIDTH, _ROWS), _WIDTH, _ROWS, how)


@query("cs_counters", "row:l col:l c:l", _CS + "@@ SELECT * FROM counters")
def _cs1(spark, sf_dir):
    return countsketch.count_sketch(_keys(spark, sf_dir), "k", _WIDTH, _ROWS)


@query("cs_point_estimate", "k:s estimate:l", _CS + "@@ SELECT * FROM est")
def _cs2(spark, sf_dir):
    keys = _keys(spark, sf_dir)
    return countsketch.cs_estimate(keys, "k", countsketch.count_sketch(keys, "k", _WIDTH, _ROWS), _WIDTH, _ROWS)


@query("cs_topk", "k:s estimate:l place:l", _CS + "@@ SELECT *, row_number() OVER (ORDER BY estimate DESC, k) AS place FROM est QUALIFY place <= 20")
def _cs3(spark, sf_dir):
    keys = _keys(spark, sf_dir)
    return countsketch.cs_topk(keys, "k", countsketch.count_sketch(keys, "k", _WIDTH, _ROWS), _WIDTH, _ROWS, 20)


# --- universal sketches and the grid ---

_HEAP = "grid_row:l grid_col:l layer:l subpop_key:s m:l f:l depth:l"
_VIDEO2 = {"max_order": 2}


def _state(spark, sf_dir, cfg: GridConfig, name: str = "video", **spec) -> grid.GridState:
    return grid.build_grid(view(spark, sf_dir, name), spec_of(name, **spec), cfg)


def _all(spark, sf_dir, name: str, **spec):
    return fanout.pair_counts(view(spark, sf_dir, name), spec_of(name, **spec)).select("subpop_key").distinct()


_NESTED = TINY.but(layer_mode="nested")
for _name, _cfg in (("nested", _NESTED), ("deepest", TINY)):

    @query(f"us_heaps_{_name}", _HEAP, O.grid_ctes("video", _cfg, **_VIDEO2) + "@@ SELECT * FROM heaps")
    def _heaps(spark, sf_dir, cfg=_cfg):
        return _state(spark, sf_dir, cfg, **_VIDEO2).heaps


for _name, _g in (("l1", "l1"), ("l2", "l2"), ("card", "card"), ("flogf", "flogf")):

    @query(f"us_gsum_{_name}", "subpop_key:s grid_row:l g:d", O.grid_ctes("video", TINY, **_VIDEO2) + f"@@ SELECT subpop_key, grid_row, {_g} AS g FROM row_sums")
    def _gsum(spark, sf_dir, g=_g):
        return grid.row_sums(_state(spark, sf_dir, TINY, **_VIDEO2)).withColumn("g", F.col(g))


_SINGLE = TINY.but(layers=1)


@query("us_single_layer", "subpop_key:s l1:d card:d", O.grid_ctes("video", _SINGLE, **_VIDEO2) + "@@ SELECT subpop_key, l1, card FROM estimates")
def _one_layer(spark, sf_dir):
    return grid.estimate(_state(spark, sf_dir, _SINGLE, **_VIDEO2), _all(spark, sf_dir, "video", **_VIDEO2))


@query("grid_counters", "grid_row:l grid_col:l layer:l cs_row:l cs_col:l c:l", O.grid_ctes("flow_card", TINY) + "@@ SELECT * FROM counters")
def _grid_counters(spark, sf_dir):
    cells = U.to_cells(fanout.pair_counts(view(spark, sf_dir, "flow_card"), spec_of("flow_card")), TINY)
    return U.counters(cells, TINY)


@query("grid_heaps", _HEAP, O.grid_ctes("flow_card", TIGHT) + "@@ SELECT * FROM heaps")
def _grid_heaps(spark, sf_dir):
    return _state(spark, sf_dir, TIGHT, "flow_card").heaps


_EST = "subpop_key:s found_rows:l l1:d l2:d card:d entropy:d"
_METRIC = TINY.but(key_mode="metric")
_ONE_ROW = TIGHT.but(r=1)
for _name, _view, _cfg, _spec in (
    ("estimate_pair", "flow_card", TIGHT, {}),
    ("estimate_metric", "video", _METRIC, _VIDEO2),
    ("vector_r1", "video", _ONE_ROW, _VIDEO2),
    ("all_stats", "video", TIGHT, {}),
    ("nested_many_hashes", "video", TINY.but(layer_mode="nested", hash_mode="many"), _VIDEO2),
    ("shared_bits", "video", _SHARED, _VIDEO2),
    ("tracked_heaps", "video", TIGHT.but(heap_value="tracked"), {}),
):

    @query(f"grid_{_name}", _EST, O.grid_ctes(_view, _cfg, **_spec) + "@@ SELECT * FROM estimates")
    def _estimate(spark, sf_dir, name=_view, cfg=_cfg, spec=_spec):
        return grid.estimate(_state(spark, sf_dir, cfg, name, **spec), _all(spark, sf_dir, name, **spec))


_RF = {"cuboids": (("l_returnflag",),)}


@query(
    "grid_heavy_hitters",
    "subpop_key:s m:l f:l",
    O.grid_ctes("flow_card", TIGHT, **_RF) + ", hh AS (SELECT subpop_key, m, list_sort(list(f)) AS fs FROM nested WHERE layer = 0 GROUP BY ALL HAVING count(*) > 1)"
    "@@ SELECT h.subpop_key, m, fs[(len(fs) - 1) // 2 + 1] AS f FROM hh h JOIN estimates e ON h.subpop_key = e.subpop_key WHERE fs[(len(fs) - 1) // 2 + 1] >= 0.005 * l1",
)
def _hitters(spark, sf_dir):
    return grid.heavy_hitters(_state(spark, sf_dir, TIGHT, "flow_card", **_RF), 0.005)


_MOMENTS = {"f0_5": "pow(f, 0.5)", "f1_5": "pow(f, 1.5)", "capped": "least(f, 10)"}


@query("grid_moments", "subpop_key:s found_rows:l f0_5:d f1_5:d capped:d", O.grid_ctes("video", TIGHT, _MOMENTS, **_VIDEO2) + "@@ SELECT * FROM estimates")
def _moments(spark, sf_dir):
    gs = [S.moment(0.5), S.moment(1.5), S.GSum("capped", "least(f, 10)")]
    return grid.estimate(_state(spark, sf_dir, TIGHT, **_VIDEO2), _all(spark, sf_dir, "video", **_VIDEO2), {g.name: g.column() for g in gs})


@query("grid_mean_std", "subpop_key:s mean:d std:d", O.grid_ctes("flow", TIGHT, max_order=1) + "@@ SELECT * FROM estimates")
def _mean_std(spark, sf_dir):
    return grid.estimate(_state(spark, sf_dir, TIGHT, "flow", max_order=1), _all(spark, sf_dir, "flow", max_order=1))


@query("grid_euclidean", "subpop_key:s l2_root:d", O.grid_ctes("docs", TIGHT) + "@@ SELECT subpop_key, sqrt(l2) AS l2_root FROM estimates")
def _euclid(spark, sf_dir):
    return grid.estimate(_state(spark, sf_dir, TIGHT, "docs"), _all(spark, sf_dir, "docs")).withColumn("l2_root", F.sqrt("l2"))


@query(
    "grid_median",
    "subpop_key:s median:l",
    O.grid_ctes("flow", TIGHT, max_order=1) + ", mass AS (SELECT subpop_key, grid_row, m, sum(w * f) AS mass FROM weighted GROUP BY ALL HAVING sum(w * f) > 0), "
    "ranked AS (SELECT *, sum(mass) OVER (PARTITION BY subpop_key, grid_row ORDER BY m) AS upto, sum(mass) OVER (PARTITION BY subpop_key, grid_row) AS whole FROM mass), "
    "mids AS (SELECT subpop_key, grid_row, min(m) AS mid FROM ranked WHERE 2 * upto >= whole GROUP BY ALL)"
    "@@ SELECT subpop_key, v[(len(v) - 1) // 2 + 1] AS median FROM (SELECT subpop_key, list_sort(list(mid)) AS v FROM mids GROUP BY subpop_key)",
)
def _median(spark, sf_dir):
    return grid.weighted_median(_state(spark, sf_dir, TIGHT, "flow", max_order=1))


_BINS = {f"bin{b}": f"CASE WHEN m > {10 * b} AND m <= {10 * b + 10} THEN f ELSE 0 END" for b in range(5)}


@query("grid_histogram", "subpop_key:s bin0:d bin1:d bin2:d bin3:d bin4:d", O.grid_ctes("flow", TIGHT, _BINS, max_order=1) + "@@ SELECT * FROM estimates")
def _histogram(spark, sf_dir):
    return grid.estimate(_state(spark, sf_dir, TIGHT, "flow", max_order=1), _all(spark, sf_dir, "flow", max_order=1), {k: F.expr(v) for k, v in _BINS.items()})


@query("grid_discover", "subpop_key:s l1:d", O.grid_ctes("video", TIGHT) + "@@ SELECT subpop_key, l1 FROM found WHERE l1 >= 320")
def _discover(spark, sf_dir):
    return grid.discover(_state(spark, sf_dir, TIGHT), "l1", 320)


@query(
    "grid_example_video",
    "event_type:s entropy:d l1:d",
    O.grid_ctes("video", TIGHT) + "@@ SELECT event_type, entropy, l1 FROM (SELECT DISTINCT subpop_key, event_type FROM pairs WHERE gid = 7) JOIN estimates USING (subpop_key)",
)
def _example_video(spark, sf_dir):
    df = view(spark, sf_dir, "video")
    return grid.StatQuery(("event_type",), ("entropy", "l1")).run(_state(spark, sf_dir, TIGHT), df)


@query(
    "grid_example_flow",
    "l_returnflag:s l_linestatus:s card:d",
    O.grid_ctes("flow_card", TIGHT) + "@@ SELECT l_returnflag, l_linestatus, card FROM (SELECT DISTINCT subpop_key, l_returnflag, l_linestatus FROM pairs WHERE gid = 3) JOIN estimates USING (subpop_key)",
)
def _example_flow(spark, sf_dir):
    df = view(spark, sf_dir, "flow_card")
    return grid.StatQuery(("l_returnflag", "l_linestatus"), ("card",)).run(_state(spark, sf_dir, TIGHT, "flow_card"), df)


@query("grid_cell_hll", "grid_row:l grid_col:l card:l")
def _cell_hll(spark, sf_dir):
    return B.grid_of_hll(view(spark, sf_dir, "video"), spec_of("video"), TINY)


@query("grid_cell_countmin", "grid_row:l grid_col:l bytes:l")
def _cell_cm(spark, sf_dir):
    return B.grid_of_countmin(view(spark, sf_dir, "conv"), spec_of("conv"), TINY)


@query("grid_cell_countsketch", "grid_row:l grid_col:l cs_row:l cs_col:l c:l", O.grid_ctes("docs", _SINGLE) + "@@ SELECT * FROM counters")
def _cell_cs(spark, sf_dir):
    return U.counters(U.to_cells(fanout.pair_counts(view(spark, sf_dir, "docs"), spec_of("docs")), _SINGLE), _SINGLE)


# --- merges: records split by a column, so both engines split alike ---

_SPLIT = ("user10 < 5", "user10 >= 5")
_MERGE = TIGHT.but(merge_mode="full")


def _halves(spark, sf_dir, cfg):
    df = view(spark, sf_dir, "video")
    return [grid.build_grid(df.where(s), spec_of("video"), cfg) for s in _SPLIT]


def _halves_sql(cfg: GridConfig) -> str:
    parts = []
    for i, s in enumerate(_SPLIT):
        body = ", ".join([O.pairs_ctes(f"SELECT * FROM ({view_sql('video')}) WHERE {s}", spec_of("video")), O.cells_ctes(cfg), O.heap_ctes(cfg)])
        parts.append(f"h{i} AS MATERIALIZED (WITH {body} SELECT * FROM heaps), c{i} AS MATERIALIZED (WITH {body} SELECT * FROM counters)")
    return ", ".join(parts)


_SUM_COUNTERS = "SELECT grid_row, grid_col, layer, cs_row, cs_col, CAST(sum(c) AS BIGINT) AS c FROM (SELECT * FROM c0 UNION ALL SELECT * FROM c1) GROUP BY ALL"
_COUNTER = "grid_row:l grid_col:l layer:l cs_row:l cs_col:l c:l"


@query("merge_counters_linear", _COUNTER, O.grid_ctes("video", _MERGE) + "@@ SELECT * FROM counters")
def _linear(spark, sf_dir):
    return merge.merge_full(*_halves(spark, sf_dir, _MERGE)).counters


_KEYS_BACK = f"keys AS (SELECT DISTINCT grid_row, grid_col, layer, subpop_key, m, depth FROM (SELECT * FROM h0 UNION ALL SELECT * FROM h1)), xs AS (SELECT k.*, CAST('0x' || substr(md5('p0|' || subpop_key || chr(31) || m), CAST(grid_row * 10 + 1 AS INT), 10) AS BIGINT) AS x, 0 AS f FROM keys k), counters AS ({_SUM_COUNTERS})"


@query(
    "merge_full",
    _HEAP,
    _halves_sql(_MERGE) + ", " + _KEYS_BACK
    + f", probes AS (SELECT *, (x >> CAST(9 + j * 8 AS INT)) & 127 AS cs_col, ((x >> CAST(9 + j * 8 + 7 AS INT)) & 1) * 2 - 1 AS s FROM xs, (SELECT unnest(range(3)) AS j)), "
    "est AS (SELECT p.grid_row, p.grid_col, p.layer, p.subpop_key, p.m, p.depth, list_sort(list(s * c))[2] AS f FROM probes p JOIN counters q ON p.grid_row = q.grid_row AND p.grid_col = q.grid_col AND p.layer = q.layer AND p.j = q.cs_row AND p.cs_col = q.cs_col GROUP BY ALL)"
    f"@@ SELECT * FROM est WHERE f > 0 QUALIFY row_number() OVER (PARTITION BY grid_row, grid_col, layer ORDER BY f DESC, subpop_key, m) <= {_MERGE.k}",
)
def _full(spark, sf_dir):
    return merge.merge_full(*_halves(spark, sf_dir, _MERGE)).heaps


_HEAP_SUM = "SELECT grid_row, grid_col, layer, subpop_key, m, depth, CAST(sum(f) AS BIGINT) AS f FROM (SELECT * FROM h0 UNION ALL SELECT * FROM h1) GROUP BY ALL"
_BEST = f"QUALIFY row_number() OVER (PARTITION BY grid_row, grid_col, layer ORDER BY f DESC, subpop_key, m) <= {TIGHT.k}"


@query("merge_heap_only", _HEAP, _halves_sql(TIGHT) + f"@@ SELECT * FROM ({_HEAP_SUM}) {_BEST}")
def _heap_only(spark, sf_dir):
    return merge.merge_heaps(*_halves(spark, sf_dir, TIGHT)).heaps


@query("merge_tree_two_round", _HEAP, _halves_sql(TIGHT) + f"@@ SELECT * FROM ({_HEAP_SUM}) {_BEST}")
def _tree(spark, sf_dir):
    a, b = _halves(spark, sf_dir, TIGHT)
    both = a.heaps.withColumn("part", F.lit(0)).unionByName(b.heaps.withColumn("part", F.lit(1)))
    return merge.tree_merge(both, None, a).heaps


# --- the bounded build ---


@query("bounded_counters_md5", _COUNTER, O.grid_ctes("video", TINY, **_VIDEO2) + "@@ SELECT * FROM counters WHERE c != 0")
def _bounded_counters(spark, sf_dir):
    return bounded.bounded_counters(view(spark, sf_dir, "video"), spec_of("video", **_VIDEO2), TINY)


_WIDE_HEAPS = TIGHT.but(k=100_000, heap_value="tracked")


@query("bounded_heaps_exact", _HEAP, O.grid_ctes("video", _WIDE_HEAPS, **_VIDEO2) + "@@ SELECT * FROM heaps")
def _bounded_exact(spark, sf_dir):
    return bounded.build_bounded(view(spark, sf_dir, "video"), spec_of("video", **_VIDEO2), _WIDE_HEAPS).heaps


@query("bounded_heaps", _HEAP)
def _bounded_heaps(spark, sf_dir):
    return bounded.build_bounded(view(spark, sf_dir, "video"), spec_of("video"), TIGHT.but(hash_fn="xxhash64")).heaps


@query("bounded_build_merge", "subpop_key:s l1:d l2:d card:d entropy:d")
def _bounded_estimates(spark, sf_dir):
    return grid.estimate(bounded.build_bounded(view(spark, sf_dir, "flow_card"), spec_of("flow_card"), TIGHT.but(hash_fn="xxhash64")))


@query("bounded_store_roundtrip", "subpop_key:s l1:d", O.grid_ctes("conv", TIGHT) + "@@ SELECT subpop_key, l1 FROM found")
def _store(spark, sf_dir):
    path = scratch(spark, "store")
    state = _state(spark, sf_dir, TIGHT, "conv")
    store.save(state, path)
    return grid.estimate(store.compact(spark, path, state.spec, TIGHT, frozen=True))


# --- configuration ---


def _values(cols: str, rows: list[tuple]) -> str:
    lit = lambda v: f"'{v}'" if isinstance(v, str) else repr(v)
    return f"SELECT * FROM (VALUES {', '.join('(' + ', '.join(map(lit, r)) + ')' for r in rows)}) t({cols})"


#: Figures of a given table that configurations are made for: one row, read by Spark.
_LINE_FIGURES = "SELECT count(*) AS n, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem"


def _line_figures(spark, sf_dir):
    """Counts of ``lineitem`` from one scan."""
    return load(spark, sf_dir, "lineitem").agg(F.count(F.lit(1)).alias("n"), F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers")).first()


@query("cfg_rows_for_delta", "l_linenumber:l delta:d n:l", "@@ SELECT l_linenumber, delta, n + (1 - n % 2) AS n FROM (SELECT l_linenumber, delta, CAST(ceil(ln(1 / delta) - 1e-12) AS BIGINT) AS n FROM (SELECT l_linenumber, 1 / (1 + CAST(count(*) AS DOUBLE)) AS delta FROM lineitem GROUP BY l_linenumber))")
def _rows_for(spark, sf_dir):
    """Rows that let one of a line number's records fail at most: delta is one in their count, and one more."""
    counts = load(spark, sf_dir, "lineitem").groupBy("l_linenumber").count().collect()  # a row a line number
    return spark.createDataFrame([(r[0], 1 / (1 + r[1]), C.rows_for(1 / (1 + r[1]))) for r in counts], "l_linenumber long, delta double, n long")


_MEMORIES = (1e5, 1e6, 2e6, 1e7)


@query(
    "cfg_optimal_widths",
    "l_linenumber:l memory:d ratio:d inner_error:d inner_width:l outer_width:l printed:d",
    "@@ SELECT l_linenumber, memory, ratio, x AS inner_error, round(1 / (x * x)) AS inner_width, round(memory * x * x) AS outer_width, sqrt(2 * ratio / memory) AS printed FROM (SELECT *, pow(2 * ratio / memory, 1.0 / 3) AS x FROM "
    "(SELECT l_linenumber, (SELECT count(*) FROM lineitem) / CAST(count(*) AS DOUBLE) AS ratio FROM lineitem GROUP BY l_linenumber), (" + _values("memory", [(m,) for m in _MEMORIES]) + "))",
)
def _widths(spark, sf_dir):
    """Widths for each line number of ``lineitem`` as the least subpopulation: the ratio is all lines over its own."""
    counts = load(spark, sf_dir, "lineitem").groupBy("l_linenumber").count().collect()  # a row a line number
    n = sum(r[1] for r in counts)
    rows = [(b, m, n / k, C.optimal_inner(m, n / k)[0], C.optimal_inner(m, n / k)[1], C.optimal_outer(m, n / k)[1], C.optimal_inner(m, n / k, True)[0]) for b, k in counts for m in _MEMORIES]
    return spark.createDataFrame(rows, "l_linenumber long, memory double, ratio double, inner_error double, inner_width long, outer_width long, printed double")


@query(
    "cfg_bound_interval",
    "subpop_key:s truth:d lo:d hi:d",
    O.pairs_ctes(view_sql("docs"), spec_of("docs")) + ", " + O.TRUTH + "@@ SELECT subpop_key, l1 AS truth, l1 * 0.9 AS lo, l1 * 1.1 + 4 * 1.1 / 32 * (SELECT sum(l1) FROM truth) AS hi FROM truth",
)
def _bounds(spark, sf_dir):
    t = B.ground_truth(view(spark, sf_dir, "docs"), spec_of("docs"))
    gs = t.agg(F.sum("l1").alias("gs"))
    lo, hi = C.bound(F.col("l1"), F.col("gs"), TIGHT, 0.1)
    return t.crossJoin(F.broadcast(gs)).select("subpop_key", F.col("l1").alias("truth"), lo.alias("lo"), hi.alias("hi"))  # gs is one row


_MODELS = [(r, w, r_cs, w_cs, k) for r, w, r_cs, w_cs, k in ((3, 8, 3, 64, 25), (3, 32, 3, 128, 100), (3, 1024, 3, 128, 100), (5, 10000, 3, 256, 225))]


@query(
    "cfg_memory_model",
    "r:l w:l layers:l bytes:l",
    "@@ SELECT r, w, layers, CAST(r AS BIGINT) * w * layers * (r_cs * w_cs * 4 + k * 16) AS bytes FROM (" + _values("r, w, r_cs, w_cs, k", _MODELS) + "), (SELECT greatest(1, CAST(ceil(log2(greatest(2, n))) AS BIGINT)) AS layers FROM (" + _LINE_FIGURES + "))",
)
def _memory(spark, sf_dir):
    """Bytes of grids whose layers halve the lines of ``lineitem`` until few are left."""
    n = C.layers_for(_line_figures(spark, sf_dir)["n"])
    rows = [(r, w, n, C.model_bytes(GridConfig(r=r, w=w, layers=n, r_cs=a, w_cs=b, k=k))) for r, w, a, b, k in _MODELS]
    return spark.createDataFrame(rows, "r long, w long, layers long, bytes long")


@query(
    "cfg_cost_model",
    "design:s time:l space:l",
    "@@ SELECT c.* FROM (SELECT n, parts AS q, n * 32 AS fan, CAST(3 * 128 AS BIGINT) AS cell FROM (" + _LINE_FIGURES + ")) t, LATERAL (SELECT unnest([{'design': 'per_key_state', 'time': fan, 'space': q * n}, {'design': 'sketch_per_subpop_and_stat', 'time': fan * 4 * 3, 'space': q * 4 * cell}, "
    "{'design': 'grid_per_stat', 'time': fan * 4 * 9, 'space': 96 * 4 * cell}, {'design': 'universal_grid', 'time': fan * 9, 'space': 96 * 10 * cell}], recursive := true)) c",
)
def _cost_model(spark, sf_dir):
    """The designs' costs for the lines of ``lineitem``, with five dimensions and its parts as subpopulations."""
    f = _line_figures(spark, sf_dir)
    rows = [(d, *C.cost_model(d, f["n"], 5, f["parts"], 4, TIGHT)) for d in ("per_key_state", "sketch_per_subpop_and_stat", "grid_per_stat", "universal_grid")]
    return spark.createDataFrame(rows, "design string, time long, space long")


@query("cfg_recommend", "mode:s r:l w:l w_cs:l k:l layers:l bytes:l")
def _recommend(spark, sf_dir):
    """Grids for ``lineitem``: as many pairs as its lines, and a supplier's mean share as the least one."""
    f, rows = _line_figures(spark, sf_dir), []
    for mode in ("paper", "strict"):
        c = C.recommend(0.2, 0.1, 1 / max(1, f["suppliers"]), f["n"], mode=mode)
        rows.append((mode, c.r, c.w, c.w_cs, c.k, c.layers, C.model_bytes(c)))
    return spark.createDataFrame(rows, "mode string, r long, w long, w_cs long, k long, layers long, bytes long")


@query("cfg_profile", "name:s value:d")
def _profile(spark, sf_dir):
    p = C.profile(view(spark, sf_dir, "flow"), spec_of("flow"), 0.1)
    return spark.createDataFrame([(k, float(v)) for k, v in sorted(p.items())], "name string, value double")


@query("cfg_op_counts", "variant:s hashes:d layer_updates:d merged:d")
def _ops(spark, sf_dir):
    n = fanout.pair_counts(view(spark, sf_dir, "conv"), spec_of("conv")).count()
    base = TIGHT.but(layer_mode="nested", hash_mode="many", merge_mode="full")
    steps = (("none", base), ("heap_merge", base.but(merge_mode="heap_only")), ("one_hash", base.but(merge_mode="heap_only", hash_mode="one")), ("one_layer", TIGHT))
    return spark.createDataFrame([(v, *C.op_counts(c, n, 8).values()) for v, c in steps], "variant string, hashes double, layer_updates double, merged double")


