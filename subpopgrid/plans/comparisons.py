"""Queries of the baselines, measures and experiment workloads."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import baselines as B
from ..operators import bounded, fanout, grid
from ..operators import measures as M
from ..schema import TIGHT, TINY, GridConfig
from ..sources.tables import ZIPF_SPEC, load, spec_of, view, view_sql, zipf, zipf_sql
from . import config as C
from . import oracle as O
from .registry import query

STATS = ("l1", "l2", "card", "entropy")
_TRUTH = "subpop_key:s l1:l l2:l card:l entropy:d"


def _pairs(name: str, **spec) -> str:
    return O.pairs_ctes(view_sql(name), spec_of(name, **spec)) + ", " + O.TRUTH


# --- baselines ---


@query("base_exact_sql_lists", _TRUTH, _pairs("docs", max_order=2) + "@@ SELECT * FROM truth")
def _lists(spark, sf_dir):
    return B.exact_lists(view(spark, sf_dir, "docs"), spec_of("docs", max_order=2))


@query("base_ground_truth", _TRUTH, _pairs("flow_card") + "@@ SELECT * FROM truth")
def _ground(spark, sf_dir):
    return B.ground_truth(view(spark, sf_dir, "flow_card"), spec_of("flow_card"))


@query("base_kv_build", "subpop_key:s m:l f:l", _pairs("video") + "@@ SELECT subpop_key, m, f FROM pairs")
def _kv_build(spark, sf_dir):
    return B.kv_build(view(spark, sf_dir, "video"), spec_of("video"))


@query("base_kv_query", "subpop_key:s l1:l l2:l card:l entropy:d mean:d std:d", _pairs("video") + "@@ SELECT * FROM truth")
def _kv_query(spark, sf_dir):
    return B.kv_query(B.kv_build(view(spark, sf_dir, "video"), spec_of("video")))


@query("base_rollup_build", "event_type:s dow:l hod:l user10:l m:l wgt:l", "@@ SELECT event_type, dow, hod, user10, m, sum(wgt) AS wgt FROM (" + view_sql("video") + ") GROUP BY ALL")
def _rollup_build(spark, sf_dir):
    return B.rollup_build(view(spark, sf_dir, "video"), spec_of("video"))


@query("base_rollup_query", _TRUTH, _pairs("video", max_order=2) + "@@ SELECT * FROM truth")
def _rollup_query(spark, sf_dir):
    s = spec_of("video", max_order=2)
    return B.rollup_query(B.rollup_build(view(spark, sf_dir, "video"), s), s)


_ONE_IN, _CARD_IN = 10, 4


@query(
    "base_hash_sample_card",
    "subpop_key:s card:l",
    O.pairs_ctes(f"SELECT * FROM ({view_sql('flow_card')}) WHERE CAST('0x' || substr(md5('v|' || m), 1, 15) AS BIGINT) % {_CARD_IN} = 0", spec_of("flow_card")) + f"@@ SELECT subpop_key, count(*) * {_CARD_IN} AS card FROM pairs GROUP BY subpop_key",
)
def _hash_sample(spark, sf_dir):
    return B.hash_sample_card(view(spark, sf_dir, "flow_card"), spec_of("flow_card"), _CARD_IN)


_EVENT_ID = view_sql("video").replace("SELECT event_type", "SELECT event_id, event_type", 1)


def _video_sample(spark, sf_dir, one_in: int) -> DataFrame:
    """Events kept by a hash of their id, then the view over them."""
    from ..sources.tables import VIEWS, sql

    events = load(spark, sf_dir, "events")
    return sql(spark, sf_dir, VIEWS["video"][1], events=B.uniform_sample(events, F.col("event_id").cast("string"), one_in))


_SAMPLED = f"SELECT * FROM ({_EVENT_ID}) WHERE CAST('0x' || substr(md5('u|' || event_id), 1, 15) AS BIGINT) % {_ONE_IN} = 0"
_P = 1 / _ONE_IN
_SAMPLE_STATS = f"SELECT subpop_key, l1 * {_ONE_IN} AS l1, (l2 - (1 - {_P}) * l1) / ({_P} * {_P}) AS l2, card, card * {_ONE_IN} AS card_scaled, entropy FROM truth"


@query("base_uniform_hash_sample_l1_l2", "subpop_key:s l1:l l2:d", O.pairs_ctes(_SAMPLED, spec_of("video")) + ", " + O.TRUTH + f"@@ {_SAMPLE_STATS}")
def _uniform(spark, sf_dir):
    return B.sample_stats(_video_sample(spark, sf_dir, _ONE_IN), spec_of("video"), _ONE_IN, with_entropy=False)


@query("base_uniform_sample_kv", "subpop_key:s l1:l l2:d card:l card_scaled:l entropy:d", O.pairs_ctes(_SAMPLED, spec_of("video")) + ", " + O.TRUTH + f"@@ {_SAMPLE_STATS}")
def _sample_kv(spark, sf_dir):
    return B.sample_stats(_video_sample(spark, sf_dir, _ONE_IN), spec_of("video"), _ONE_IN)


@query("base_sample_builtin", "subpop_key:s l1:l")
def _sample_builtin(spark, sf_dir):
    df = view(spark, sf_dir, "video").sample(0.1, seed=11)
    return B.sample_stats(df, spec_of("video"), 10)


_PER = TINY.but(r=1, k=20, layers=6)


def _per_subpop_sql(name: str, cfg: GridConfig, **spec) -> str:
    named = O.cells_ctes(cfg).replace(f"% {cfg.w} AS grid_col", "AS grid_col").replace(f"md5('s{cfg.salt}|' || subpop_key), CAST(r * 15 + 1 AS INT), 15)", "md5(subpop_key), 1, 15)")
    return ", ".join([_pairs(name, **spec), named, O.heap_ctes(cfg), O.estimate_ctes(cfg, {k: O.SUM_SQL[k] for k in ("l1", "l2", "card", "flogf")}, O.ALL_KEYS)])


@query("base_sketch_per_subpop", "subpop_key:s l1:l l2:l card:l entropy:d", _per_subpop_sql("docs", _PER, max_order=2) + "@@ SELECT * FROM found")
def _per(spark, sf_dir):
    return B.sketch_per_subpop(view(spark, sf_dir, "docs"), spec_of("docs", max_order=2), _PER)


@query(
    "base_quantiles_exact",
    "subpop_key:s q25:d q50:d q75:d",
    O.pairs_ctes(view_sql("docs"), spec_of("docs", max_order=2)) + ", each AS (SELECT subpop_key, m FROM (SELECT subpop_key, m, unnest(range(f)) AS i FROM pairs))@@ SELECT subpop_key, quantile_cont(m, 0.25) AS q25, quantile_cont(m, 0.5) AS q50, quantile_cont(m, 0.75) AS q75 FROM each GROUP BY subpop_key",
)
def _quantiles(spark, sf_dir):
    return B.quantiles_exact(view(spark, sf_dir, "docs"), spec_of("docs", max_order=2))


@query("base_quantiles_sketch", "subpop_key:s q25:l q50:l q75:l")
def _quantile_sketch(spark, sf_dir):
    return B.quantiles_sketched(view(spark, sf_dir, "docs"), spec_of("docs", max_order=2))


@query("base_stat_sketch_hll", "subpop_key:s card:l")
def _hll(spark, sf_dir):
    return B.stat_sketch_per_subpop(view(spark, sf_dir, "flow_card"), spec_of("flow_card"))


# --- measures ---


def _est(spark, sf_dir, name: str, cfg: GridConfig, **spec) -> DataFrame:
    df, s = view(spark, sf_dir, name), spec_of(name, **spec)
    return grid.estimate(grid.build_grid(df, s, cfg))


def _err(spark, sf_dir, name: str, cfg: GridConfig, stats=STATS, **spec) -> DataFrame:
    df, s = view(spark, sf_dir, name), spec_of(name, **spec)
    return M.relative_error(grid.estimate(grid.build_grid(df, s, cfg)), B.ground_truth(df, s), stats)


def _err_sql(name: str, cfg: GridConfig, stats=STATS, **spec) -> str:
    return O.grid_ctes(name, cfg, **spec) + ", " + O.error_ctes(stats)


_ERR = "subpop_key:s stat:s truth:d est:d err:d"


@query("err_relative", _ERR, _err_sql("video", TIGHT) + "@@ SELECT * FROM errors")
def _relative(spark, sf_dir):
    return _err(spark, sf_dir, "video", TIGHT)


_BOX = "stat:s low:d q1:d median:d q3:d high:d n:l whisker_low:d whisker_high:d"


def _box_sql(src: str = "big") -> str:
    return (
        f"SELECT q.*, (SELECT min(err) FROM {src} e WHERE e.stat = q.stat AND err >= q1 - 1.5 * (q3 - q1)) AS whisker_low, (SELECT max(err) FROM {src} e WHERE e.stat = q.stat AND err <= q3 + 1.5 * (q3 - q1)) AS whisker_high "
        f"FROM (SELECT stat, min(err) AS low, quantile_cont(err, 0.25) AS q1, quantile_cont(err, 0.5) AS median, quantile_cont(err, 0.75) AS q3, max(err) AS high, count(*) AS n FROM {src} GROUP BY stat) q"
    )


@query("err_boxplot", _BOX, _err_sql("video", TIGHT) + ", " + O.qualifying_cte(0.002) + "@@ " + _box_sql())
def _box(spark, sf_dir):
    return M.boxplot(M.qualifying(_err(spark, sf_dir, "video", TIGHT), 0.002))


_BY_SIZE = "SELECT stat, CAST(floor(log10(truth / gs)) AS INT) AS decade, count(*) AS n, avg(abs(err)) AS mean_abs, quantile_cont(err, 0.5) AS median, var_samp(err) AS variance FROM (SELECT e.*, sum(truth) OVER (PARTITION BY stat) AS gs FROM errors e) GROUP BY ALL"
_SIZED = "stat:s decade:l n:l mean_abs:d median:d variance:d"


@query("err_by_gsum_bucket", _SIZED, _err_sql("video", TIGHT) + "@@ " + _BY_SIZE)
def _by_size(spark, sf_dir):
    return M.error_by_size(_err(spark, sf_dir, "video", TIGHT))


@query("err_within_threshold", "stat:s share:d n:l", _err_sql("video", TIGHT) + ", " + O.qualifying_cte(0.002) + "@@ SELECT stat, avg(CASE WHEN abs(err) <= 0.2 THEN 1.0 ELSE 0 END) AS share, count(*) AS n FROM big GROUP BY stat")
def _within(spark, sf_dir):
    return M.within(M.qualifying(_err(spark, sf_dir, "video", TIGHT), 0.002), 0.2)


@query("err_mean_over_stats", "subpop_key:s mean_err:d", _err_sql("docs", TIGHT) + "@@ SELECT subpop_key, avg(abs(err)) AS mean_err FROM errors GROUP BY subpop_key")
def _mean(spark, sf_dir):
    return M.mean_error(_err(spark, sf_dir, "docs", TIGHT))


def _coverage(src: str = "errors", w: int = 32, e: float = 0.1) -> str:
    return f"SELECT stat, avg(CASE WHEN est >= truth * (1 - {e}) AND est <= truth * (1 + {e}) + gs * (4 * (1 + {e}) / {w}) THEN 1.0 ELSE 0 END) AS coverage, count(*) AS n FROM (SELECT e.*, sum(truth) OVER (PARTITION BY stat) AS gs FROM {src} e) GROUP BY stat"


@query("err_bound_coverage", "stat:s coverage:d n:l", _err_sql("flow_card", TIGHT) + "@@ " + _coverage())
def _bounds(spark, sf_dir):
    return M.bound_coverage(_err(spark, sf_dir, "flow_card", TIGHT), TIGHT, 0.1)


@query("err_as_columns", "subpop_key:s l1:d l2:d card:d entropy:d", _err_sql("conv", TIGHT) + "@@ SELECT subpop_key, max(err) FILTER (WHERE stat = 'l1') AS l1, max(err) FILTER (WHERE stat = 'l2') AS l2, max(err) FILTER (WHERE stat = 'card') AS card, max(err) FILTER (WHERE stat = 'entropy') AS entropy FROM errors GROUP BY subpop_key")
def _columns(spark, sf_dir):
    return M.errors_as_columns(_err(spark, sf_dir, "conv", TIGHT))


_STATE = "heap_bytes:l counter_bytes:l"


@query("err_state_bytes", _STATE, O.grid_ctes("video", TIGHT) + "@@ SELECT (SELECT count(*) * 16 FROM heaps) AS heap_bytes, (SELECT count(*) * 4 FROM counters) AS counter_bytes")
def _bytes(spark, sf_dir):
    s = grid.build_grid(view(spark, sf_dir, "video"), spec_of("video"), TIGHT.but(merge_mode="full"))
    return M.state_bytes(s.heaps, s.counters)


# --- sweeps: one row a configuration ---

_SWEEP = [(w, k) for w in (4, 16, 64) for k in (10, 50)]


def _sweep_cfg(w: int, k: int, **more) -> GridConfig:
    return TIGHT.but(w=w, k=k, **more)


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def _l1_error(spark, sf_dir, name: str, cfg: GridConfig, share: float, stat: str = "l1", **spec) -> DataFrame:
    errors = M.qualifying(_err(spark, sf_dir, name, cfg, **spec), share).where(F.col("stat") == stat)
    return errors.agg(F.avg(F.abs("err")).alias("mean_abs"), F.count(F.lit(1)).alias("n"))


def _sweep_sql(rows: list[tuple[str, str]], stat: str, share: float) -> str:
    """One subquery a labelled chain of CTEs: (label list, CTEs)."""
    return "@@ " + " UNION ALL ".join(f"(WITH {ctes}, {O.qualifying_cte(share)} SELECT {label}, avg(abs(err)) AS mean_abs, count(*) AS n FROM big WHERE stat = '{stat}')" for label, ctes in rows)


_SWEEP_SQL = _sweep_sql([(f"{w} AS w, {k} AS k, {C.model_bytes(_sweep_cfg(w, k))} AS bytes", _err_sql("video", _sweep_cfg(w, k), max_order=2)) for w, k in _SWEEP], "l1", 0.002)
_FRONT = "SELECT *, coalesce(mean_abs < min(mean_abs) OVER (ORDER BY bytes, mean_abs ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), true) AS on_frontier FROM (SELECT * REPLACE (round(mean_abs, 9) AS mean_abs) FROM ({}))"


def _sweep(spark, sf_dir, **more) -> DataFrame:
    parts = [
        _l1_error(spark, sf_dir, "video", _sweep_cfg(w, k, **more), 0.002, max_order=2).select(F.lit(w).alias("w"), F.lit(k).alias("k"), F.lit(C.model_bytes(_sweep_cfg(w, k))).alias("bytes"), F.round("mean_abs", 9).alias("mean_abs"), "n")
        for w, k in _SWEEP
    ]
    return _union(parts).coalesce(1)


_PARETO = "w:l k:l bytes:l mean_abs:d n:l on_frontier:b"


@query("err_pareto", _PARETO, "@@ " + _FRONT.format(_SWEEP_SQL[3:]))
def _pareto(spark, sf_dir):
    return M.pareto(_sweep(spark, sf_dir), "bytes", "mean_abs")


# --- workloads ---


@query(
    "w_W1",
    "event_type:s entropy:d l1:d entropy_true:d l1_true:l",
    O.grid_ctes("video", TIGHT) + "@@ SELECT k.event_type, e.entropy, e.l1, t.entropy AS entropy_true, t.l1 AS l1_true FROM (SELECT DISTINCT subpop_key, event_type FROM pairs WHERE gid = 7) k JOIN estimates e ON k.subpop_key = e.subpop_key JOIN truth t ON k.subpop_key = t.subpop_key",
)
def _w1(spark, sf_dir):
    df, s = view(spark, sf_dir, "video"), spec_of("video")
    keys = grid.StatQuery(("event_type",), ()).subpops(df, s)
    est = grid.estimate(grid.build_grid(df, s, TIGHT), keys)
    t = B.ground_truth(df, s).select("subpop_key", F.col("entropy").alias("entropy_true"), F.col("l1").alias("l1_true"))
    return keys.join(est, "subpop_key").join(t, "subpop_key")


@query(
    "w_W2",
    "l_returnflag:s l_linestatus:s card:d card_true:l",
    O.grid_ctes("flow_card", TIGHT) + "@@ SELECT k.l_returnflag, k.l_linestatus, e.card, t.card AS card_true FROM (SELECT DISTINCT subpop_key, l_returnflag, l_linestatus FROM pairs WHERE gid = 3) k JOIN estimates e ON k.subpop_key = e.subpop_key JOIN truth t ON k.subpop_key = t.subpop_key",
)
def _w2(spark, sf_dir):
    df, s = view(spark, sf_dir, "flow_card"), spec_of("flow_card")
    keys = grid.StatQuery(("l_returnflag", "l_linestatus"), ()).subpops(df, s)
    est = grid.estimate(grid.build_grid(df, s, TIGHT), keys)
    return keys.join(est, "subpop_key").join(B.ground_truth(df, s).select("subpop_key", F.col("card").alias("card_true")), "subpop_key")


def _spec_flow():
    return spec_of("flow")


def _uniform_lines(spark, sf_dir, one_in: int) -> DataFrame:
    """The flow view over a uniform sample of lines."""
    from ..sources.tables import VIEWS, sql

    text = F.concat_ws("-", *(F.col(c).cast("string") for c in ("l_orderkey", "l_linenumber", "l_partkey")))
    return sql(spark, sf_dir, VIEWS["flow"][1], lineitem=B.uniform_sample(load(spark, sf_dir, "lineitem"), text, one_in))


def _offline(spark, sf_dir, s, df: DataFrame) -> tuple:
    """Offline samples at 1 %: cardinality from a hash sample, L1, L2 and entropy from a uniform one."""
    kept = df.where(B.hash_slice(F.concat(F.lit("v|"), F.col("m").cast("string"))) % 100 == 0)

    def ask(st: DataFrame) -> DataFrame:
        values, lines = (st.where(F.col("sample") == n) for n in ("hash", "uniform"))
        card = B.kv_query(values.select("subpop_key", "m", "f")).select("subpop_key", (F.col("card") * 100).alias("card"))
        own = B.scaled(B.kv_query(lines.select("subpop_key", "m", "f")), 100).select("subpop_key", "l1", "l2", "entropy")
        return own.join(card, "subpop_key", "full").select("subpop_key", *(F.coalesce(c, F.lit(0)).alias(c) for c in STATS))

    return (lambda: B.kv_build(kept, s).withColumn("sample", F.lit("hash")).unionByName(B.kv_build(_uniform_lines(spark, sf_dir, 100), s).withColumn("sample", F.lit("uniform"))), ask)


#: Bounded state for the engines' comparison: far below the pairs of all cuboids.
ENGINE_CFG = TIGHT.but(w=64, w_cs=256, hash_fn="xxhash64", heap_value="tracked")


def _engines(spark, sf_dir, df: DataFrame | None = None, s=None) -> dict:
    """Engine -> (ingest, query): what each keeps, and how it answers all subpopulations."""
    df, s = view(spark, sf_dir, "flow") if df is None else df, s or _spec_flow()
    cfg = ENGINE_CFG
    return {
        "grid_bounded": (lambda: bounded.build_bounded(fanout.preaggregate(df, s), s, cfg).heaps, lambda st: grid.estimate(grid.GridState(s, cfg, st))),
        "grid": (lambda: grid.build_grid(df, s, cfg).heaps, lambda st: grid.estimate(grid.GridState(s, cfg, st))),
        "lists": (lambda: df, lambda st: B.exact_lists(st, s)),
        "exact": (lambda: df, lambda st: B.ground_truth(st, s)),
        "kv": (lambda: B.kv_build(df, s), B.kv_query),
        "rollup": (lambda: B.rollup_build(df, s), lambda st: B.rollup_query(st, s)),
        "sample_kv": (lambda: B.kv_build(_uniform_lines(spark, sf_dir, 10), s), lambda st: B.scaled(B.kv_query(st), 10)),
        "offline_samples": _offline(spark, sf_dir, s, df),
        "sketch_per_subpop": (lambda: B.sketches_build(df, s, cfg.but(k=50, layers=6)), lambda st: B.sketches_query(st, cfg.but(k=50, layers=6))),
    }


#: Each statistic has its own least share: over all cuboids no cardinality or entropy comes near that of counts.
LEAST_SHARES = ((0.002, ("l1", "l2")), (0.00005, ("card", "entropy")))


@query("w_W3", "engine:s stat:s mean_abs:d ingest_s:d query_s:d state_rows:l core_seconds:d")
def _w3(spark, sf_dir):
    """Cost against accuracy over all cuboids: every engine's ingest and query time, state rows and mean error by statistic.

    All records are read and cached before."""
    df, s = _done(view(spark, sf_dir, "flow")), _spec_flow()
    true, cores, rows = _done(B.ground_truth(df, s)), spark.sparkContext.defaultParallelism, []
    for name, (ingest, ask) in _engines(spark, sf_dir, df, s).items():
        state, t0 = M.timed(lambda f=ingest: _done(f()))
        est, t1 = M.timed(lambda f=ask, st=state: _done(f(st)))
        n = state.count()
        errors = M.relative_error(est, true)
        large = _union([M.qualifying(errors.where(F.col("stat").isin(*stats)), share) for share, stats in LEAST_SHARES])
        for r in large.groupBy("stat").agg(F.avg(F.abs("err")).alias("e")).collect():  # a row a statistic
            rows.append((name, r["stat"], r["e"], t0, t1, n, M.cost(t0 + t1, cores)))
        est.unpersist()
        if name not in ("lists", "exact"):  # theirs are the records themselves
            state.unpersist()
    true.unpersist()
    df.unpersist()
    return spark.createDataFrame(rows, "engine string, stat string, mean_abs double, ingest_s double, query_s double, state_rows long, core_seconds double")


def _done(df: DataFrame) -> DataFrame:
    df = df.cache()
    df.count()
    return df


@query("w_W4", "size:s d:l engine:s subpops:l ingest_s:d query_s:d state_rows:l")
def _w4(spark, sf_dir):
    """Latency and ingestion as dimensions, and so subpopulations, grow from one to five, over a quarter and all of the data."""
    from ..sources.tables import VIEWS, sql

    rows, dims = [], VIEWS["flow"][0]
    for size, where in (("quarter", " WHERE l.l_orderkey % 4 = 0"), ("all", "")):
        df = _done(sql(spark, sf_dir, VIEWS["flow"][1] + where))
        for d in range(1, len(dims) + 1):
            s = type(_spec_flow())(dims=dims[:d], weight="wgt")
            own = _engines(spark, sf_dir, df, s)
            subpops = None
            for name in ("kv", "grid_bounded", "lists", "rollup"):
                ingest, ask = own[name]
                state, t0 = M.timed(lambda f=ingest: _done(f()))
                n, t1 = M.timed(lambda f=ask, st=state: f(st).count())
                subpops = n if subpops is None else subpops
                rows.append((size, d, name, subpops, t0, t1, state.count()))
                if name != "lists":
                    state.unpersist()
        df.unpersist()
    return spark.createDataFrame(rows, "size string, d long, engine string, subpops long, ingest_s double, query_s double, state_rows long")


_SETS = (("l1",), ("l1", "l2"), ("l1", "l2", "entropy"), STATS)


@query(
    "w_W5",
    "n_stats:l " + _BOX,
    _err_sql("video", TIGHT, max_order=2) + ", " + O.qualifying_cte(0.002) + ", box AS (" + _box_sql() + ")@@ " + " UNION ALL ".join(f"SELECT {len(s)} AS n_stats, * FROM box WHERE stat IN ({', '.join(repr(x) for x in s)})" for s in _SETS),
)
def _w5(spark, sf_dir):
    """Statistic sets of growing size from one state: each set is asked on its own, and estimates don't depend on it."""
    df, s = view(spark, sf_dir, "video"), spec_of("video", max_order=2)
    state, true = grid.build_grid(df, s, TIGHT), B.ground_truth(df, s)
    from ..functions.statistics import sum_exprs

    need = {"l1": ("l1",), "l2": ("l2",), "card": ("card",), "entropy": ("l1", "flogf", "card")}
    parts = []
    for stats in _SETS:
        gs = {k: v for k, v in sum_exprs().items() if k in {x for st in stats for x in need[st]}}
        all_errors = M.relative_error(grid.estimate(state, None, gs), true, stats)
        parts.append(M.boxplot(M.qualifying(all_errors, 0.002)).withColumn("n_stats", F.lit(len(stats))))
    return _union(parts)


_SAMPLE_ERR = ", ".join([O.pairs_ctes(_SAMPLED, spec_of("video")), O.TRUTH])


@query(
    "w_W6",
    "engine:s " + _SIZED,
    "@@ " + f"SELECT 'grid' AS engine, * FROM (WITH {_err_sql('video', TIGHT)} {_BY_SIZE}) UNION ALL SELECT 'sample' AS engine, * FROM (WITH sampled AS (WITH {_SAMPLE_ERR} {_SAMPLE_STATS}), {_pairs('video')}, {O.error_ctes(est='sampled')} {_BY_SIZE})",
)
def _w6(spark, sf_dir):
    """Error against the normalised sum: grid and uniform sampling."""
    df, s = view(spark, sf_dir, "video"), spec_of("video")
    true = B.ground_truth(df, s)
    sample = B.sample_stats(_video_sample(spark, sf_dir, _ONE_IN), s, _ONE_IN)
    parts = [M.error_by_size(M.relative_error(e, true)).withColumn("engine", F.lit(n)) for n, e in (("grid", _est(spark, sf_dir, "video", TIGHT)), ("sample", sample))]
    return _union(parts)


@query("w_W7", "subpop_key:s card:l truth:l err:d", _per_subpop_sql("flow_card", _PER.but(k=50), max_order=2) + "@@ SELECT t.subpop_key, e.card, t.card AS truth, (e.card - t.card) / t.card AS err FROM truth t JOIN found e ON t.subpop_key = e.subpop_key")
def _w7(spark, sf_dir):
    """Cardinality from a sketch of one's own."""
    df, s = view(spark, sf_dir, "flow_card"), spec_of("flow_card", max_order=2)
    own = B.sketch_per_subpop(df, s, _PER.but(k=50)).select("subpop_key", "card")
    t = B.ground_truth(df, s).select("subpop_key", F.col("card").alias("truth"))
    return own.join(t, "subpop_key").withColumn("err", (F.col("card") - F.col("truth")) / F.col("truth"))


_DIMS = spec_of("video").dims


def _w8_part(d: int) -> str:
    s = type(spec_of("video"))(dims=_DIMS[:d], weight="wgt")
    chain = O.grid_ctes((view_sql("video"), s), TIGHT)
    return f"SELECT * FROM (WITH {chain} SELECT {d} AS d, (SELECT count(DISTINCT subpop_key) FROM pairs) AS subpops, (SELECT count(*) FROM heaps) * 16 AS grid_bytes, (SELECT count(*) FROM pairs) * 24 AS kv_bytes, (SELECT count(*) FROM recs) * 24 AS raw_bytes)"


@query("w_W8", "d:l subpops:l grid_bytes:l kv_bytes:l raw_bytes:l", "@@ " + " UNION ALL ".join(map(_w8_part, (1, 2, 3, 4))))
def _w8(spark, sf_dir):
    """State of the engines as subpopulations grow: heaps level off, pair counts don't."""
    parts = []
    for d in (1, 2, 3, 4):
        df, s = view(spark, sf_dir, "video"), type(spec_of("video"))(dims=_DIMS[:d], weight="wgt")
        p = fanout.pair_counts(df, s).agg(F.count_distinct("subpop_key").alias("subpops"), (F.count(F.lit(1)) * 24).alias("kv_bytes"))
        h = grid.build_grid(df, s, TIGHT).heaps.agg((F.count(F.lit(1)) * 16).alias("grid_bytes"))
        parts.append(p.crossJoin(h).crossJoin(df.agg((F.count(F.lit(1)) * 24).alias("raw_bytes"))).withColumn("d", F.lit(d)))  # one row each
    return _union(parts)


@query("w_W9", _PARETO, "@@ " + _FRONT.format(_SWEEP_SQL[3:]))
def _w9(spark, sf_dir):
    """Configuration sweep: memory against error."""
    return M.pareto(_sweep(spark, sf_dir), "bytes", "mean_abs")


_STEPS = (
    ("none", {"layer_mode": "nested", "hash_mode": "many", "merge_mode": "full"}),
    ("heap_merge", {"layer_mode": "nested", "hash_mode": "many", "merge_mode": "heap_only"}),
    ("one_hash", {"layer_mode": "nested", "hash_mode": "one", "merge_mode": "heap_only"}),
    ("one_layer", {"layer_mode": "deepest", "hash_mode": "one", "merge_mode": "heap_only"}),
)


@query("w_W10", "variant:s seconds:d share:d mean_abs:d")
def _w10(spark, sf_dir):
    """The optimisations one after another on the sketch's own update: each task hashes, updates layers and counters, then
    states merge and answer; time as a share of the first variant. All records are read before, collapsed to counts of full
    combinations (what a task does first) and cached, and so is the truth, which is no part of a variant."""
    s = _spec_flow()
    df = _done(fanout.preaggregate(view(spark, sf_dir, "flow"), s).repartition(8))
    true, rows = _done(B.ground_truth(df, s)), []
    for name, changes in (("warm-up", dict(_STEPS)["none"]), *_STEPS):
        cfg = ENGINE_CFG.but(**changes)

        def run(cfg=cfg):
            state = bounded.build_bounded(df, s, cfg)
            if state.counters is not None:  # a full merge adds the counters too
                state.counters.write.format("noop").mode("overwrite").save()
            return M.qualifying(M.relative_error(grid.estimate(state), true), 0.002).agg(F.avg(F.abs("err"))).first()[0]

        error, seconds = M.timed(run)
        if name != "warm-up":
            rows.append((name, seconds, seconds / (rows[0][1] if rows else seconds), error))
    true.unpersist()
    df.unpersist()
    return spark.createDataFrame(rows, "variant string, seconds double, share double, mean_abs double")


_BASIC = {"layer_mode": "nested", "hash_mode": "many"}


@query(
    "w_W11",
    "variant:s " + _PARETO,
    "@@ " + " UNION ALL ".join(f"SELECT '{v}' AS variant, * FROM ({_FRONT.format(_sweep_sql([(f'{w} AS w, {k} AS k, {C.model_bytes(_sweep_cfg(w, k))} AS bytes', _err_sql('video', _sweep_cfg(w, k, **c), max_order=2)) for w, k in _SWEEP], 'l1', 0.002)[3:])})" for v, c in (("basic", _BASIC), ("optimised", {}))),
)
def _w11(spark, sf_dir):
    """Frontiers of the basic and the optimised sketch."""
    return _union([M.pareto(_sweep(spark, sf_dir, **c), "bytes", "mean_abs").withColumn("variant", F.lit(v)) for v, c in (("basic", _BASIC), ("optimised", {}))])


_ALPHAS = (0.0, 0.7, 0.99)
_ZIPF_CFG = TIGHT.but(w=4, k=20)


@query(
    "w_W12",
    "alpha:d stat:s mean_abs:d n:l",
    "@@ " + " UNION ALL ".join(f"SELECT {a} AS alpha, * FROM (WITH {O.grid_ctes((zipf_sql(a, '(SELECT count(*) FROM lineitem)'), ZIPF_SPEC), _ZIPF_CFG)}, {O.error_ctes()}, {O.qualifying_cte(0.02)} SELECT stat, avg(abs(err)) AS mean_abs, count(*) AS n FROM big GROUP BY stat)" for a in _ALPHAS),
)
def _w12(spark, sf_dir):
    """Skew: errors on Zipf-distributed subpopulations."""
    n, parts = load(spark, sf_dir, "lineitem").count(), []
    for a in _ALPHAS:
        df = zipf(spark, a, n)
        errors = M.relative_error(grid.estimate(grid.build_grid(df, ZIPF_SPEC, _ZIPF_CFG)), B.ground_truth(df, ZIPF_SPEC))
        parts.append(M.qualifying(errors, 0.02).groupBy("stat").agg(F.avg(F.abs("err")).alias("mean_abs"), F.count(F.lit(1)).alias("n")).withColumn("alpha", F.lit(a)))
    return _union(parts)


_SMALL = ("video", "conv", "docs")


@query("w_W13", "name:s stat:s mean_abs:d n:l", "@@ " + " UNION ALL ".join(f"SELECT '{v}' AS name, * FROM (WITH {_err_sql(v, TIGHT)}, {O.qualifying_cte(0.002)} SELECT stat, avg(abs(err)) AS mean_abs, count(*) AS n FROM big GROUP BY stat)" for v in _SMALL))
def _w13(spark, sf_dir):
    """Smaller datasets."""
    return _union([M.qualifying(_err(spark, sf_dir, v, TIGHT), 0.002).groupBy("stat").agg(F.avg(F.abs("err")).alias("mean_abs"), F.count(F.lit(1)).alias("n")).withColumn("name", F.lit(v)) for v in _SMALL])


_KEY_CFGS = (("pair", TIGHT), ("metric", TIGHT.but(key_mode="metric")))


@query("w_W15", "key_mode:s stat:s mean_abs:d n:l", "@@ " + " UNION ALL ".join(f"SELECT '{k}' AS key_mode, * FROM (WITH {_err_sql('video', c, max_order=2)}, {O.qualifying_cte(0.002)} SELECT stat, avg(abs(err)) AS mean_abs, count(*) AS n FROM big GROUP BY stat)" for k, c in _KEY_CFGS))
def _w15(spark, sf_dir):
    """Pair keys against bare values."""
    parts = []
    df, s = view(spark, sf_dir, "video"), spec_of("video", max_order=2)
    for k, c in _KEY_CFGS:
        keys = fanout.pair_counts(df, s).select("subpop_key").distinct()
        errors = M.relative_error(grid.estimate(grid.build_grid(df, s, c), keys), B.ground_truth(df, s))
        parts.append(M.qualifying(errors, 0.002).groupBy("stat").agg(F.avg(F.abs("err")).alias("mean_abs"), F.count(F.lit(1)).alias("n")).withColumn("key_mode", F.lit(k)))
    return _union(parts)


@query("w_W16", "r:l stat:s share:d n:l", "@@ " + " UNION ALL ".join(f"SELECT {r} AS r, * FROM (WITH {_err_sql('video', TINY.but(r=r), max_order=2)}, {O.qualifying_cte(0.002)} SELECT stat, avg(CASE WHEN abs(err) <= 0.2 THEN 1.0 ELSE 0 END) AS share, count(*) AS n FROM big GROUP BY stat)" for r in (1, 3, 5)))
def _w16(spark, sf_dir):
    """More rows, steadier medians."""
    return _union([M.within(M.qualifying(_err(spark, sf_dir, "video", TINY.but(r=r), max_order=2), 0.002), 0.2).withColumn("r", F.lit(r)) for r in (1, 3, 5)])


@query("w_W17", "salt:l stat:s coverage:d n:l", "@@ " + " UNION ALL ".join(f"SELECT {z} AS salt, * FROM (WITH {_err_sql('docs', TIGHT.but(salt=z))} {_coverage()})" for z in (1, 2, 3)))
def _w17(spark, sf_dir):
    """Estimates inside the theoretical interval, over salts."""
    return _union([M.bound_coverage(_err(spark, sf_dir, "docs", TIGHT.but(salt=z)), TIGHT, 0.1).withColumn("salt", F.lit(z)) for z in (1, 2, 3)])
