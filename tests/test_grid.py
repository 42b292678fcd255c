"""Invariants of the grid, its variants, bounds and configuration."""

from __future__ import annotations

import math

import pytest
from pyspark.sql import functions as F

from subpopgrid.functions import statistics as S
from subpopgrid.functions.hashing import hash_plan
from subpopgrid.operators import baselines as B
from subpopgrid.operators import bounded, fanout, grid, merge, store
from subpopgrid.operators import measures as M
from subpopgrid.operators import universal as U
from subpopgrid.plans import config as C
from subpopgrid.schema import EXACT, TIGHT, TINY, GridConfig, WorkloadSpec
from subpopgrid.sources.tables import ZIPF_SPEC, spec_of, view, zipf
from tests.conftest import SF

SPEC = WorkloadSpec(dims=("a", "b"))
ONE = WorkloadSpec(dims=("a",))


def frame(spark, rows, schema="a string, b string, m long"):
    return spark.createDataFrame(rows, schema)


# --- fan-out and keys ---


def test_one_record_belongs_to_all_cuboids(spark):
    df = frame(spark, [("x", "y", "z", 5)], "a string, b string, c string, m long")
    rows = fanout.fan_out(df, WorkloadSpec(dims=("a", "b", "c"))).collect()
    assert len(rows) == 8 and len({r["subpop_key"] for r in rows}) == 8
    assert {r["subpop_key"] for r in rows if r["gid"] == 7} == {"7|"}


def test_null_differs_from_rolled_up_and_keys_are_injective(spark):
    us = "\x1f"
    df = frame(spark, [(None, "y", 1), ("\\N", "y", 1), ("p" + us, "q", 1), ("p", us + "q", 1), ("", "y", 1)])
    keys = fanout.pair_counts(df, SPEC).where("gid = 0").select("subpop_key").distinct().count()
    assert keys == 5
    by_a = fanout.pair_counts(df, SPEC).where("gid = 1")
    assert by_a.select("subpop_key").distinct().count() == 5
    a = {(r["gid"], r["subpop_key"], r["m"]): r["f"] for r in fanout.pair_counts(df, SPEC, False).collect()}
    assert a == {(r["gid"], r["subpop_key"], r["m"]): r["f"] for r in fanout.pair_counts(df, SPEC, True).collect()}


def test_sums_over_cuboids(spark):
    df, s = view(spark, SF, "flow_card"), spec_of("flow_card")
    n, pairs = df.count(), fanout.pair_counts(df, s)
    per = pairs.groupBy("gid").agg(F.sum("f").alias("n")).collect()
    assert len(per) == 16 and all(r["n"] == n for r in per)
    assert fanout.shape(df, s).first()["gs_l1"] == 16 * n


def test_negative_weights_are_refused(spark):
    df = spark.createDataFrame([("x", 1, -1)], "a string, m long, wgt long")
    with pytest.raises(Exception, match="negative weight"):
        fanout.pair_counts(df, WorkloadSpec(dims=("a",), weight="wgt")).collect()


def test_empty_input(spark):
    df = frame(spark, [])
    assert grid.estimate(grid.build_grid(df, SPEC, TINY)).count() == 0
    assert B.ground_truth(df, SPEC).count() == 0 and B.exact_lists(df, SPEC).count() == 0
    assert grid.estimate(bounded.build_bounded(df, SPEC, TINY)).count() == 0


# --- statistics ---


def test_statistics_of_known_frequencies(spark):
    one = B.ground_truth(frame(spark, [("x", 7)] * 1000, "a string, m long"), ONE).where("subpop_key = '0|x'").first()
    assert (one["l1"], one["l2"], one["card"], one["entropy"]) == (1000, 10**6, 1, 0)
    many = B.ground_truth(frame(spark, [("x", i) for i in range(64)], "a string, m long"), ONE).where("subpop_key = '0|x'").first()
    assert many["card"] == 64 and math.isclose(many["entropy"], math.log(64)) and math.isclose(many["std"], math.sqrt((64**2 - 1) / 12))


def test_user_functions_are_checked(spark):
    S.GSum("ok", "ln(1 + f)").check(spark)
    for bad in ("f * f * f", "1.0 / f", "-f"):
        with pytest.raises(ValueError):
            S.GSum("bad", bad).check(spark)
    with pytest.raises(ValueError):
        S.moment(3)
    with pytest.raises(NotImplementedError):
        S.quantile(0.5)


# --- exactness and variants ---


@pytest.mark.parametrize("changes", [{}, {"layers": 6, "layer_mode": "nested"}, {"layers": 6}, {"hash_fn": "xxhash64", "layers": 4}, {"hash_mode": "many", "r": 3, "w": 16}])
def test_wide_heaps_give_the_truth(spark, changes):
    df, s = view(spark, SF, "docs"), spec_of("docs")
    cfg = EXACT.but(w_cs=64, **changes)
    e = M.relative_error(grid.estimate(grid.build_grid(df, s, cfg)), B.ground_truth(df, s))
    assert e.where("abs(err) > 1e-9").count() == 0


def test_counters_are_linear_and_heaps_merge(spark):
    df, s = view(spark, SF, "video"), spec_of("video", max_order=1)
    cfg = TINY.but(k=100_000, heap_value="tracked", merge_mode="full")
    parts = [grid.build_grid(df.where(c), s, cfg) for c in ("user10 < 3", "user10 >= 3 AND user10 < 7", "user10 >= 7")]
    whole = grid.build_grid(df, s, cfg)
    assert merge.merge_full(*parts).counters.exceptAll(whole.counters.select(parts[0].counters.columns)).count() == 0
    names = whole.heaps.columns
    for m in (merge.merge_heaps(*parts), merge.merge_heaps(merge.merge_heaps(parts[2], parts[0]), parts[1]), merge.merge_full(*parts)):
        assert m.heaps.select(names).exceptAll(whole.heaps).count() == 0 and m.heaps.count() == whole.heaps.count()
    with pytest.raises(ValueError):
        merge.merge_heaps(parts[0], grid.build_grid(df, s, cfg.but(salt=1)))
    with pytest.raises(ValueError):
        merge.merge_full(merge.merge_heaps(*parts), parts[0])


def test_full_merge_with_estimates_equals_one_build(spark):
    df, s = view(spark, SF, "video"), spec_of("video", max_order=1)
    cfg = TIGHT.but(k=100_000, merge_mode="full")
    whole = grid.build_grid(df, s, cfg)
    merged = merge.merge_full(*(grid.build_grid(df.where(c), s, cfg) for c in ("user10 < 5", "user10 >= 5")))
    # the merge re-estimates every key that had a positive value in a part
    assert merged.heaps.select(whole.heaps.columns).exceptAll(whole.heaps).count() == 0


def test_heap_only_merge_loses_at_most_the_least_entries(spark):
    df, s = view(spark, SF, "video"), spec_of("video", max_order=1)
    cfg = TINY.but(k=5, heap_value="tracked", layers=1)
    parts = [grid.build_grid(df.where(c), s, cfg) for c in ("user10 < 5", "user10 >= 5")]
    merged = merge.merge_heaps(*parts).heaps.alias("a")
    true = fanout.pair_counts(df, s).select("subpop_key", "m", F.col("f").alias("t"))
    lost = merged.join(true, ["subpop_key", "m"]).withColumn("lost", F.col("t") - F.col("f"))
    least = parts[0].heaps.unionByName(parts[1].heaps).groupBy("grid_row", "grid_col").agg(F.max("f").alias("top"))
    assert lost.where("lost < 0").count() == 0
    assert lost.join(least, ["grid_row", "grid_col"]).where("lost > top").count() == 0


def test_bare_values_collide_pair_keys_do_not(spark):
    df = frame(spark, [("x", 1)] * 10 + [("y", 1)] * 3, "a string, m long")
    one_cell = EXACT.but(w=1, w_cs=64)
    keys = fanout.pair_counts(df, ONE).select("subpop_key").distinct()
    bare = {r["subpop_key"]: r["l1"] for r in grid.estimate(grid.build_grid(df, ONE, one_cell.but(key_mode="metric")), keys).collect()}
    pair = {r["subpop_key"]: r["l1"] for r in grid.estimate(grid.build_grid(df, ONE, one_cell), keys).collect()}
    assert len(set(bare.values())) == 1 and pair == {"0|x": 10, "0|y": 3, "1|": 13}
    with pytest.raises(ValueError):
        grid.discover(grid.build_grid(df, ONE, one_cell.but(key_mode="metric")), "l1", 1)


def test_missed_subpopulations_count_as_zero(spark):
    df = view(spark, SF, "docs")
    asked = spark.createDataFrame([("0|no such",)], "subpop_key string")
    r = grid.estimate(grid.build_grid(df, spec_of("docs"), TINY), asked).first()
    assert r["found_rows"] == 0 and r["l1"] == 0 and r["entropy"] == 0


def test_estimates_do_not_depend_on_the_set_asked(spark):
    state = grid.build_grid(view(spark, SF, "video"), spec_of("video", max_order=2), TINY)
    alone = grid.estimate(state, None, {"l1": F.col("f")}).select("subpop_key", "l1")
    assert alone.exceptAll(grid.estimate(state).select("subpop_key", "l1")).count() == 0


def test_half_of_the_keys_reach_each_further_layer(spark):
    cells = U.to_cells(fanout.pair_counts(view(spark, SF, "flow_card"), spec_of("flow_card")), TIGHT)
    n = cells.count()
    for j in (1, 2, 3):
        assert abs(cells.where(f"depth >= {j}").count() / n - 2.0**-j) < 0.02
    assert abs(U.layered(cells, TIGHT.but(layer_mode="nested")).count() / n - 2) < 0.05


def test_estimates_are_unbiased_over_salts(spark):
    df, s = view(spark, SF, "video"), spec_of("video", cuboids=(("event_type",),))
    true = B.ground_truth(df, s)
    total = None
    for salt in range(12):
        cfg = TIGHT.but(k=12, w=2, r=1, salt=salt, heap_value="tracked")
        e = M.relative_error(grid.estimate(grid.build_grid(df, s, cfg)), true, ("l1",)).agg(F.avg("err")).first()[0]
        total = (total or 0) + e
    assert abs(total / 12) < 0.15


def test_more_rows_and_tighter_grids_err_less(spark):
    df, s = view(spark, SF, "video"), spec_of("video", max_order=2)
    true = B.ground_truth(df, s)
    err = lambda cfg: M.qualifying(M.relative_error(grid.estimate(grid.build_grid(df, s, cfg)), true), 0.002).agg(F.avg(F.abs("err"))).first()[0]
    small, large = err(TINY.but(k=10)), err(TIGHT)
    assert large < small and err(TINY.but(r=5, k=10)) < err(TINY.but(r=1, k=10)) * 1.05


def test_bounds_hold_for_pair_keys(spark):
    df, s = view(spark, SF, "flow_card"), spec_of("flow_card")
    errors = M.relative_error(grid.estimate(grid.build_grid(df, s, TIGHT)), B.ground_truth(df, s), ("l1", "card"))
    cover = {r["stat"]: r["coverage"] for r in M.bound_coverage(M.qualifying(errors, 0.002).drop("gs"), TIGHT, 0.1).collect()}
    assert cover["l1"] >= 0.9


# --- the bounded build ---


@pytest.mark.parametrize("limits", [{}, {"max_entries": 500}])
def test_bounded_counters_equal_the_declarative_ones(spark, limits):
    df, s = view(spark, SF, "video"), spec_of("video", max_order=1)
    cells = U.to_cells(fanout.pair_counts(df, s), TINY)
    want = U.counters(cells, TINY).where("c != 0")
    got = bounded.bounded_counters(df.repartition(3), s, TINY, **limits)
    assert got.count() == want.count() and got.exceptAll(want.select(got.columns)).count() == 0


def test_bounded_estimates(spark):
    df, s = view(spark, SF, "video"), spec_of("video", max_order=2)
    cfg = TIGHT.but(hash_fn="xxhash64", k=100_000)
    e = M.relative_error(grid.estimate(bounded.build_bounded(df.repartition(3), s, cfg)), B.ground_truth(df, s))
    assert e.where("abs(err) > 1e-9").count() == 0


def test_store_keeps_and_merges(spark, tmp_path):
    df, s = view(spark, SF, "video"), spec_of("video", max_order=1)
    cfg, path = TIGHT.but(k=100_000, heap_value="tracked", merge_mode="full"), f"file://{tmp_path}/store"
    for i, c in enumerate(("user10 < 5", "user10 >= 5")):
        store.append(grid.build_grid(df.where(c), s, cfg), path, str(i))
    store.append(grid.build_grid(df.where("user10 >= 5"), s, cfg), path, "1")  # again: replaces
    whole = grid.build_grid(df, s, cfg)
    got = store.compact(spark, path, s, cfg, frozen=False)
    assert got.counters.exceptAll(whole.counters.select(got.counters.columns)).count() == 0
    assert grid.estimate(got).exceptAll(grid.estimate(whole)).count() == 0


# --- configuration ---


def test_worked_configuration():
    x, w_u = C.optimal_inner(2e6, 1e3)
    assert math.isclose(x, 0.1) and w_u == 100
    eps, w = C.optimal_outer(2e6, 1e3)
    assert w == 20_000 and math.isclose(eps * 1e3, x / 2)
    assert math.isclose(C.optimal_inner(2e6, 1e3, printed_root=True)[0], math.sqrt(1e-3))
    assert C.rows_for(0.1) == 3 and C.heap_for(0.1) == 100
    assert C.strict_rows(0.1, 0.1, 10.5) == 3 and C.strict_rows(0.1) > 3
    with pytest.raises(ValueError):
        C.strict_rows(0.1, 0.4, 4)
    cfg = C.recommend(0.2, 0.1, 1e-3, 1e6)
    assert cfg.r == 3 and 5e3 < cfg.w < 5e4
    assert C.model_bytes(C.recommend(0.2, 0.1, 1e-3, 1e6, memory=10**8)) <= 10**8
    assert C.predicted_error(cfg, 1e3) <= 0.25


def test_hash_budget():
    assert hash_plan(GridConfig(r=3, layers=16, w_cs=128))["one"] is True
    assert hash_plan(GridConfig(r=5, layers=16, w_cs=128))["one"] is False
    with pytest.raises(ValueError):
        hash_plan(GridConfig(layers=30, r_cs=5, w_cs=4096))
    with pytest.raises(ValueError):
        GridConfig(r=2)


def test_op_counts_fall_with_each_optimisation():
    base = TIGHT.but(layer_mode="nested", hash_mode="many", merge_mode="full")
    none, last = C.op_counts(base, 1000, 4), C.op_counts(TIGHT, 1000, 4)
    assert all(last[k] < none[k] for k in none) and abs(none["layer_updates"] / last["layer_updates"] - 2) < 0.01


def test_cost_models_order_the_designs():
    cost = {d: C.cost_model(d, 10**6, 5, 15_000, 4, TIGHT) for d in ("per_key_state", "sketch_per_subpop_and_stat", "grid_per_stat", "universal_grid")}
    assert cost["universal_grid"][1] < cost["sketch_per_subpop_and_stat"][1] < cost["per_key_state"][1]
    assert cost["universal_grid"][0] < cost["grid_per_stat"][0]


# --- skew and samples ---


def test_zipf_sizes(spark):
    n = zipf(spark, 0.99, 20_000).groupBy("g").count().orderBy(F.desc("count")).collect()
    assert n[0]["g"] == 0 and sum(r["count"] for r in n) == 20_000 and n[0]["count"] > 10 * n[-1]["count"]
    assert B.ground_truth(zipf(spark, 0.0, 5000), ZIPF_SPEC).where("subpop_key = '1|'").first()["l1"] == 5000


def test_sample_correction_is_unbiased(spark):
    df = frame(spark, [("x", i % 20) for i in range(4000)], "a string, m long").withColumn("i", F.monotonically_increasing_id())
    got = []
    for k in range(10):
        kept = B.uniform_sample(df, F.concat(F.lit(f"{k}."), F.col("i").cast("string")), 4)
        got.append(B.sample_stats(kept, ONE, 4).where("subpop_key = '0|x'").first())
    assert abs(sum(r["l1"] for r in got) / 10 / 4000 - 1) < 0.05 and abs(sum(r["l2"] for r in got) / 10 / (20 * 200**2) - 1) < 0.08


def test_stateful_heaps_over_several_batches(spark, tmp_path):
    from subpopgrid.plans.streams import stateful_heaps
    from subpopgrid.streaming import windows as SW

    spec, cfg = WorkloadSpec(dims=("event_type",)), TINY.but(heap_value="tracked", k=1000)
    rows = spark.read.parquet(f"{SF}/events.parquet")
    for i in range(3):
        rows.where(F.col("event_id") % 3 == i).coalesce(1).write.mode("append").parquet(f"file://{tmp_path}/events")
    stream = spark.readStream.schema(SW.EVENTS).option("maxFilesPerTrigger", 1).parquet(f"file://{tmp_path}/events").withColumn("m", F.floor(F.col("value") / 10).cast("long"))
    got = stateful_heaps(stream, spec, cfg, f"file://{tmp_path}/work")
    batch = grid.build_grid(rows.withColumn("m", F.floor(F.col("value") / 10).cast("long")), spec, cfg).heaps
    assert batch.count() > 100 and got.exceptAll(batch.select(*got.columns)).count() == 0 == batch.select(*got.columns).exceptAll(got).count()


def test_windows_of_wide_heaps_give_the_truth(spark):
    from subpopgrid.streaming import windows as SW

    pairs = spark.createDataFrame([("a", "0|x", 1, 3), ("a", "0|x", 2, 1), ("b", "0|x", 1, 5), ("b", "1|", 7, 2)], "win string, subpop_key string, m long, f long")
    got = {(r["win"], r["subpop_key"]): (r["l1"], r["l2"], r["card"]) for r in SW.window_estimates(pairs, TINY.but(heap_value="tracked")).collect()}
    assert got == {("a", "0|x"): (4, 10, 2), ("b", "0|x"): (5, 25, 1), ("b", "1|"): (2, 4, 1)}


def test_least_counters_never_fall_short(spark):
    df, s = view(spark, SF, "docs"), spec_of("docs", max_order=2)
    pairs = fanout.pair_counts(df, s).select("subpop_key", "m", "f")
    both = B.countmin_points(pairs, TINY.but(layers=1, w_cs=16)).withColumnRenamed("f", "est").join(pairs, ["subpop_key", "m"])
    assert both.count() == pairs.count() and both.where("est < f").count() == 0 < both.where("est > f").count()
    hll = B.hll_grid_estimates(df, s, TINY.but(w=512, hash_fn="xxhash64")).join(B.ground_truth(df, s).select("subpop_key", F.col("card").alias("t")), "subpop_key")
    assert hll.where("card >= 0.9 * t").count() == hll.count() > 0


def test_hash_a_use_and_dense_counters_change_no_truth(spark, monkeypatch):
    df, s = view(spark, SF, "video"), spec_of("video", max_order=1)
    wide = GridConfig(w=8, layers=4, w_cs=64, k=100_000, heap_value="tracked")
    true = {r["subpop_key"]: (r["l1"], r["card"]) for r in B.ground_truth(df, s).collect()}
    for changes in ({"hash_mode": "many"}, {"layer_mode": "nested"}, {"merge_mode": "full"}):
        est = grid.estimate(bounded.build_bounded(df, s, wide.but(**changes)))
        assert {r["subpop_key"]: (r["l1"], r["card"]) for r in est.collect()} == true


def test_compaction_reads_all_parts_at_once(spark, tmp_path):
    df, s, cfg = view(spark, SF, "docs"), spec_of("docs", max_order=1), TINY.but(heap_value="tracked", k=1000, merge_mode="full")
    path = f"file://{tmp_path}/store"
    for i in range(3):
        store.append(grid.build_grid(df.where(F.pmod(F.hash("source"), F.lit(3)) == i), s, cfg), path, str(i))
    one = grid.build_grid(df, s, cfg)
    for frozen in (False, True):
        state = store.compact(spark, path, s, cfg, frozen)
        key = lambda h: sorted(map(tuple, h.select("grid_row", "grid_col", "layer", "subpop_key", "m", "f", "depth").collect()))
        assert key(state.heaps) == key(one.heaps)


def test_suggested_configuration_is_no_worse_than_the_base(spark):
    from subpopgrid.plans.catalog import QUERIES

    rows = QUERIES["w_W9_statistics"](spark, SF).toPandas()
    l1 = rows[rows.stat == "l1"].set_index("point").mean_abs
    assert set(rows.stat) == {"l1", "l2", "card", "entropy"} and l1["suggested"] <= 0.5 and l1["w=64"] <= l1["w=4"] and l1["k=200"] <= l1["k=10"]
