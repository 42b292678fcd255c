"""DuckDB SQL for the grid and its measures: the same numbers by another engine."""

from __future__ import annotations

from ..functions.hashing import HEX, hash_plan
from ..schema import GridConfig, WorkloadSpec
from ..sources.tables import spec_of, view_sql


def cast_list(cols: str) -> str:
    """``a:l b:d c:s`` as a select list: longs, doubles rounded to 6 digits, strings, booleans."""
    out = []
    for c in cols.split():
        name, kind = c.split(":")
        out.append({"l": f"CAST({name} AS BIGINT)", "d": f"round(CAST({name} AS DOUBLE), 6) + 0.0", "s": f"CAST({name} AS VARCHAR)", "b": f"CAST({name} AS BOOLEAN)"}[kind] + f" AS {name}")
    return ", ".join(out)


def key_sql(spec: WorkloadSpec, gid: str = "gid") -> str:
    n = len(spec.dims)
    parts = [f"CASE WHEN {gid} & {1 << (n - 1 - i)} = 0 THEN coalesce(replace(replace(CAST({d} AS VARCHAR), '\\', '\\\\'), chr(31), '\\u'), '\\N') END" for i, d in enumerate(spec.dims)]
    return f"CAST({gid} AS VARCHAR) || '|' || concat_ws(chr(31), {', '.join(parts)})"


def pairs_ctes(records: str, spec: WorkloadSpec) -> str:
    sets = ", ".join("(" + ", ".join([*c, "m"]) + ")" for c in spec.sets())
    used = {d for c in spec.sets() for d in c}
    dims = ", ".join(d if d in used else f"NULL AS {d}" for d in spec.dims)
    n = len(spec.dims)
    gid = " + ".join(f"CAST({f'grouping({d})' if d in used else 1} AS BIGINT) * {1 << (n - 1 - i)}" for i, d in enumerate(spec.dims))
    names = ", ".join(spec.dims)
    weight = spec.weight or "1"
    return (
        f"recs AS MATERIALIZED ({records}), grouped AS MATERIALIZED (SELECT {dims}, m, CAST(sum({weight}) AS BIGINT) AS f, {gid} AS gid FROM recs GROUP BY GROUPING SETS ({sets})), "
        f"pairs AS MATERIALIZED (SELECT gid, {names}, {key_sql(spec)} AS subpop_key, m, f FROM grouped)"
    )


TRUTH = (
    "sums AS MATERIALIZED (SELECT subpop_key, sum(f) AS l1, sum(f * f) AS l2, count(*) AS card, sum(f * ln(CAST(f AS DOUBLE))) AS flogf, sum(m * f) AS mf, sum(m * m * f) AS mmf FROM pairs GROUP BY subpop_key), "
    "truth AS MATERIALIZED (SELECT *, greatest(ln(l1) - flogf / l1, 0) AS entropy, mf / l1 AS mean, sqrt(greatest(mmf / l1 - (mf / l1) * (mf / l1), 0)) AS std FROM sums)"
)


def cells_ctes(cfg: GridConfig) -> str:
    plan, t = hash_plan(cfg), "subpop_key || chr(31) || m" if cfg.key_mode == "pair" else "CAST(m AS VARCHAR)"
    row = "0" if cfg.row_bits == "shared" else "r"
    d = plan["col_digits"]
    col = f"CAST('0x' || substr(md5('s{cfg.salt}|' || subpop_key), CAST(r * {d} + 1 AS INT), {d}) AS BIGINT) % {cfg.w}"
    if plan["one"]:
        x = f"CAST('0x' || substr(md5('p{cfg.salt}|' || {t}), CAST({row} * {plan['digits']} + 1 AS INT), {plan['digits']}) AS BIGINT)"
    else:
        x = f"CAST('0x' || substr(md5('p{cfg.salt}|' || {row} || '|' || {t}), 1, {HEX}) AS BIGINT)"
    mask = (1 << (cfg.layers - 1)) - 1
    depth = f"bit_count(xor(x & {mask}, (x & {mask}) + 1)) - 1" if cfg.layers > 1 else "0"
    raw = f"SELECT subpop_key, m, f, r AS grid_row, {col} AS grid_col, {x} AS x FROM pairs, (SELECT unnest(range({cfg.r})) AS r)"
    if cfg.key_mode == "metric":
        raw = f"SELECT '' AS subpop_key, m, sum(f) AS f, grid_row, grid_col, x FROM ({raw}) GROUP BY m, grid_row, grid_col, x"
    return f"cells AS MATERIALIZED (SELECT *, CAST({depth} AS BIGINT) AS depth FROM ({raw}))"


def heap_ctes(cfg: GridConfig, cells: str = "cells", suffix: str = "") -> str:
    """Counters, estimates, heaps and nested heaps."""
    layered = f"SELECT *, depth AS layer FROM {cells}" if cfg.layer_mode == "deepest" else f"SELECT *, unnest(range(0, depth + 1)) AS layer FROM {cells}"
    at = f"({cfg.layers - 1} + j * {cfg.cs_bits + 1})"
    probe = f"SELECT *, (x >> CAST({at} AS INT)) & {cfg.w_cs - 1} AS cs_col, ((x >> CAST({at} + {cfg.cs_bits} AS INT)) & 1) * 2 - 1 AS s FROM layered{suffix}, (SELECT unnest(range({cfg.r_cs})) AS j)"
    counters = f"counters{suffix} AS MATERIALIZED (SELECT grid_row, grid_col, layer, j AS cs_row, cs_col, CAST(sum(s * f) AS BIGINT) AS c FROM probes{suffix} GROUP BY ALL)"
    if cfg.heap_value == "tracked":
        est = f"est{suffix} AS MATERIALIZED (SELECT grid_row, grid_col, layer, subpop_key, m, f, depth FROM layered{suffix})"
    else:
        est = (
            f"est{suffix} AS MATERIALIZED (SELECT p.grid_row, p.grid_col, p.layer, p.subpop_key, p.m, p.depth, list_sort(list(s * c))[{cfg.r_cs // 2 + 1}] AS f FROM probes{suffix} p "
            f"JOIN counters{suffix} q ON p.grid_row = q.grid_row AND p.grid_col = q.grid_col AND p.layer = q.layer AND p.j = q.cs_row AND p.cs_col = q.cs_col GROUP BY ALL)"
        )
    best = lambda src: f"SELECT * FROM {src} WHERE f > 0 QUALIFY row_number() OVER (PARTITION BY grid_row, grid_col, layer ORDER BY f DESC, subpop_key, m) <= {cfg.k}"
    ctes = [f"layered{suffix} AS MATERIALIZED ({layered})", f"probes{suffix} AS MATERIALIZED ({probe})", counters, est, f"heaps{suffix} AS MATERIALIZED ({best(f'est{suffix}')})"]
    return ", ".join([*ctes, nested_cte(cfg, f"heaps{suffix}", suffix)])


def nested_cte(cfg: GridConfig, heaps: str = "heaps", suffix: str = "") -> str:
    if cfg.layer_mode == "nested":
        return f"nested{suffix} AS MATERIALIZED (SELECT * FROM {heaps})"
    every = f"(SELECT * EXCLUDE (layer), unnest(range(0, depth + 1)) AS layer FROM {heaps})"
    return f"nested{suffix} AS MATERIALIZED (SELECT * FROM {every} QUALIFY row_number() OVER (PARTITION BY grid_row, grid_col, layer ORDER BY f DESC, subpop_key, m) <= {cfg.k})"


SUM_SQL = {"l1": "f", "l2": "f * f", "card": "1", "flogf": "f * ln(CAST(f AS DOUBLE))", "mf": "m * f", "mmf": "m * m * f"}


def estimate_ctes(cfg: GridConfig, gs: dict[str, str] | None = None, subpops: str | None = None, suffix: str = "") -> str:
    gs = gs or SUM_SQL
    weight = f"CASE WHEN layer = {cfg.layers - 1} THEN 1 << CAST(layer AS INT) WHEN depth > layer THEN -(1 << CAST(layer AS INT)) ELSE 1 << CAST(layer AS INT) END"
    sums = ", ".join(f"sum(w * {g}) AS {n}" for n, g in gs.items())
    weighted = f"weighted{suffix} AS MATERIALIZED (SELECT *, {weight} AS w FROM nested{suffix})"
    if cfg.key_mode == "pair":
        rows = f"SELECT subpop_key, grid_row, {sums} FROM weighted{suffix} GROUP BY subpop_key, grid_row"
    else:
        d = hash_plan(cfg)["col_digits"]
        cell = f"SELECT grid_row, grid_col, {sums} FROM weighted{suffix} GROUP BY grid_row, grid_col"
        keys = f"SELECT subpop_key, r AS grid_row, CAST('0x' || substr(md5('s{cfg.salt}|' || subpop_key), CAST(r * {d} + 1 AS INT), {d}) AS BIGINT) % {cfg.w} AS grid_col FROM (SELECT DISTINCT subpop_key FROM pairs), (SELECT unnest(range({cfg.r})) AS r)"
        rows = f"SELECT k.subpop_key, k.grid_row, c.* EXCLUDE (grid_row, grid_col) FROM ({keys}) k LEFT JOIN ({cell}) c ON k.grid_row = c.grid_row AND k.grid_col = c.grid_col"
    derived, names = "*", list(gs)
    if {"l1", "flogf"} <= set(gs):
        h = "greatest(ln(l1) - flogf / l1, 0)"
        derived += f", CASE WHEN l1 > 0 THEN {f'least({h}, ln(greatest(card, 1)))' if 'card' in gs else h} END AS entropy"
        names.append("entropy")
    if {"l1", "mf", "mmf"} <= set(gs):
        derived += ", CASE WHEN l1 > 0 THEN mf / l1 END AS mean, CASE WHEN l1 > 0 THEN sqrt(greatest(mmf / l1 - (mf / l1) * (mf / l1), 0)) END AS std"
        names += ["mean", "std"]
    med = ", ".join(f"list_sort(list_concat(list(coalesce(CAST({n} AS DOUBLE), 0)), list_transform(range({cfg.r} - count(*)), lambda i: CAST(0 AS DOUBLE))))[{cfg.r // 2 + 1}] AS {n}" for n in names)
    ctes = [weighted, f"row_sums{suffix} AS MATERIALIZED (SELECT {derived} FROM ({rows}))", f"found{suffix} AS MATERIALIZED (SELECT subpop_key, count(*) AS found_rows, {med} FROM row_sums{suffix} GROUP BY subpop_key)"]
    if subpops:
        back = ", ".join(f"coalesce(e.{n}, 0) AS {n}" for n in ["found_rows", *names])
        ctes.append(f"estimates{suffix} AS MATERIALIZED (SELECT k.subpop_key, {back} FROM ({subpops}) k LEFT JOIN found{suffix} e ON k.subpop_key = e.subpop_key)")
    else:
        ctes.append(f"estimates{suffix} AS MATERIALIZED (SELECT * FROM found{suffix})")
    return ", ".join(ctes)


ALL_KEYS = "SELECT DISTINCT subpop_key FROM pairs"


def grid_ctes(view: str | tuple[str, WorkloadSpec], cfg: GridConfig, gs: dict[str, str] | None = None, **spec) -> str:
    """Everything from records to estimates of all subpopulations, and the truth."""
    records, s = (view_sql(view), spec_of(view, **spec)) if isinstance(view, str) else view
    return ", ".join([pairs_ctes(records, s), TRUTH, cells_ctes(cfg), heap_ctes(cfg), estimate_ctes(cfg, gs, ALL_KEYS)])


def error_ctes(stats=("l1", "l2", "card", "entropy"), est: str = "estimates", true: str = "truth") -> str:
    rows = " UNION ALL ".join(f"SELECT t.subpop_key, '{s}' AS stat, CAST(t.{s} AS DOUBLE) AS truth, coalesce(CAST(e.{s} AS DOUBLE), 0) AS est FROM {true} t LEFT JOIN {est} e ON t.subpop_key = e.subpop_key" for s in stats)
    return f"errors AS MATERIALIZED (SELECT *, (est - truth) / truth AS err FROM ({rows}) WHERE truth != 0)"


def qualifying_cte(share: float) -> str:
    return f"big AS MATERIALIZED (SELECT e.*, gs FROM errors e JOIN (SELECT stat, sum(truth) AS gs FROM errors GROUP BY stat) g ON e.stat = g.stat WHERE truth >= {share} * gs)"
