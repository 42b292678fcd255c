"""The bounded builder: one grid a task, over Arrow batches, then a merge of bounded state.

A task collapses equal combinations of all dimensions and value, fans the collapsed rows out as arrays, and keeps for
every (cell, layer) its largest candidates and, unless the state is heaps only, its counters. It never holds more than
``max_entries`` candidates, collapsed rows or touched counters: beyond that it cuts, or emits what it has and begins
anew, which is safe as states add. Rows out of a task are bounded by the configuration, so the shuffle behind it does
not grow with the records.

``hash_fn='md5'`` hashes canonical texts and so gives the declarative build's counters bit for bit (slow: for checks);
``xxhash64`` mixes per-dimension hashes, which makes 2^D cuboids affordable. Mixed cells are the builder's own: with
pair keys queries find their subpopulations by key, so only bare-value grids need md5 here.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import HEX, hash_plan
from ..schema import SEPARATOR, GridConfig, WorkloadSpec
from ..sources.tables import scratch
from . import universal as U
from .fanout import weight_of
from .grid import GridState
from .merge import add_counters, tree_merge

SCHEMA = "part int, kind string, grid_row int, grid_col int, layer int, cs_row int, cs_col int, c long, subpop_key string, m long, f long, depth int"


#: A task holds all counters of a grid of at most so many bytes; those of a larger grid it holds as they are touched.
DENSE_BYTES = 256 << 20
ENTRY = (("cell", np.int64), ("pair", np.uint64), ("sub", np.uint64), ("m", np.int64), ("f", np.int64), ("depth", np.int64))


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _seed(*parts) -> np.uint64:
    return np.uint64(int(hashlib.md5("|".join(map(str, parts)).encode()).hexdigest()[:16], 16))


def _text(v) -> str:
    return "\\N" if v is None or v != v else str(v).replace("\\", "\\\\").replace(SEPARATOR, "\\u")


class _Builder:
    """One task's grid as flat arrays."""

    def __init__(self, spec: WorkloadSpec, cfg: GridConfig, part: int, max_entries: int):
        if cfg.key_mode == "metric" and cfg.hash_fn != "md5":
            raise ValueError("bare values need md5 here: queries must find the builder's cells")
        self.spec, self.cfg, self.part, self.max_entries = spec, cfg, part, max_entries
        self.plan, self.frames, self.waiting = hash_plan(cfg), [], 0
        self.counted = cfg.merge_mode == "full"
        self.reset()

    def reset(self) -> None:
        cfg = self.cfg
        size = cfg.r * cfg.w * cfg.layers * cfg.r_cs * cfg.w_cs
        #: All counters of the grid where they are few enough, else the touched ones as (places, sums).
        self.dense = np.zeros(size, np.int64) if self.counted and 8 * size <= DENSE_BYTES else None
        self.counters: tuple[np.ndarray, np.ndarray] = (np.empty(0, np.int64), np.empty(0, np.int64))
        self.entries = {k: np.empty(0, t) for k, t in ENTRY}
        self.fresh: list[dict] = []  # candidates since the last cut, with the cuboid and row that name them
        self.n_fresh = 0
        self.names: dict[int, str] = {}

    def add(self, frame) -> None:
        self.frames.append(self.collapse(frame))
        self.waiting += len(self.frames[-1])
        if self.waiting > self.max_entries // 8 and len(self.frames) > 1:
            self.frames = [self.collapse(self.joined())]
            self.waiting = len(self.frames[0])
        if self.waiting > self.max_entries // 8:
            self.fan_out()

    def collapse(self, frame):
        return frame.groupby([*self.spec.dims, "m"], dropna=False, sort=False)["wgt"].sum().reset_index()

    def joined(self):
        import pandas as pd

        return pd.concat(self.frames, ignore_index=True)

    def fan_out(self) -> None:
        """Pairs of every cuboid of the collapsed rows, into cells."""
        import pandas as pd
        import xxhash

        if not self.frames:
            return
        frame = self.collapse(self.joined()) if len(self.frames) > 1 else self.frames[0]
        self.frames, self.waiting = [], 0
        m, w = frame["m"].to_numpy(np.int64), frame["wgt"].to_numpy(np.int64)
        codes, texts, hashes = {}, {}, {}
        for d in self.spec.dims:
            c, values = pd.factorize(frame[d].map(_text), sort=False)
            codes[d], texts[d] = c, list(values)
            hashes[d] = np.array([xxhash.xxh64_intdigest(t.encode(), seed=self.cfg.salt) for t in texts[d]], np.uint64)
        cuboids = self.spec.sets()
        key = lambda c, i: f"{self.spec.gid(cuboids[c])}|" + SEPARATOR.join(texts[d][codes[d][i]] for d in cuboids[c])
        for c, cuboid in enumerate(cuboids):
            sub = np.full(len(m), _seed(self.cfg.salt, self.spec.gid(cuboid)), np.uint64)
            for d in cuboid:
                sub = _mix(sub * np.uint64(0x9E3779B97F4A7C15) + hashes[d][codes[d]])
            pair = _mix(sub * np.uint64(0xD1B54A32D192ED03) + _mix(m.astype(np.uint64) + np.uint64(0x632BE59BD9B4E019)))
            order = np.argsort(pair)
            first = np.flatnonzero(np.r_[True, pair[order][1:] != pair[order][:-1]])
            at, f = order[first], np.add.reduceat(w[order], first)
            self.to_cells(sub[at], pair[at], m[at], f, at, c, key)
            if self.n_fresh > self.max_entries:
                self.settle(key)
        self.settle(key)

    def fields(self, sub, pair, m, at, c, key) -> list[tuple[np.ndarray, np.ndarray]]:
        """(grid column, bit fields) of every grid row."""
        cfg, plan = self.cfg, self.plan
        rows = [0 if cfg.row_bits == "shared" else i for i in range(cfg.r)]
        if cfg.hash_fn != "md5":
            many = cfg.hash_mode == "many"
            return [((_mix(sub + _seed("col", i)) % np.uint64(cfg.w)).astype(np.int64), self.separate(pair, k) if many else (_mix(pair + _seed("x", k)) >> np.uint64(4)).astype(np.int64)) for i, k in enumerate(rows)]
        md5 = lambda t: hashlib.md5(t.encode()).hexdigest()
        names, d, out = [key(c, i) for i in at], plan["col_digits"], []
        cols = [md5(f"s{cfg.salt}|{n}") for n in names]
        full = [f"{n}{SEPARATOR}{v}" if cfg.key_mode == "pair" else str(v) for n, v in zip(names, m, strict=True)]
        once = [md5(f"p{cfg.salt}|{t}") for t in full] if plan["one"] else None
        for i, k in enumerate(rows):
            col = np.array([int(h[i * d : (i + 1) * d], 16) % cfg.w for h in cols], np.int64)
            if once is not None:
                x = [int(h[k * plan["digits"] : (k + 1) * plan["digits"]], 16) for h in once]
            else:
                x = [int(md5(f"p{cfg.salt}|{k}|{t}")[:HEX], 16) for t in full]
            out.append((col, np.array(x, np.int64)))
        return out

    def separate(self, pair: np.ndarray, row: int) -> np.ndarray:
        """A row's bit fields from a hash a use: each sampling bit, bucket and sign has its own."""
        cfg, x = self.cfg, np.zeros(len(pair), np.int64)
        uses = [(j, 1) for j in range(cfg.layers - 1)] + [(cfg.layers - 1 + j * (cfg.cs_bits + 1) + o, n) for j in range(cfg.r_cs) for o, n in ((0, cfg.cs_bits), (cfg.cs_bits, 1))]
        for at, bits in uses:
            x |= (_mix(pair + _seed("x", row, at)) >> np.uint64(64 - bits)).astype(np.int64) << at
        return x

    def to_cells(self, sub, pair, m, f, at, c, key) -> None:
        cfg = self.cfg
        mask = (1 << (cfg.layers - 1)) - 1
        if cfg.key_mode == "metric":
            name, ident = np.zeros(len(m), np.uint64), _mix(m.astype(np.uint64))
        else:
            name, ident = sub, pair
        for row, (col, x) in enumerate(self.fields(sub, pair, m, at, c, key)):
            low = x & mask
            depth = np.bitwise_count(low ^ (low + 1)).astype(np.int64) - 1
            for layer in range(cfg.layers if cfg.layer_mode == "nested" else 1):
                pick = depth >= layer if cfg.layer_mode == "nested" else slice(None)
                if cfg.layer_mode == "nested" and not pick.any():
                    break
                xs, fs, ds = x[pick], f[pick], depth[pick]
                cell = (row * cfg.w + col[pick]) * cfg.layers + (layer if cfg.layer_mode == "nested" else ds)
                self.fresh.append({"cell": cell, "pair": ident[pick], "sub": name[pick], "m": m[pick], "f": fs, "depth": ds, "at": at[pick], "cuboid": np.full(len(cell), c, np.int32)})
                self.n_fresh += len(cell)
                if self.counted:
                    for j in range(cfg.r_cs):
                        start = cfg.layers - 1 + j * (cfg.cs_bits + 1)
                        slot = (cell * cfg.r_cs + j) * cfg.w_cs + (xs >> start & (cfg.w_cs - 1))
                        self.count(slot, fs * ((xs >> (start + cfg.cs_bits) & 1) * 2 - 1))

    def settle(self, key) -> None:
        """The candidates since the last cut join the kept ones; new survivors get their texts while their rows are at hand."""
        if not self.fresh:
            return
        n = len(self.entries["cell"])
        both = {k: np.concatenate([self.entries[k], *(p[k] for p in self.fresh)]) for k, _ in ENTRY}
        at, cuboid = (np.concatenate([p[k] for p in self.fresh]) for k in ("at", "cuboid"))
        self.fresh, self.n_fresh = [], 0
        self.entries, first = self.cut(both)
        if self.cfg.key_mode == "pair":
            came = first[first >= n] - n
            subs, one = np.unique(both["sub"][came + n], return_index=True)
            for s, i in zip(subs.tolist(), came[one].tolist(), strict=True):
                if s not in self.names:
                    self.names[s] = key(cuboid[i], at[i])
            if len(self.names) > 4 * self.max_entries:
                alive = set(self.entries["sub"].tolist())
                self.names = {s: t for s, t in self.names.items() if s in alive}

    def count(self, slot, value) -> None:
        if self.dense is not None:
            np.add.at(self.dense, slot, value)
            return
        slots, inverse = np.unique(np.concatenate([self.counters[0], slot]), return_inverse=True)
        sums = np.zeros(len(slots), np.int64)
        np.add.at(sums, inverse, np.concatenate([self.counters[1], value]))
        self.counters = (slots, sums)

    def cut(self, e: dict, k: int | None = None) -> tuple[dict, np.ndarray]:
        """Equal keys of a cell become one; with too many, each cell keeps its 2k (or k) largest. Also where each came first."""
        order = np.lexsort((e["pair"], e["cell"]))
        cell, pair = e["cell"][order], e["pair"][order]
        first = np.flatnonzero(np.r_[True, (cell[1:] != cell[:-1]) | (pair[1:] != pair[:-1])]) if len(cell) else np.empty(0, int)
        f = np.add.reduceat(e["f"][order], first) if len(first) else np.empty(0, np.int64)
        at = order[first]
        out = {c: e[c][at] for c in e} | {"f": f}
        if k or len(f) > self.max_entries:
            by = np.lexsort((out["pair"], -f, out["cell"]))
            c = out["cell"][by]
            start = np.flatnonzero(np.r_[True, c[1:] != c[:-1]]) if len(c) else np.empty(0, int)
            place = np.arange(len(c)) - np.repeat(start, np.diff(np.r_[start, len(c)]))
            by = by[place < (k or 2 * self.cfg.k)]
            out, at = {n: v[by] for n, v in out.items()}, at[by]
        return out, at

    def full(self) -> bool:
        return len(self.counters[0]) > 4 * self.max_entries

    def emit(self):
        """The task's rows so far, as columns; then empty."""
        cfg, (slots, sums) = self.cfg, self.counters
        if self.dense is not None:
            slots = np.flatnonzero(self.dense)
            sums = self.dense[slots]
        live = sums != 0
        slots, sums = slots[live], sums[live]
        cell = slots // (cfg.r_cs * cfg.w_cs)
        yield "c", {"cell": cell, "cs_row": slots // cfg.w_cs % cfg.r_cs, "cs_col": slots % cfg.w_cs, "c": sums}
        top, _ = self.cut(self.entries, cfg.k)
        yield "h", {"cell": top["cell"], "subpop_key": [self.names.get(int(s), "") for s in top["sub"]], "m": top["m"], "f": top["f"], "depth": top["depth"]}
        self.reset()


def build_parts(df: DataFrame, spec: WorkloadSpec, cfg: GridConfig, max_entries: int = 1_000_000) -> DataFrame:
    """Rows of every task's counters (kind ``c``; none in heap-only states) and heaps (kind ``h``)."""
    rows = df.select(*spec.dims, F.col(spec.metric).cast("long").alias("m"), weight_of(spec).alias("wgt"))
    columns = [c.split() for c in SCHEMA.split(", ")]

    def build(batches):
        import pyarrow as pa
        from pyspark import TaskContext

        kinds = {"int": pa.int32(), "long": pa.int64(), "string": pa.string()}
        one = _Builder(spec, cfg, TaskContext.get().partitionId(), max_entries)

        def emit():
            for kind, found in one.emit():
                cell = found.pop("cell")
                found |= {"grid_row": cell // (cfg.layers * cfg.w), "grid_col": cell // cfg.layers % cfg.w, "layer": cell % cfg.layers}
                for i in range(0, len(cell), 50_000):
                    n = min(50_000, len(cell) - i)
                    fixed = {"part": pa.array([one.part] * n, pa.int32()), "kind": pa.array([kind] * n)}
                    yield pa.RecordBatch.from_arrays([fixed[c] if c in fixed else pa.array(found[c][i : i + n]).cast(kinds[k]) if c in found else pa.nulls(n, kinds[k]) for c, k in columns], names=[c for c, _ in columns])

        for b in batches:
            if b.num_rows:
                one.add(pa.Table.from_batches([b]).to_pandas(integer_object_nulls=True))
                if one.full():
                    yield from emit()
        one.fan_out()
        yield from emit()

    return rows.mapInArrow(build, SCHEMA)


def build_bounded(df: DataFrame, spec: WorkloadSpec, cfg: GridConfig, **limits) -> GridState:
    """Task grids merged by sums: the scalable build. Heap values are the tasks' tracked counts."""
    parts = build_parts(df, spec, cfg, **limits)
    if cfg.merge_mode != "heap_only":  # heaps and counters are both read: records are scanned once, for a stored table
        path = scratch(df.sparkSession, "grid-parts")
        parts.write.parquet(path)
        parts = df.sparkSession.read.schema(SCHEMA).parquet(path)
    heaps = parts.where("kind = 'h'").select("part", *U.CELL, "layer", "subpop_key", "m", "f", "depth")
    counters = parts.where("kind = 'c'").select(*U.CELL, "layer", "cs_row", "cs_col", "c")
    return tree_merge(heaps, None if cfg.merge_mode == "heap_only" else counters, GridState(spec, cfg, heaps))


def bounded_counters(df: DataFrame, spec: WorkloadSpec, cfg: GridConfig, **limits) -> DataFrame:
    """Merged counters: equal to the declarative build's, however records are split."""
    parts = build_parts(df, spec, cfg.but(merge_mode="full"), **limits).where("kind = 'c'")
    return add_counters(parts).where("c != 0")
