"""Declared workloads, sketch configurations and the canonical key of a subpopulation."""

from __future__ import annotations

import hashlib
import json
from dataclasses import asdict, dataclass, replace
from itertools import combinations

SEPARATOR = "\x1f"


@dataclass(frozen=True)
class WorkloadSpec:
    """Which columns are dimensions, which one is the metric (a discrete BIGINT), and an optional weight.

    ``cuboids`` names subsets of the dimensions; otherwise all of at most ``max_order`` dimensions are meant, with the
    grand total unless ``include_total`` is off.
    """

    dims: tuple[str, ...]
    metric: str = "m"
    weight: str | None = None
    time: str | None = None
    max_order: int | None = None
    include_total: bool = True
    cuboids: tuple[tuple[str, ...], ...] | None = None

    def sets(self) -> list[tuple[str, ...]]:
        if self.cuboids is not None:
            return list(self.cuboids)
        top = len(self.dims) if self.max_order is None else self.max_order
        return [c for k in range(0 if self.include_total else 1, top + 1) for c in combinations(self.dims, k)]

    def gid(self, cuboid: tuple[str, ...]) -> int:
        """Grouping-set id: the first dimension is the highest bit, 1 means rolled up."""
        return sum(1 << (len(self.dims) - 1 - i) for i, d in enumerate(self.dims) if d not in cuboid)


@dataclass(frozen=True)
class GridConfig:
    """The grid's parameters: r x w cells; a cell has ``layers`` Count-Sketches of r_cs x w_cs counters and heaps of k."""

    r: int = 3
    w: int = 32
    layers: int = 10
    r_cs: int = 3
    w_cs: int = 128
    k: int = 100
    cell: str = "universal"  # universal, hll, countmin, countsketch
    key_mode: str = "pair"  # pair: (subpopulation, value); metric: bare value
    layer_mode: str = "deepest"  # deepest: one layer a key; nested: all layers it reaches
    hash_mode: str = "one"  # one: bit fields of one wide hash; many: a hash a use
    hash_fn: str = "xxhash64"  # xxhash64: fast; md5: portable to other engines
    row_bits: str = "independent"  # independent: every grid row has its own layer bits; shared: all the same
    merge_mode: str = "heap_only"  # heap_only, full
    heap_value: str = "estimate"  # estimate: Count-Sketch value; tracked: exact within the build
    key_store: str = "text"  # text, fingerprint
    salt: int = 0

    def __post_init__(self) -> None:
        if self.r % 2 == 0 or self.r_cs % 2 == 0:
            raise ValueError("r and r_cs must be odd, so that a median is one of the estimates")
        if self.w_cs & (self.w_cs - 1):
            raise ValueError("w_cs must be a power of two: buckets are bit fields")

    @property
    def cs_bits(self) -> int:
        return self.w_cs.bit_length() - 1

    @property
    def row_bits_needed(self) -> int:
        return self.layers - 1 + self.r_cs * (self.cs_bits + 1)

    def but(self, **changes) -> GridConfig:
        return replace(self, **changes)

    def manifest(self) -> str:
        return json.dumps(asdict(self), sort_keys=True)

    @property
    def config_id(self) -> str:
        """States of different ids never merge."""
        return hashlib.md5(self.manifest().encode()).hexdigest()[:12]


#: Configurations by purpose: ``exact`` holds everything, ``tiny`` and ``tight`` approximate, ``paper_like`` is sized for real runs.
EXACT = GridConfig(r=1, w=64, layers=1, w_cs=4096, k=100_000, heap_value="tracked", hash_fn="md5")
TINY = GridConfig(w=8, layers=6, w_cs=64, k=25, hash_fn="md5")
TIGHT = GridConfig(w=32, layers=10, w_cs=128, k=100, hash_fn="md5")
PAPER_LIKE = GridConfig(w=1024, layers=10, w_cs=128, k=100)
