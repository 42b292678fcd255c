"""Bit fields of wide hashes: grid columns of a subpopulation, layers, buckets and signs of a key.

A subpopulation's cell depends on it alone (a query knows no more). A key's hash gives, for every grid row,
``layers - 1`` sampling bits and for each Count-Sketch row a bucket and a sign. With ``hash_mode='one'`` the rows
share one 128-bit hash if their fields fit; else, and with ``'many'``, each row has a hash of its own.
``md5`` is the portable hash, ``xxhash64`` (one 64-bit word a row, seeded) the fast one.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..schema import SEPARATOR, GridConfig, WorkloadSpec

HEX = 15  # hexadecimal digits that always fit a signed 64-bit integer


def hash_plan(cfg: GridConfig) -> dict:
    """How the fields lie: hexadecimal digits a row, and whether one wide hash holds all rows."""
    digits = min(HEX, 32 // cfg.r)
    fits = cfg.row_bits_needed <= 4 * digits
    if cfg.row_bits_needed > 4 * HEX:
        raise ValueError(f"a row needs {cfg.row_bits_needed} bits; {4 * HEX} is the most: use fewer layers or narrower sketches")
    shared = cfg.hash_mode == "one" and (fits or cfg.row_bits == "shared")
    return {"digits": digits if shared and cfg.row_bits != "shared" else HEX, "one": shared, "hashes_per_pair": 1 if shared else cfg.r, "col_digits": digits}


def canonical_key(spec: WorkloadSpec, gid: str = "gid") -> Column:
    """``gid|a<US>b``: only dims of the cuboid are written; NULL is ``\\N``; separator and backslash are escaped."""
    parts = []
    for i, d in enumerate(spec.dims):
        text = F.replace(F.replace(F.col(d).cast("string"), F.lit("\\"), F.lit("\\\\")), F.lit(SEPARATOR), F.lit("\\u"))
        present = (F.col(gid).bitwiseAND(1 << (len(spec.dims) - 1 - i))) == 0
        parts.append(F.when(present, F.coalesce(text, F.lit("\\N"))))
    return F.concat(F.col(gid).cast("string"), F.lit("|"), F.concat_ws(SEPARATOR, *parts))


def _slice(text: Column, start: int, digits: int) -> Column:
    return F.conv(F.substring(text, start + 1, digits), 16, 10).cast("long")


def add_cells(df: DataFrame, cfg: GridConfig, key: str = "subpop_key") -> DataFrame:
    """A row for each grid row: adds ``grid_row`` and ``grid_col``."""
    if cfg.hash_fn == "md5":
        digits = hash_plan(cfg)["col_digits"]
        df = df.withColumn("_h", F.md5(F.concat(F.lit(f"s{cfg.salt}|"), F.col(key))))
        cols = [_slice(F.col("_h"), i * digits, digits) % cfg.w for i in range(cfg.r)]
    else:
        cols = [F.pmod(F.xxhash64(F.lit(cfg.salt), F.lit(i), F.col(key)), F.lit(cfg.w)) for i in range(cfg.r)]
    rows = F.posexplode(F.array(*(c.cast("int") for c in cols))).alias("grid_row", "grid_col")
    return df.select("*", rows).drop("_h")


def add_fields(df: DataFrame, cfg: GridConfig, row: str = "grid_row") -> DataFrame:
    """Adds ``x``, the key's bit fields for its grid row, and ``depth``, the deepest layer it is sampled into."""
    plan = hash_plan(cfg)
    text = F.concat(F.col("subpop_key"), F.lit(SEPARATOR), F.col("m").cast("string")) if cfg.key_mode == "pair" else F.col("m").cast("string")
    which = F.lit(0) if cfg.row_bits == "shared" else F.col(row)
    if cfg.hash_fn == "md5":
        if plan["one"]:
            h = F.md5(F.concat(F.lit(f"p{cfg.salt}|"), text))
            x = F.conv(F.substring(h, which * plan["digits"] + 1, F.lit(plan["digits"])), 16, 10).cast("long")
        else:
            x = _slice(F.md5(F.concat(F.lit(f"p{cfg.salt}|"), which.cast("string"), F.lit("|"), text)), 0, HEX)
    else:
        x = F.shiftrightunsigned(F.xxhash64(F.lit(cfg.salt), F.lit("p"), which, text), 4)
    df = df.withColumn("x", x)
    return df.withColumn("depth", layer_depth(F.col("x"), cfg.layers))


def layer_depth(x: Column, layers: int) -> Column:
    """Trailing ones of the sampling bits: each further layer keeps half of the keys."""
    if layers == 1:
        return F.lit(0)
    bits = x.bitwiseAND((1 << (layers - 1)) - 1)
    return (F.bit_count(bits.bitwiseXOR(bits + 1)) - 1).cast("int")


def bucket(x: Column, cs_row: Column | int, cfg: GridConfig) -> Column:
    at = (F.lit(cs_row) if isinstance(cs_row, int) else cs_row) * (cfg.cs_bits + 1) + (cfg.layers - 1)
    return F.call_function("shiftright", x, at.cast("int")).bitwiseAND(cfg.w_cs - 1).cast("int")


def sign(x: Column, cs_row: Column | int, cfg: GridConfig) -> Column:
    at = (F.lit(cs_row) if isinstance(cs_row, int) else cs_row) * (cfg.cs_bits + 1) + (cfg.layers - 1 + cfg.cs_bits)
    return (F.call_function("shiftright", x, at.cast("int")).bitwiseAND(1) * 2 - 1).cast("long")
