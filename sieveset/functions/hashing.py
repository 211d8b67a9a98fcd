"""The 64-bit mixer, range reduction and cell hashes, three times over: NumPy, Spark columns and DuckDB SQL.

All three give the same numbers. The Spark form never overflows, so it works with ANSI arithmetic on: products are
taken in limbs small enough for a long.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

MASK64 = (1 << 64) - 1
MASK32 = (1 << 32) - 1
#: Multipliers and shift of the mixer. Fixed values.
MULTIPLIERS = (0xFF51AFD7ED558CCD, 0xC4CEB9FE1A85EC53)
SHIFT = 33


def mix64(key: int, seed: int) -> int:
    """The mixer on Python integers; the result is unsigned."""
    h = (key + seed) & MASK64
    for m in MULTIPLIERS:
        h = ((h ^ (h >> SHIFT)) * m) & MASK64
    return h ^ (h >> SHIFT)


def derived_seed(seed, role):
    """Seeds of the several hash functions. As a seed enters by addition, nearby ones would give shifted copies; these are mixed.

    One of the two may be an array (uint64), which gives an array of the same seeds.
    """
    return _mix64_any(_mix64_any(role + 1, 0x9E3779B97F4A7C15), _mix64_any(seed & MASK64, 0))


def _mix64_any(key, seed):
    """Key and seed are added, so either may be the array."""
    if isinstance(key, np.ndarray):
        return mix64_np(key, seed)
    return mix64_np(seed, key) if isinstance(seed, np.ndarray) else mix64(key, seed)


def signed(value: int) -> int:
    return value - (1 << 64) if value >> 63 else value


# --- NumPy ------------------------------------------------------------------------------------------------------------


def mix64_np(keys: np.ndarray, seed: int | np.ndarray) -> np.ndarray:
    """``keys``: int64 or uint64; ``seed`` may be an array (uint64) that goes with them."""
    h = keys.view(np.uint64) + (seed if isinstance(seed, np.ndarray) else np.uint64(seed & MASK64))
    for m in MULTIPLIERS:
        h ^= h >> np.uint64(SHIFT)
        h *= np.uint64(m)
    h ^= h >> np.uint64(SHIFT)
    return h


def high32(h: np.ndarray) -> np.ndarray:
    return h >> np.uint64(32)


def low32(h: np.ndarray) -> np.ndarray:
    return h & np.uint64(MASK32)


def reduce_range_np(h32: np.ndarray, size: int) -> np.ndarray:
    """Numbers below 2**32 to [0, size) without division."""
    return ((h32 * np.uint64(size)) >> np.uint64(32)).astype(np.int64)


# --- Spark ------------------------------------------------------------------------------------------------------------


def _lit(value: int) -> Column:
    return F.lit(signed(value & MASK64)).cast("long")


def high32_col(h: Column) -> Column:
    return F.shiftrightunsigned(h, 32)


def low32_col(h: Column) -> Column:
    return h.bitwiseAND(_lit(MASK32))


def _add_seed(k: Column, seed: int) -> Column:
    seed &= MASK64
    low = low32_col(k) + F.lit(seed & MASK32)
    high = high32_col(k) + F.lit(seed >> 32) + F.shiftright(low, 32)
    return F.shiftleft(low32_col(high), 32).bitwiseOR(low32_col(low))


def _fold(h: Column) -> Column:
    return h.bitwiseXOR(F.shiftrightunsigned(h, SHIFT))


def _times(x: Column, m: int) -> Column:
    """Product modulo 2**64: two 32-bit limbs of x by four 16-bit limbs of m; all sums stay below 2**52."""
    m0, m1, m2, m3 = (F.lit((m >> s) & 0xFFFF).cast("long") for s in (0, 16, 32, 48))
    xl, xh = low32_col(x), high32_col(x)
    sixteen = lambda c: F.shiftleft(c.bitwiseAND(F.lit(0xFFFF).cast("long")), 16)
    p1 = xl * m1
    low = xl * m0 + F.shiftleft(low32_col(p1), 16)
    high = F.shiftright(low, 32) + F.shiftleft(F.shiftright(p1, 32), 16) + xl * m2 + sixteen(xl * m3) + xh * m0 + sixteen(xh * m1)
    return F.shiftleft(low32_col(high), 32).bitwiseOR(low32_col(low))


def with_mix64(df: DataFrame, key: str, seeds: dict[str, int]) -> DataFrame:
    """Adds one mixed column (a long holding the 64 bits) for each seed.

    Each step is a projection of its own, since steps use their input several times; all of them run in one stage of generated code.
    """
    out = df.withColumns({name: _add_seed(F.col(key), seed) for name, seed in seeds.items()})
    for m in MULTIPLIERS:
        out = out.withColumns({name: _fold(F.col(name)) for name in seeds})
        out = out.withColumns({name: _times(F.col(name), m) for name in seeds})
    return out.withColumns({name: _fold(F.col(name)) for name in seeds})


def reduce_range_col(h32: Column, size: Column | int) -> Column:
    """Safe while ``size`` is below 2**31."""
    size = F.lit(size).cast("long") if isinstance(size, int) else size.cast("long")
    return F.shiftrightunsigned(h32 * size, 32)


def reduce_mod_col(h: Column, size: int) -> Column:
    """The slower reduction, by remainder."""
    return F.pmod(h, F.lit(size).cast("long"))


def canonical_key(col: Column, kind: str, mode: str = "identity") -> Column:
    """Any value as a 64-bit key. ``kind`` is the Spark type's name; nulls stay null.

    Integers, dates, timestamps and booleans keep their identity. All else is hashed: by ``xxhash64`` or, when ``mode`` is
    ``md5``, by the leading 64 bits of its md5, which other engines have too.
    """
    kind = kind.lower()
    if mode != "md5" and kind in ("tinyint", "smallint", "int", "bigint", "byte", "short", "integer", "long", "boolean"):
        return (col.cast("int") if kind == "boolean" else col).cast("long")
    if kind == "date":
        return F.unix_date(col).cast("long")
    if kind.startswith("timestamp"):
        return F.unix_micros(F.convert_timezone(F.lit("UTC"), F.lit("UTC"), col).cast("timestamp") if kind == "timestamp_ntz" else col)
    if kind.startswith("decimal") and (p := [int(x) for x in kind[8:-1].split(",")]) and p[0] <= 18:
        return (col * F.lit(10 ** p[1])).cast("decimal(38,0)").cast("long")
    if kind in ("float", "double"):
        plain = F.when(F.isnan(col), F.lit(float("nan"))).otherwise(col + F.lit(0.0))
        return F.when(col.isNotNull(), F.xxhash64(plain.cast("double")))
    if kind.startswith("interval"):
        return F.when(col.isNotNull(), F.xxhash64(col.cast("string")))
    if kind.startswith("map"):
        return F.when(col.isNotNull(), F.xxhash64(F.array_sort(F.map_entries(col))))
    if mode == "md5":
        return md5_key(col.cast("binary") if kind in ("string", "binary") else col.cast("string").cast("binary"))
    return F.when(col.isNotNull(), F.xxhash64(col))


def md5_key(data: Column, half: int = 0) -> Column:
    """The leading (or, with ``half`` 1, the trailing) 64 bits of an md5."""
    digits = F.substring(F.md5(data), 1 + 16 * half, 16)
    word = lambda at: F.conv(F.substring(digits, at, 8), 16, 10).cast("long")
    return F.shiftleft(word(1), 32).bitwiseOR(word(9))


# --- DuckDB -----------------------------------------------------------------------------------------------------------

_M = f"{MASK64}::uhugeint"


def mix64_sql(key: str, seed: int) -> str:
    """An unsigned value of type uhugeint."""
    h = f"((({key})::hugeint & {MASK64}::hugeint)::uhugeint + {seed & MASK64}::uhugeint) & {_M}"
    for m in MULTIPLIERS:
        h = f"((xor(({h}), ({h}) >> {SHIFT}) * {m}::uhugeint) & {_M})"
    return f"xor({h}, {h} >> {SHIFT})"


def signed_sql(value: str) -> str:
    return f"(case when ({value}) >= {1 << 63}::uhugeint then (({value})::hugeint - {1 << 64}::hugeint)::bigint else ({value})::bigint end)"


def md5_key_sql(text: str) -> str:
    return f"(('0x' || substr(md5({text}), 1, 16))::ubigint)"


def reduce_sql(h32: str, size: int | str) -> str:
    return f"((({h32}) * ({size})::uhugeint) >> 32)::bigint"
