"""Linear hashing of 64-bit keys, in three engines that agree bit for bit: Columns, numpy, DuckDB SQL.

y = a x mod 2^64, then by modulus b: odd, y mod b; a power of two, the top bits of u; else even, y with its upper part
(from bit u / 2 on) folded in, mod b. u is the width of the keys: 64, or 2 q for q-grams. Keys are unsigned; Spark longs
carry their bit pattern.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

MASK = (1 << 64) - 1
LOW32 = 0xFFFFFFFF
PREMIX = 0xD6E8FEB86659FD93
#: Flipped before scrambling: key 0, which every linear hash leaves at 0, becomes a key like any other.
FLIP = 0x9E3779B97F4A7C15


def constant(seed: int, index: int) -> int:
    """Odd multiplier number ``index`` of a seed (the splitmix64 generator)."""
    x = (seed * 0x9E3779B97F4A7C15 + (index + 1) * 0xBF58476D1CE4E5B9) & MASK
    x = ((x ^ (x >> 30)) * 0xBF58476D1CE4E5B9) & MASK
    x = ((x ^ (x >> 27)) * 0x94D049BB133111EB) & MASK
    return (x ^ (x >> 31)) | 1


def is_power(b: int) -> bool:
    return b & (b - 1) == 0


# --- numpy -----------------------------------------------------------------------------------


def np_premix(x: np.ndarray) -> np.ndarray:
    y = (x ^ np.uint64(FLIP)) * np.uint64(PREMIX)
    return y ^ (y >> np.uint64(32))


def top_shift(b: int, u: int) -> int:
    """Bits below the top log2(b) ones of u."""
    return max(0, u - b.bit_length() + 1)


def np_hash(x: np.ndarray, a: int, b: int, u: int = 64) -> np.ndarray:
    if b == 1:
        return np.zeros(len(x), np.int64)
    y = x * np.uint64(a)
    if is_power(b):
        y >>= np.uint64(top_shift(b, u))
        if b << top_shift(b, u) <= MASK:  # bits above the key's width are left
            y &= np.uint64(b - 1)
        return y.view(np.int64)
    if b % 2 == 0:
        y ^= y >> np.uint64(u // 2)
    y %= np.uint64(b)
    return y.view(np.int64)


# --- Columns ---------------------------------------------------------------------------------


def mul64(x: Column, a: int) -> Column:
    """a x mod 2^64 without overflow: the constant in limbs of 16 bits, the key in halves of 32."""
    a0, a1, a2, a3 = (a >> s & 0xFFFF for s in (0, 16, 32, 48))
    low, high = x.bitwiseAND(F.lit(LOW32)), F.shiftrightunsigned(x, 32)
    p0, p1 = low * a0, low * a1
    foot = p0.bitwiseAND(F.lit(LOW32)) + F.shiftleft(p1.bitwiseAND(F.lit(0xFFFF)), 16)
    head = F.shiftright(p0, 32) + F.shiftright(p1, 16) + low * a2 + F.shiftleft((low * a3).bitwiseAND(F.lit(0xFFFF)), 16)
    head = head + high * a0 + F.shiftleft((high * a1).bitwiseAND(F.lit(0xFFFF)), 16) + F.shiftright(foot, 32)
    return F.shiftleft(head.bitwiseAND(F.lit(LOW32)), 32).bitwiseOR(foot.bitwiseAND(F.lit(LOW32)))


def unsigned_mod(y: Column, b: int) -> Column:
    return ((F.shiftrightunsigned(y, 1) % b) * 2 + y.bitwiseAND(F.lit(1))) % b


def reduce_to(y: Column, b: int, u: int = 64) -> Column:
    """y, an unsigned product already made, to 0..b-1."""
    if b == 1:
        return F.lit(0).cast("long")
    if is_power(b):
        return F.shiftrightunsigned(y, top_shift(b, u)).bitwiseAND(F.lit(b - 1).cast("long"))
    return unsigned_mod(y.bitwiseXOR(F.shiftrightunsigned(y, u // 2)) if b % 2 == 0 else y, b)


def premix(x: Column) -> Column:
    y = mul64(x.bitwiseXOR(F.lit(FLIP - (1 << 64))), PREMIX)
    return y.bitwiseXOR(F.shiftrightunsigned(y, 32))


# --- DuckDB SQL ------------------------------------------------------------------------------


def sql_mul(x: str, a: int) -> str:
    return f"CAST((CAST({x} AS UHUGEINT) * CAST('{a}' AS UHUGEINT)) % CAST('18446744073709551616' AS UHUGEINT) AS UBIGINT)"


def sql_premix(x: str) -> str:
    y = sql_mul(f"xor(CAST({x} AS UBIGINT), CAST({FLIP} AS UBIGINT))", PREMIX)
    return f"xor({y}, {y} >> 32)"


def sql_hash(x: str, a: int, b: int, u: int = 64) -> str:
    if b == 1:
        return "CAST(0 AS BIGINT)"
    y = sql_mul(x, a)
    if is_power(b):
        return f"CAST(({y} >> {top_shift(b, u)}) & CAST({b - 1} AS UBIGINT) AS BIGINT)"
    if b % 2 == 0:
        y = f"xor({y}, {y} >> {u // 2})"
    return f"CAST({y} % {b} AS BIGINT)"


def sql_reduce(y: str, b: str) -> str:
    """The same for a modulus that only the statement knows (an expression) and keys of 64 bits."""
    return f"""CAST(CASE WHEN {b} = 1 THEN 0 WHEN {b} & ({b} - 1) = 0 THEN {y} >> CAST(64 - log2({b}) AS INTEGER)
      WHEN {b} % 2 = 0 THEN xor({y}, {y} >> 32) % CAST({b} AS UBIGINT) ELSE {y} % CAST({b} AS UBIGINT) END AS BIGINT)"""
