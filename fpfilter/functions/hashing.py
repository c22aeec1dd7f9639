"""Linear hash functions on unsigned 64-bit keys: as Spark columns, numpy arrays, Python integers and DuckDB SQL.

A key is a signed long that carries 64 unsigned bits. Columns stay inside code generation and never overflow, so they
also work where arithmetic is checked: products are put together from limbs of 22 bits.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

MASK = (1 << 64) - 1
_LIMB = (1 << 22) - 1
#: The multipliers of the premixing bijection (a published 64-bit finaliser).
MIX_1, MIX_2 = 0xBF58476D1CE4E5B9, 0x94D049BB133111EB
ROLES = ("sub", "address", "fingerprint", "offset", "partner", "block", "tag", "extra")


def signed(x: int) -> int:
    return x - (1 << 64) if x >= 1 << 63 else x


def mix_int(x: int) -> int:
    x &= MASK
    x = (x ^ (x >> 30)) * MIX_1 & MASK
    x = (x ^ (x >> 27)) * MIX_2 & MASK
    return x ^ (x >> 31)


def _prime(n: int) -> bool:
    """Miller-Rabin with bases that decide all 64-bit numbers."""
    small = (2, 3, 5, 7, 11, 13, 17, 19, 23, 29, 31, 37)
    if any(n % p == 0 for p in small):
        return n in small
    d, r = n - 1, 0
    while d % 2 == 0:
        d, r = d // 2, r + 1
    for base in small:
        x = pow(base, d, n)
        if x in (1, n - 1):
            continue
        for _ in range(r - 1):
            x = x * x % n
            if x == n - 1:
                break
        else:
            return False
    return True


@lru_cache(4096)
def factor(seed: int, role: str) -> int:
    """A random 64-bit prime: a factor that has no divisor in common with any smaller table size."""
    state = mix_int(seed * 0x9E3779B97F4A7C15 + ROLES.index(role) + 1)
    a = state | 1 << 63 | 1
    while not _prime(a):
        a = (a + 2) & MASK | 1 << 63
    return a


def multiplier(seed: int, role: str, b: int) -> int:
    """The factor of a role for hashes into ``b`` values."""
    if not 0 < b < 1 << 63:
        raise ValueError(f"no hash into {b} values")
    return factor(seed, role)


# Python integers


def linear_int(x: int, a: int, b: int) -> int:
    p = (x & MASK) * a & MASK
    if b & (b - 1) == 0:
        return p >> (64 - b.bit_length() + 1) if b > 1 else 0
    return (p ^ (p >> 32) if b % 2 == 0 else p) % b


# numpy


def mix_np(x: np.ndarray) -> np.ndarray:
    x = x.astype(np.uint64)
    x = (x ^ (x >> np.uint64(30))) * np.uint64(MIX_1)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(MIX_2)
    return x ^ (x >> np.uint64(31))


def unmix_np(h: np.ndarray) -> np.ndarray:
    """The keys that :func:`mix_np` gives these values for."""
    x = h.astype(np.uint64)
    for shift, back in ((31, pow(MIX_2, -1, 1 << 64)), (27, pow(MIX_1, -1, 1 << 64))):
        x = (x ^ (x >> np.uint64(shift)) ^ (x >> np.uint64(2 * shift))) * np.uint64(back)
    return x ^ (x >> np.uint64(30)) ^ (x >> np.uint64(60))


def linear_np(x: np.ndarray, a: int, b: int | np.ndarray) -> np.ndarray:
    """Hashes of ``x`` into ``b`` values, as int64."""
    p = x.astype(np.uint64) * np.uint64(a)
    if b & (b - 1) == 0:
        return (p >> np.uint64(64 - b.bit_length() + 1)).astype(np.int64) if b > 1 else np.zeros(len(p), np.int64)
    if b % 2 == 0:
        p = p ^ (p >> np.uint64(32))
    return (p % np.uint64(b)).astype(np.int64)


# Spark columns


def _bits(col: Column, low: int, mask: int) -> Column:
    return (F.shiftrightunsigned(col, low) if low else col).bitwiseAND(F.lit(mask))


def product(col: Column, a: int) -> Column:
    """``col * a`` modulo 2^64."""
    x0, x1, x2 = _bits(col, 0, _LIMB), _bits(col, 22, _LIMB), _bits(col, 44, (1 << 20) - 1)
    a0, a1, a2 = a & _LIMB, a >> 22 & _LIMB, a >> 44
    low = x0 * a0
    middle = x0 * a1 + x1 * a0 + F.shiftright(low, 22)
    high = x0 * a2 + x1 * a1 + x2 * a0 + F.shiftright(middle, 22)
    word = low.bitwiseAND(F.lit(_LIMB)).bitwiseOR(F.shiftleft(middle.bitwiseAND(F.lit(_LIMB)), 22))
    return word.bitwiseOR(F.shiftleft(high.bitwiseAND(F.lit((1 << 20) - 1)), 44))


def unsigned_mod(col: Column, b: int) -> Column:
    """The unsigned value of ``col`` modulo ``b`` < 2^62: the half's remainder, doubled, plus the last bit."""
    return (F.shiftrightunsigned(col, 1) % b * 2 + col.bitwiseAND(F.lit(1))) % b


def with_premix(df: DataFrame, key: Column, to: str) -> DataFrame:
    """``df`` with ``to``: a bijection of ``key`` that spreads dense keys over all 64 bits.

    A column a step: a product names its operand ten times, and nested products would multiply. Steps stay separate
    projections, because the optimiser does not inline what is used more than once, and are compiled together.
    """
    a, b = f"{to}_a", f"{to}_b"
    df = df.withColumn(a, key.cast("long"))
    for shift, factor_ in ((30, MIX_1), (27, MIX_2)):
        df = df.withColumn(b, F.col(a).bitwiseXOR(F.shiftrightunsigned(F.col(a), shift))).withColumn(a, product(F.col(b), factor_))
    return df.withColumn(to, F.col(a).bitwiseXOR(F.shiftrightunsigned(F.col(a), 31))).drop(a, b)


def linear(col: Column, a: int, b: int) -> Column:
    """The hash of ``col``, a plain column, into ``b`` values. The form for this ``b`` is chosen here, not per row.

    A power of two takes the product's highest bits; another even number folds the high half onto the low one first,
    because low bits of a product depend on low bits of the key alone.
    """
    if b == 1:
        return F.lit(0).cast("long") + col * 0
    p = product(col, a)
    if b & (b - 1) == 0:
        return F.shiftrightunsigned(p, 64 - b.bit_length() + 1)
    return unsigned_mod(p.bitwiseXOR(F.shiftrightunsigned(p, 32)) if b % 2 == 0 else p, b)


# DuckDB SQL, for oracles


def unsigned_sql(x: str) -> str:
    return f"(CASE WHEN {x} < 0 THEN ({x}::HUGEINT + 18446744073709551616) ELSE {x}::HUGEINT END)::UBIGINT"


def product_sql(x: str, a: int) -> str:
    return f"(({x}::UHUGEINT * {a}::UHUGEINT) % 18446744073709551616::UHUGEINT)::UBIGINT"


def mix_steps_sql(source: str, key: str, to: str = "mixed") -> str:
    """CTEs that end with ``to``: all columns of ``source`` and ``h``, the premixed key."""
    return f"""
{to}_0 AS (SELECT *, {unsigned_sql(key)} AS h0 FROM {source}),
{to}_1 AS (SELECT * EXCLUDE (h0), {product_sql('xor(h0, h0 >> 30)', MIX_1)} AS h1 FROM {to}_0),
{to}_2 AS (SELECT * EXCLUDE (h1), {product_sql('xor(h1, h1 >> 27)', MIX_2)} AS h2 FROM {to}_1),
{to} AS MATERIALIZED (SELECT * EXCLUDE (h2), xor(h2, h2 >> 31) AS h FROM {to}_2)"""


def linear_sql(x: str, a: int, b: int | str) -> str:
    """Hash into ``b`` values; ``b`` may be an expression, for tables whose size depends on the data."""
    return reduced_sql(product_sql(x, a), b)


def reduced_sql(p: str, b: int | str) -> str:
    """The hash into ``b`` values of a key whose product with the factor is ``p``."""
    if isinstance(b, str):
        power = f"({p} >> (64 - length(bin({b})) + 1)::UBIGINT)"
        folded = f"(xor({p}, {p} >> 32) % {b}::UBIGINT)"
        return f"(CASE WHEN {b} = 1 THEN 0 WHEN {b} & ({b} - 1) = 0 THEN {power} WHEN {b} % 2 = 0 THEN {folded} ELSE {p} % {b}::UBIGINT END)::BIGINT"
    if b == 1:
        return "0::BIGINT"
    if b & (b - 1) == 0:
        return f"({p} >> {64 - b.bit_length() + 1})::BIGINT"
    return f"((xor({p}, {p} >> 32)) % {b}::UBIGINT)::BIGINT" if b % 2 == 0 else f"({p} % {b}::UBIGINT)::BIGINT"
