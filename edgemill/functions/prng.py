"""Counter-based draws: a value depends on its arguments alone, never on partitions or attempts."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def sort_key(seed: int, purpose: str, key: Column, backend: str = "fast") -> Column:
    """A key to shuffle by: md5 text (portable, also computable in other SQL engines) or a 64-bit hash (fast)."""
    if backend == "portable":
        return F.md5(F.concat_ws(":", F.lit(str(seed)), F.lit(purpose), key.cast("string")))
    return F.xxhash64(F.lit(seed), F.lit(purpose), key)


def key_bucket(key: Column, bits: int, backend: str = "fast") -> Column:
    """The high bits of a sort key, in the key's order; even without sampling, as keys are uniform."""
    if backend == "portable":
        digits = -(-bits // 4)
        return F.shiftright(F.conv(F.substring(key, 1, digits), 16, 10).cast("long"), 4 * digits - bits)
    return F.shiftright(key, 64 - bits) + F.lit(1 << (bits - 1))


def block_hash(seed: int, purpose: str, key: Column, block: int, backend: str = "fast") -> Column:
    """The source of several draws: 8 of 16 bits (portable) or 2 of 32 bits (fast)."""
    if backend == "portable":
        return F.md5(F.concat_ws(":", F.lit(str(seed)), F.lit(purpose), key.cast("string"), F.lit(str(block))))
    return F.xxhash64(F.lit(seed), F.lit(purpose), key, F.lit(block))


def draws_per_block(backend: str) -> int:
    return 8 if backend == "portable" else 2


def draw_bits(backend: str) -> int:
    return 16 if backend == "portable" else 32


def draw(hashed: Column, nth: int, backend: str = "fast") -> Column:
    """The nth draw of a block hash, uniform below 2^draw_bits."""
    if backend == "portable":
        return F.conv(F.substring(hashed, 4 * nth + 1, 4), 16, 10).cast("long")
    return F.shiftrightunsigned(hashed, 32) if nth == 0 else hashed.bitwiseAND(0xFFFFFFFF)


def hash_constants(key: int, rounds: int) -> list[tuple[int, int]]:
    """Odd multiplier and addend of each round, from a 64-bit mix of the key."""
    out, x = [], key & (2**64 - 1)
    for _ in range(rounds):
        x = (x * 6364136223846793005 + 1442695040888963407) % 2**64
        out.append((((x >> 33) | 1) % 2**30, (x >> 12) % 2**30))
    return out


def bijective_hash(v: Column, bits: int, key: int = 7, rounds: int = 4) -> Column:
    """A bijection on [0, 2^bits), bits at most 38: odd multiples modulo 2^bits alternate with xor of the upper half.

    Multipliers are taken modulo 2^min(bits, 24), so products stay below 2^62 at any allowed size.
    """
    if bits == 0:
        return v * 0
    mask, low, half = (1 << bits) - 1, (1 << min(bits, 24)) - 1, (bits + 1) // 2
    for a, c in hash_constants(key, rounds):
        v = (v * F.lit((a & low) | 1) + F.lit(c & mask)).bitwiseAND(F.lit(mask))
        v = v.bitwiseXOR(F.shiftright(v, half))
    return v


def mixing_steps(n: int, key: int, rounds: int) -> list[tuple[int, int, int]]:
    """(multiplier without a common factor with n, addend, odd multiplier of the upper half) of each round; products stay below 2^62 for n up to 2^38."""
    out = []
    for a, c in hash_constants(key, rounds):
        factor = a % min(n, 1 << 24) | 1
        while math.gcd(factor, n) != 1:
            factor += 2
        out.append((factor, c % n, a % (1 << 24) | 1))
    return out


def mixed_columns(df: DataFrame, columns: list[str], n: int, key: int = 7, rounds: int = 4) -> DataFrame:
    """df with columns of [0, n) put through a bijection on [0, n), any n up to 2^38.

    Where n is a power of two it is bijective_hash. Else a round is an affine map modulo n and an exchange of pairs:
    x and x xor (upper half of x, multiplied, cut to the lower half), where both are below n. Each half-round is a
    projection of its own: the planner does not merge one that is used more than once, so what makes the columns is
    computed once and the code stays short.
    """
    bits = max(0, (n - 1).bit_length())
    if n < 2:
        return df
    whole = lambda made: df.select(*(made(F.col(c)).alias(c) if c in columns else F.col(c) for c in df.columns))
    if n == 1 << bits:
        mask, low, half = n - 1, (1 << min(bits, 24)) - 1, (bits + 1) // 2
        for a, k in hash_constants(key, rounds):
            df = whole(lambda v: (v * F.lit((a & low) | 1) + F.lit(k & mask)).bitwiseAND(F.lit(mask)))
            df = whole(lambda v: v.bitwiseXOR(F.shiftright(v, half)))
        return df
    half = bits // 2
    size, low = F.lit(n).cast("long"), F.lit((1 << half) - 1).cast("long")
    for factor, addend, odd in mixing_steps(n, key, rounds):
        df = whole(lambda v: F.pmod(v * F.lit(factor).cast("long") + F.lit(addend).cast("long"), size))
        other = lambda v: v.bitwiseXOR((F.shiftright(v, half) * F.lit(odd).cast("long")).bitwiseAND(low))
        df = whole(lambda v: F.when(other(v) < size, other(v)).otherwise(v))
    return df
