"""Integer hashing: a portable 32-bit base hash, a fast one, and cheap remixing by seed."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

WIDTH = 1 << 32


def base32(token: Column) -> Column:
    """First 32 bits of md5 as a bigint; equal in other engines, so results can be checked there."""
    return F.conv(F.substring(F.md5(token.cast("binary")), 1, 8), 16, 10).cast("bigint")


def base64bits(token: Column) -> Column:
    """First 64 bits of md5 as a signed bigint; its upper half is base32()."""
    return F.conv(F.substring(F.md5(token.cast("binary")), 1, 16), 16, -10).cast("bigint")


def coefficients(seed: int) -> tuple[int, int]:
    """Odd multiplier and offset under 2^31 for a seed."""
    return ((seed * 40_503 + 1_013_904_223) * 69_069 % (1 << 30)) * 2 + 1, (seed * 1_664_525 + 907_633_385) * 22_695_477 % (1 << 31)


def mix(h: Column, seed: int | Column) -> Column:
    """h remixed to [0, 2^32) for a seed; a product of 32 and 31 bits stays inside a bigint."""
    if isinstance(seed, int):
        a, b = coefficients(seed)
        return (h * F.lit(a) + F.lit(b)) % F.lit(WIDTH)
    s = seed.cast("bigint")
    a = ((s * 40_503 + 1_013_904_223) * 69_069 % (1 << 30)) * 2 + 1
    b = (s * 1_664_525 + 907_633_385) * 22_695_477 % (1 << 31)
    return (h * a + b) % F.lit(WIDTH)


def mix_sql(h: str, seed: str) -> str:
    """The same as text for another engine."""
    return f"(({h}) * ((((({seed})::BIGINT) * 40503 + 1013904223) * 69069 % 1073741824) * 2 + 1) + ((({seed})::BIGINT) * 1664525 + 907633385) * 22695477 % 2147483648) % 4294967296"


def unit(h: Column, seed: int = 0) -> Column:
    """A uniform number in [0, 1) that belongs to h and the seed."""
    return mix(h, seed) / F.lit(float(WIDTH))
