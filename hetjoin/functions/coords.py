"""Coordinates: where a key lies on a variable's range."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

PRIME = (1 << 31) - 1


@dataclass(frozen=True)
class Coordinate:
    """``size`` values from 0; ``of`` makes the column for a variable's key."""

    size: int
    of: Callable[[Column, str], Column]


def identity(low: int, size: int) -> Coordinate:
    """For dense keys: the key itself, from its least value."""
    return Coordinate(size, lambda key, var: key.cast("long") - F.lit(low))


def md5(seed: int, bits: int = 20) -> Coordinate:
    """The first hex digits of a digest; SQL engines agree on it. At most 32 bits."""

    def of(key, var):
        digest = F.md5(F.concat(F.lit(f"{seed}:{var}:"), key.cast("string")).cast("binary"))
        return F.shiftrightunsigned(F.conv(F.substring(digest, 1, 8), 16, 10).cast("long"), 32 - bits)

    return Coordinate(1 << bits, of)


def affine(seed: int, bits: int = 20) -> Coordinate:
    """A line modulo a prime; cheap, but keys that are lines themselves stay lines."""
    a = 1_000_000_007 + 2 * 48271 * (seed + 1)

    def of(key, var):
        b = sum(map(ord, var)) * 7919 + seed
        return F.pmod(F.pmod(key.cast("long"), F.lit(PRIME)) * F.lit(a % PRIME) + F.lit(b), F.lit(PRIME)).bitwiseAND(F.lit((1 << bits) - 1))

    return Coordinate(1 << bits, of)


def xx(seed: int, bits: int = 20) -> Coordinate:
    """64-bit hash, independent for each variable; keys of any type."""
    return Coordinate(1 << bits, lambda key, var: F.shiftrightunsigned(F.xxhash64(key, F.lit(f"{seed}:{var}")), 64 - bits))


def day(ts: Column) -> Column:
    return F.date_trunc("day", ts)


def json_key(props: Column, key: str) -> Column:
    return F.get_json_object(props, f"$.{key}")


def text(value: Column) -> Column:
    return F.lower(F.trim(value))
