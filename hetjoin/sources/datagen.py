"""Matching and dense relations out of contiguous keys."""

from __future__ import annotations

from math import gcd

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Multipliers of the fixtures.
A, B, D = (7919, 11), (104729, 17), (1299709, 5)


def line(key: Column, rule: tuple[int, int], n: int) -> Column:
    """A permutation of 0..n-1, for multipliers without a divisor in common with n."""
    if gcd(rule[0], n) != 1:
        raise ValueError(f"{rule[0]} is no permutation modulo {n}")
    return F.pmod(key * F.lit(rule[0]) + F.lit(rule[1]), F.lit(n))


def matching(keys: DataFrame, key: str, n: int, columns: dict[str, tuple[int, int] | None]) -> DataFrame:
    """Columns that are the key itself (None) or a permutation of it: every value once."""
    return keys.select(*[(F.col(key) if rule is None else line(F.col(key), rule, n)).alias(c) for c, rule in columns.items()])


def dense(left: DataFrame, right: DataFrame, a: str, b: str, rule: tuple[int, int, int], theta: float) -> DataFrame:
    """The pairs of two small key sets that a fixed rule keeps, about a part theta of all."""
    kept = F.pmod(F.col(a) * rule[0] + F.col(b) * rule[1] + rule[2], F.lit(100)) < F.lit(round(100 * theta))
    return left.crossJoin(right).where(kept)


def triangles(keys: DataFrame, key: str, n: int, part: int | None = None) -> dict[str, DataFrame]:
    """Three matchings R(x,y), S(y,z), T(z,x) with a triangle planted for every even key of S and T."""
    k, part = F.col(key), part or n
    turned = F.when(k % 2 == 0, k).otherwise(F.pmod(k + 2, F.lit(part)))
    few = keys.where(k < part)
    return {
        "R": keys.select(k.alias("x"), line(k, A, n).alias("y")),
        "S": few.select(line(k, A, n).alias("y"), line(turned, B, n).alias("z")),
        "T": few.select(line(k, B, n).alias("z"), k.alias("x")),
    }
