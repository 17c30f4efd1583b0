"""What kind of input this is: matching, dense, or neither."""

from __future__ import annotations

from collections.abc import Mapping, Sequence
from dataclasses import dataclass
from functools import reduce
from math import prod

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import coords
from ..plans.query import FullCQ

DENSE = 0.1


def degrees(df: DataFrame, attribute: str) -> DataFrame:
    """rows, distinct, max_degree, lo, hi of one attribute: one partial-and-final aggregate by value."""
    by = df.groupBy(attribute).agg(F.count("*").alias("_n"))
    return by.agg(F.sum("_n").alias("rows"), F.count("*").alias("distinct"), F.max("_n").alias("max_degree"), F.min(attribute).alias("lo"), F.max(attribute).alias("hi"))


def profile(df: DataFrame, name: str, attributes: Sequence[str]) -> DataFrame:
    """A row for each attribute: atom, attribute, rows, distinct, max_degree, lo, hi."""
    return reduce(DataFrame.unionAll, [degrees(df, a).select(F.lit(name).alias("atom"), F.lit(a).alias("attribute"), "*") for a in attributes])


def distinct(df: DataFrame, attribute: str, exact: bool = True, rsd: float = 0.02) -> DataFrame:
    return df.agg((F.countDistinct(attribute) if exact else F.approx_count_distinct(attribute, rsd)).alias("distinct"))


def density(df: DataFrame, sizes: Sequence[int]) -> DataFrame:
    """Rows over all possible rows."""
    space = reduce(lambda a, b: a * b, sizes, 1)
    return df.agg(F.count("*").alias("rows")).withColumn("density", F.col("rows") / F.lit(float(space)))


def is_matching(profiled: DataFrame) -> bool:
    """No attribute has a value twice."""
    return profiled.where("max_degree > 1").isEmpty()


def quantiles(df: DataFrame, attribute: str, at: Sequence[float] = (0.5, 0.9, 0.99), accuracy: int = 10_000) -> DataFrame:
    """Approximate quantiles of the degrees of an attribute's values, by mergeable summaries."""
    return df.groupBy(attribute).agg(F.count("*").alias("_n")).agg(F.percentile_approx("_n", list(at), accuracy).alias("degrees"))


@dataclass(frozen=True)
class Class:
    """``kind``: matching (no value twice, a unary one with at most half of its domain), dense (at least ``DENSE`` of all tuples) or other."""

    kind: str
    rows: int
    max_degree: int
    density: float
    ranges: dict


def classify(cq: FullCQ, relations: Mapping[str, DataFrame]) -> dict[str, Class]:
    """The class of every atom, from one profile row for each of its variables; keys that are no integers have no density."""
    out = {}
    for a in cq.atoms:
        df = relations[a.name]
        whole = all(isinstance(df.schema[x].dataType, T.IntegralType) for x in a.vars)
        rows = {x: degrees(df, x).first() for x in a.vars}
        n = next(iter(rows.values()))["rows"] or 0
        degree = max(r["max_degree"] or 0 for r in rows.values())
        ranges = {x: (r["lo"], r["hi"] - r["lo"] + 1) for x, r in rows.items()} if whole and n else {}
        density = n / prod(size for _, size in ranges.values()) if ranges else 0.0
        sparse = len(a.vars) > 1 or density <= 0.5
        out[a.name] = Class("matching" if n and degree == 1 and sparse else "dense" if density >= DENSE else "other", n, degree, density, ranges)
    return out


def dense_coordinates(cq: FullCQ, classes: Mapping[str, Class]) -> dict[str, coords.Coordinate]:
    """Variables of dense atoms only are their own coordinates, from the least key of any atom."""
    out = {}
    for x in cq.vars:
        own = [classes[a.name] for a in cq.having(x)]
        if all(c.kind == "dense" for c in own):
            low = min(c.ranges[x][0] for c in own)
            out[x] = coords.identity(low, max(sum(c.ranges[x]) for c in own) - low)
    return out
