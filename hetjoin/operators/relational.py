"""Small relational helpers around the round."""

from __future__ import annotations

from collections.abc import Mapping, Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.query import FullCQ


def reduce_dangling(relations: Mapping[str, DataFrame], cq: FullCQ) -> dict[str, DataFrame]:
    """Keeps tuples that match every atom that shares a variable: one semi-join for each, before the round."""
    out = dict(relations)
    for a in cq.atoms:
        for b in cq.atoms:
            if a is not b and (on := [x for x in a.vars if x in b.vars]):
                out[a.name] = out[a.name].join(relations[b.name].select(*on), on, "left_semi")
    return out


def missing(left: DataFrame, right: DataFrame, on: Sequence[str]) -> DataFrame:
    return left.join(right, list(on), "left_anti")


def asof(events: DataFrame, orders: DataFrame, key: str, ts: str, value: str) -> DataFrame:
    """Each event with ``value`` of the latest order of its key at or before its time, null if there is none."""
    both = events.select(*events.columns, F.lit(None).cast(orders.schema[value].dataType).alias(value), F.lit(1).alias("_side")).unionByName(orders.select(key, ts, value, F.lit(0).alias("_side")), allowMissingColumns=True)
    w = Window.partitionBy(key).orderBy(ts, "_side").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(value, F.last(value, ignorenulls=True).over(w)).where("_side = 1").drop("_side")


def same_bag(a: DataFrame, b: DataFrame) -> bool:
    b = b.select(*a.columns)
    return a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()
