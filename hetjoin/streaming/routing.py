"""Routing is row by row, so an unbounded input can be routed as it comes."""

from __future__ import annotations

from collections.abc import Callable, Mapping, Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.coords import Coordinate
from ..operators.execute import evaluate
from ..operators.route import route
from ..plans.pack import Packing
from ..plans.query import Atom, FullCQ


def route_stream(events: DataFrame, atom: Atom, packing: Packing, coordinates: Mapping[str, Coordinate]) -> DataFrame:
    """Stateless; works in append mode."""
    return route(events, atom, packing, coordinates, strategy="literal")


def join_static(events: DataFrame, name: str, cq: FullCQ, static: Mapping[str, DataFrame], costs, sink: Callable[[DataFrame, int], None], **options):
    """Every micro-batch is one round against the static atoms; returns the stream writer."""

    def one(batch: DataFrame, number: int) -> None:
        sink(evaluate(cq, {**static, name: batch}, costs, **options).answers, number)

    return events.writeStream.foreachBatch(one)


def join_streams(left: DataFrame, right: DataFrame, on: Sequence[str], ts: tuple[str, str], within: str, late: str = "1 hour") -> DataFrame:
    """Two routed streams, joined inside each machine: rows of equal ``on`` whose times lie at most ``within`` apart.

    Both have ``machine``. Rows later than the watermark are dropped; state older than both is, too.
    """
    a, b = left.withWatermark(ts[0], late).alias("a"), right.withWatermark(ts[1], late).alias("b")
    near = F.expr(f"b.{ts[1]} >= a.{ts[0]} - INTERVAL {within} AND b.{ts[1]} <= a.{ts[0]} + INTERVAL {within}")
    same = near
    for c in ("machine", *on):
        same = same & (F.col(f"a.{c}") == F.col(f"b.{c}"))
    kept = [F.col(f"b.{c}") for c in right.columns if c not in ("machine", *on)]
    return a.join(b, same).select("a.*", *kept)


def load_windows(routed: DataFrame, ts: str, size: str, slide: str | None = None, gap: str | None = None, late: str = "1 hour") -> DataFrame:
    """Tuples by machine and time: tumbling, sliding (``slide``) or session (``gap``) windows; rows later than the watermark are dropped."""
    window = F.session_window(ts, gap) if gap else F.window(ts, size, slide) if slide else F.window(ts, size)
    return routed.withWatermark(ts, late).groupBy(window.alias("window"), "machine").agg(F.count("*").alias("tuples"))
