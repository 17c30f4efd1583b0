"""Costs of machines: what it takes a machine to receive an amount of data."""

from __future__ import annotations

import math
from bisect import bisect_right
from collections.abc import Iterable, Mapping
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F


class CostFunction:
    """Increasing, zero at zero."""

    def __call__(self, amount: float) -> float:
        raise NotImplementedError

    def inverse(self, load: float, most: int | None = None) -> int:
        """The largest whole amount whose cost is at most ``load``, found by doubling and halving."""
        if load < 0:
            return 0
        high = 1
        while self(high) <= load and (most is None or high <= most):
            high *= 2
        low = 0
        while high - low > 1:
            mid = (low + high) // 2
            low, high = (mid, high) if self(mid) <= load else (low, mid)
        return low if most is None else min(low, most)

    def column(self, amount: Column) -> Column:
        raise NotImplementedError


@dataclass(frozen=True)
class Linear(CostFunction):
    w: float = 1.0

    def __call__(self, amount):
        return amount / self.w

    def inverse(self, load, most=None):
        got = max(0, math.floor(load * self.w * (1 + 1e-12)))
        return got if most is None else min(got, most)

    def column(self, amount):
        return amount / F.lit(float(self.w))


@dataclass(frozen=True)
class Power(CostFunction):
    w: float = 1.0
    a: float = 1.0

    def __call__(self, amount):
        return amount**self.a / self.w

    def inverse(self, load, most=None):
        got = max(0, math.floor((load * self.w) ** (1 / self.a) * (1 + 1e-12))) if load > 0 else 0
        return got if most is None else min(got, most)

    def column(self, amount):
        return F.pow(amount, F.lit(float(self.a))) / F.lit(float(self.w))


@dataclass(frozen=True)
class Tabulated(CostFunction):
    """Straight lines through (0, 0) and measured (amount, cost) points; the last slope goes on."""

    points: tuple[tuple[float, float], ...]

    def _line(self, amount):
        xs = [0.0, *(p[0] for p in self.points)]
        ys = [0.0, *(p[1] for p in self.points)]
        i = min(max(bisect_right(xs, amount), 1), len(xs) - 1)
        return xs[i - 1], ys[i - 1], (ys[i] - ys[i - 1]) / (xs[i] - xs[i - 1])

    def __call__(self, amount):
        x, y, slope = self._line(amount)
        return y + (amount - x) * slope

    def column(self, amount):
        starts = [0.0, *(p[0] for p in self.points[:-1])]
        lines = [self._line(x) for x in starts]
        out = None
        for i in reversed(range(len(starts))):
            x, y, slope = lines[i]
            piece = F.lit(y) + (amount - F.lit(x)) * F.lit(slope)
            out = piece if out is None else F.when(amount < F.lit(starts[i + 1]), piece).otherwise(out)
        return out


def from_rows(rows: Iterable[Mapping]) -> list[CostFunction]:
    """Machines given as rows (machine, kind, params), in order of ``machine``."""
    made = []
    for r in sorted(rows, key=lambda r: r["machine"]):
        p = dict(r["params"])
        if r["kind"] == "linear":
            made.append(Linear(p["w"]))
        elif r["kind"] == "power":
            made.append(Power(p["w"], p["a"]))
        elif r["kind"] == "table":
            made.append(Tabulated(tuple(sorted((float(k), v) for k, v in p.items()))))
        else:
            raise ValueError(f"unknown kind of cost: {r['kind']}")
    return made


def check_well_behaved(g: CostFunction, a: float, grid: Iterable[float], steps: Iterable[float] = (0.1, 0.5, 1.0, 3.0)) -> tuple[bool, str]:
    """Zero at zero, increasing, and growing by at most (1 + d)^a when the amount grows by 1 + d."""
    grid = sorted(grid)
    if g(0) != 0:
        return False, "not zero at zero"
    for x, y in zip(grid, grid[1:]):
        if g(y) <= g(x):
            return False, f"does not increase from {x} to {y}"
    for x in grid:
        for d in steps:
            if x > 0 and g(x * (1 + d)) > g(x) * (1 + d) ** a * (1 + 1e-9):
                return False, f"grows too fast at {x} by {d}"
    return True, ""


def as_column(costs: list[CostFunction], amount: Column, machine: Column) -> Column:
    """The cost of ``amount`` on ``machine``; machines of equal cost share one branch."""
    groups: dict[CostFunction, list[int]] = {}
    for i, c in enumerate(costs):
        groups.setdefault(c, []).append(i)
    out = F.lit(None).cast("double")
    for c, ids in groups.items():
        out = F.when(machine.isin(ids), c.column(amount)).otherwise(out)
    return out
