"""Routing: every tuple to all machines whose box, seen on the tuple's variables, has its coordinates."""

from __future__ import annotations

from bisect import bisect_right
from collections.abc import Mapping
from itertools import product
from math import prod

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.coords import Coordinate
from ..plans.pack import Packing
from ..plans.query import Atom

LITERAL_CELLS = 4096
LOOKUP_ROWS = 1_000_000


def boxes_frame(spark, packing: Packing) -> DataFrame:
    """machine, dim, lo, hi (half open), a row for each used machine and variable."""
    rows = [(c, x, *packing.boxes[c][x]) for c in packing.used() for x in packing.vars]
    return spark.createDataFrame(rows, "machine int, dim string, lo long, hi long")


def _cuts(packing: Packing, var: str) -> list[int]:
    return sorted({packing.boxes[c][var][0] for c in packing.used()})


def _cell(coordinate: Column, cuts: list[int], at: int = 0) -> Column:
    """Number of the range that a coordinate lies in, by halving."""
    if len(cuts) == 1:
        return F.lit(at)
    mid = len(cuts) // 2
    return F.when(coordinate < F.lit(cuts[mid]), _cell(coordinate, cuts[:mid], at)).otherwise(_cell(coordinate, cuts[mid:], at + mid))


def literal(atom: Atom, packing: Packing, coordinate: Mapping[str, Column]) -> Column:
    """A table from cells to machines, as a constant in the plan."""
    cuts = [_cuts(packing, x) for x in atom.vars]
    table = []
    cells: dict[tuple[int, ...], list[int]] = {}
    for c in packing.used():
        ranges = []
        for x, own in zip(atom.vars, cuts):
            lo, hi = packing.boxes[c][x]
            ranges.append(range(bisect_right(own, lo) - 1, bisect_right(own, hi - 1)))
        for cell in product(*ranges):
            cells.setdefault(cell, []).append(c)
    for cell in product(*[range(len(x)) for x in cuts]):
        table.append(F.array(*[F.lit(c) for c in cells.get(cell, [])]).cast("array<int>"))
    index = F.lit(0)
    for x, own in zip(atom.vars, cuts):
        index = index * F.lit(len(own)) + _cell(coordinate[x], own)
    return F.element_at(F.array(*table), index + 1)


def tree(atom: Atom, packing: Packing, coordinate: Mapping[str, Column]) -> Column:
    """Follows the merge tree; where it splits a variable that the atom lacks, both ways."""

    def low(node, x):
        while node.machine < 0:
            node = node.left
        return packing.boxes[node.machine][x][0]

    def walk(node):
        if node.machine >= 0:
            empty = any(hi <= lo for lo, hi in packing.boxes[node.machine].values())
            return F.array().cast("array<int>") if empty else F.array(F.lit(node.machine))
        x = packing.vars[node.dim]
        if x not in atom.vars:
            return F.concat(walk(node.left), walk(node.right))
        return F.when(coordinate[x] < F.lit(low(node.right, x)), walk(node.left)).otherwise(walk(node.right))

    if packing.root is None:
        raise ValueError("this packing has no tree")
    return walk(packing.root)


def box_join(df: DataFrame, boxes: DataFrame, atom: Atom) -> DataFrame:
    """Interval join with all boxes (broadcast: one row for each machine); the reference way."""
    on = F.lit(True)
    for x in atom.vars:
        on = on & (F.col(f"_c_{x}") >= F.col(f"_lo_{x}")) & (F.col(f"_c_{x}") < F.col(f"_hi_{x}"))
    return df.join(F.broadcast(boxes), on)


def _wide(spark, packing: Packing, atom: Atom) -> DataFrame:
    rows = [(c, *[v for x in atom.vars for v in packing.boxes[c][x]]) for c in packing.used()]
    return spark.createDataFrame(rows, "machine int, " + ", ".join(f"_lo_{x} long, _hi_{x} long" for x in atom.vars))


def route(df: DataFrame, atom: Atom, packing: Packing, coordinates: Mapping[str, Coordinate], strategy: str = "auto", coarse: int = 16) -> DataFrame:
    """``df`` with a column ``machine``, one row for each machine that is to get the tuple.

    ``literal`` and ``tree`` are Column expressions; ``cells`` looks machines up by a coarse
    cell; ``nested`` tests all boxes. ``auto`` takes literal while its table is small.
    """
    own = {x: coordinates[x].of(F.col(x), x) for x in atom.vars}
    cells = 1
    for x in atom.vars:
        cells *= len(_cuts(packing, x))
    if strategy == "auto":
        strategy = "literal" if cells <= LITERAL_CELLS and len(packing.used()) <= 256 else "tree" if packing.root is not None and len(packing.used()) <= 512 else "cells"
    if strategy in ("literal", "tree"):
        placed = df.select("*", *[c.alias(f"_c_{x}") for x, c in own.items()])
        maker = literal if strategy == "literal" else tree
        return placed.select(*df.columns, F.explode(maker(atom, packing, {x: F.col(f"_c_{x}") for x in own})).alias("machine"))
    placed = df.select("*", *[c.alias(f"_c_{x}") for x, c in own.items()])
    if strategy == "nested":
        return box_join(placed, _wide(df.sparkSession, packing, atom), atom).select(*df.columns, "machine")
    # A wide grid of coarse cells finds machines faster, but its table must stay small enough to be broadcast.
    while True:
        step = {x: max(1, -(-packing.domain[x] // coarse)) for x in atom.vars}
        ranges = {c: [range(packing.boxes[c][x][0] // step[x], (packing.boxes[c][x][1] - 1) // step[x] + 1) for x in atom.vars] for c in packing.used()}
        if coarse == 1 or sum(prod(map(len, r)) for r in ranges.values()) <= LOOKUP_ROWS:
            break
        coarse //= 2
    rows = []
    for c, own_cells in ranges.items():
        for cell in product(*own_cells):
            number = 0
            for k in cell:
                number = number * coarse + k
            rows.append((number, c, *[v for x in atom.vars for v in packing.boxes[c][x]]))
    table = df.sparkSession.createDataFrame(rows, "_cell long, machine int, " + ", ".join(f"_lo_{x} long, _hi_{x} long" for x in atom.vars))
    number = F.lit(0).cast("long")
    for x in atom.vars:
        number = number * F.lit(coarse) + F.floor(F.col(f"_c_{x}") / F.lit(step[x])).cast("long")
    inside = F.lit(True)
    for x in atom.vars:
        inside = inside & (F.col(f"_c_{x}") >= F.col(f"_lo_{x}")) & (F.col(f"_c_{x}") < F.col(f"_hi_{x}"))
    # At most a row for each machine and coarse cell, and LOOKUP_ROWS or one for each machine, whatever the data.
    return placed.withColumn("_cell", number).join(F.broadcast(table), "_cell").where(inside).select(*df.columns, "machine")
