"""What one-round box plans are held against: share grids, pairwise joins, one machine."""

from __future__ import annotations

from collections.abc import Mapping, Sequence
from math import prod

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.coords import Coordinate
from ..plans import lp
from ..plans.query import FullCQ
from .execute import exchange, join_order, local_join


def shares(cq: FullCQ, m: Mapping[str, int], p: int, method: str = "enumerate") -> dict[str, int]:
    """Grid sides of at most p points in all. ``enumerate`` finds the grid of least load of a point;
    ``lp`` rounds p^(share) down, with the shares of a minimum vertex cover."""
    if method == "lp":
        cover = lp.min_vertex_cover(cq)
        total = sum(cover.values())
        return {x: max(1, int(p ** float(cover[x] / total) + 1e-9)) for x in cq.vars}
    return min(grids(cq.vars, p), key=lambda g: sum(m[a.name] / prod(g[x] for x in a.vars) for a in cq.atoms))


def grid_route(df: DataFrame, cq: FullCQ, atom: str, grid: Mapping[str, int], seed: int = 1, coordinates: Mapping[str, Coordinate] | None = None) -> DataFrame:
    """Every tuple to all grid points that agree with the hashes, or else the coordinates, of its variables."""
    own = cq.atom(atom).vars
    number, out = F.lit(0), df
    free = [x for x in cq.vars if x not in own and grid[x] > 1]
    for x in free:
        out = out.withColumn(f"_g_{x}", F.explode(F.sequence(F.lit(0), F.lit(grid[x] - 1))))

    def cell(x: str):
        if coordinates is None:
            return F.pmod(F.xxhash64(F.col(x), F.lit(f"{seed}:{x}")), F.lit(grid[x])).cast("int")
        return F.floor(coordinates[x].of(F.col(x), x) * F.lit(grid[x]) / F.lit(coordinates[x].size)).cast("int")

    for x in cq.vars:
        number = number * F.lit(grid[x]) + (cell(x) if x in own else F.col(f"_g_{x}") if x in free else F.lit(0))
    return out.withColumn("machine", number).drop(*[f"_g_{x}" for x in free])


def hypercube(cq: FullCQ, relations: Mapping[str, DataFrame], p: int, m: Mapping[str, int], grid: Mapping[str, int] | None = None, seed: int = 1) -> tuple[DataFrame, dict[str, DataFrame]]:
    """Answers and routed atoms on a share grid of at most p machines, weights ignored."""
    grid = grid or shares(cq, m, p)
    routed = {a.name: grid_route(relations[a.name], cq, a.name, grid, seed) for a in cq.atoms}
    return local_join({k: exchange(v, p) for k, v in routed.items()}, cq, m), routed


def grid_load(cq: FullCQ, m: Mapping[str, int], grid: Mapping[str, int], w: Sequence[float]) -> float:
    """Planned load of a grid on the machines of these weights, the slowest in use counting."""
    return sum(m[a.name] / prod(grid[x] for x in a.vars) for a in cq.atoms) / sorted(w, reverse=True)[prod(grid.values()) - 1]


def grids(vars: Sequence[str], most: int):
    """All grids of at most so many points."""
    if not vars:
        yield {}
        return
    for n in range(1, most + 1):
        for rest in grids(vars[1:], most // n):
            yield {vars[0]: n} | rest


def fastest_grid(cq: FullCQ, m: Mapping[str, int], w: Sequence[float]) -> tuple[dict[str, int], float]:
    """The best grid on the q fastest machines, over all q."""
    by_speed = sorted(w, reverse=True)
    load = lambda g: sum(m[a.name] / prod(g[x] for x in a.vars) for a in cq.atoms) / by_speed[prod(g.values()) - 1]
    grid = min(grids(cq.vars, len(w)), key=load)
    return grid, load(grid)


def hypercube_fastest(cq: FullCQ, relations: Mapping[str, DataFrame], w: Sequence[float], m: Mapping[str, int], seed: int = 1) -> tuple[DataFrame, dict[str, DataFrame]]:
    """The above, with grid point i on the i-th fastest machine."""
    grid, _ = fastest_grid(cq, m, w)
    by_speed = F.array(*[F.lit(c) for c in sorted(range(len(w)), key=lambda c: -w[c])])
    routed = {a.name: grid_route(relations[a.name], cq, a.name, grid, seed).withColumn("machine", F.element_at(by_speed, F.col("machine") + 1)) for a in cq.atoms}
    return local_join({k: exchange(v, len(w)) for k, v in routed.items()}, cq, m), routed


def virtual_hypercube(cq: FullCQ, relations: Mapping[str, DataFrame], w: Sequence[int], m: Mapping[str, int], seed: int = 1) -> tuple[DataFrame, dict[str, DataFrame]]:
    """A machine of weight w owns w grid points; tuples that meet in two of its points come twice."""
    owner = [c for c, n in enumerate(w) for _ in range(int(n))]
    grid = shares(cq, m, len(owner))
    owners = F.array(*[F.lit(c) for c in owner])
    points = {a.name: grid_route(relations[a.name], cq, a.name, grid, seed) for a in cq.atoms}
    answers = local_join({k: exchange(v, len(owner)) for k, v in points.items()}, cq, m)
    to_machine = F.element_at(owners, F.col("machine") + 1)
    return answers.withColumn("machine", to_machine), {k: v.withColumn("machine", to_machine) for k, v in points.items()}


def equi_join(left: DataFrame, right: DataFrame, on: Sequence[str], strategy: str | None = None) -> DataFrame:
    """Inner join; ``strategy`` is merge, shuffle_hash, broadcast or None (Spark decides)."""
    return left.join(right.hint(strategy) if strategy else right, list(on))


def pairwise(cq: FullCQ, relations: Mapping[str, DataFrame], m: Mapping[str, int], strategy: str | None = None) -> DataFrame:
    """One join after the other, a round each."""
    order = join_order(cq, m)
    out, known = relations[order[0]], set(cq.atom(order[0]).vars)
    for name in order[1:]:
        on = [x for x in cq.atom(name).vars if x in known]
        out = equi_join(out, relations[name], on, strategy) if on else out.crossJoin(relations[name])
        known |= set(cq.atom(name).vars)
    return out


def single_machine(cq: FullCQ, relations: Mapping[str, DataFrame], m: Mapping[str, int]) -> DataFrame:
    """Everything on one machine: no copies, all the load. A yardstick for small inputs only."""
    return local_join({a.name: exchange(relations[a.name].withColumn("machine", F.lit(0)), 1) for a in cq.atoms}, cq, m)


def single_machine_load(m: Mapping[str, int], costs) -> float:
    return min(g(sum(m.values())) for g in costs)
