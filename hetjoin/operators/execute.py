"""The round: route all atoms, exchange each once, join locally in every partition."""

from __future__ import annotations

from collections.abc import Mapping, Sequence
from dataclasses import dataclass, field
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import coords, profile
from ..functions.coords import Coordinate
from ..functions.measure import ratio
from ..plans import bounds, lp, pack, sides
from ..plans.cost import CostFunction, Linear
from ..plans.pack import Packing
from ..plans.query import FullCQ, parse_cq
from .route import boxes_frame, route


@dataclass
class Plan:
    cq: FullCQ
    sizes: dict[str, int]
    costs: list[CostFunction]
    mode: str
    bound: float
    packing: Packing
    coordinates: dict[str, Coordinate]
    notes: dict[str, str] = field(default_factory=dict)

    def report(self, spark) -> DataFrame:
        """key, value: bound, planned load and its ratio to the bound, replication, machines used, figures of the packing."""
        p = self.packing
        rows = {"bound": self.bound, "planned_load": p.planned_load(self.cq, self.sizes, self.costs), "replication": p.replication(self.cq, self.sizes)}
        rows["ratio"] = ratio(rows["planned_load"], self.bound)
        rows |= {k: float(v) for k, v in p.stats().items()} | {f"cover_{x}": float(v) for x, v in lp.min_vertex_cover(self.cq).items()} | {f"size_{a}": float(n) for a, n in self.sizes.items()}
        return spark.createDataFrame([(k, float(v)) for k, v in rows.items()], "key string, value double")

    def boxes(self, spark) -> DataFrame:
        return boxes_frame(spark, self.packing)


def plan(cq: FullCQ, sizes: Mapping[str, int], costs: Sequence[CostFunction], mode: str = "auto", rounding: str = "search", coordinates: Mapping[str, Coordinate] | None = None, seed: int = 1, grid_bits: int = pack.GRID_BITS, cover=None) -> Plan:
    """Bound, sides and boxes. ``mode`` is auto, uniform, general, cartesian, join, star, triangle, padded or dual."""
    costs = list(costs)
    sizes = {k: max(1, int(v)) for k, v in sizes.items()}
    w = [getattr(c, "w", 1.0) for c in costs]
    linear = all(isinstance(c, Linear) for c in costs)
    largest = max(sizes.values())
    if mode == "auto":
        shape = sides.dispatch(cq)
        mode = "general" if not linear else "uniform" if len(set(sizes.values())) == 1 else shape if shape != "other" else "dual"
    coordinates = dict(coordinates or {x: coords.xx(seed, grid_bits) for x in cq.vars})
    notes = {}
    u = float(sum(lp.max_edge_packing(cq).values()))
    even = len(set(sizes.values())) == 1
    if mode == "general":
        made = sides.general(cq, costs, largest)
        # Where sizes differ, relations cut down to the least size still have to be joined.
        bound = bounds.lower_general(min(sizes.values()), costs, u)
        if not even:
            notes["bound"] = "of relations of the least size"
    elif mode in ("uniform", "padded"):
        bound = bounds.lower_uniform(largest, w, u) if even else bounds.lower_mixed(cq, sizes, w)[0]
        made = sides.uniform(cq, w, cover)
    else:
        bound = bounds.lower_mixed(cq, sizes, w)[0]
        if mode == "dual":
            made, notes["dual"] = sides.dual(cq, sizes, w, bound)
        else:
            made = {"cartesian": sides.cartesian, "join": sides.binary_join, "star": sides.star, "triangle": sides.triangle}[mode](cq, sizes, w, bound)
    if not linear and mode != "general":
        notes["bound"] = "of linear costs of the same weights"
    domain = {x: coordinates[x].size for x in cq.vars}
    split = [x for x in cq.vars if any(s[x] < 1 for s in made)]
    if rounding == "search" and len(split) <= 1:
        packing = pack.intervals(cq, made, domain)
    else:
        packing = pack.pack(cq, made, domain, rounding=rounding, grid_bits=max(grid_bits, max(domain.values()).bit_length()), m=sizes, w=costs)
        if rounding == "search":
            packing = pack.refine(packing, cq, sizes, costs)
    return Plan(cq, sizes, costs, mode, bound, packing, coordinates, notes)


def exchange(df: DataFrame, machines: int) -> DataFrame:
    """Machine c's rows become partition c: the id is the partition, no hash in between."""
    return df.repartitionById(machines, F.col("machine"))


def join_order(cq: FullCQ, sizes: Mapping[str, int]) -> list[str]:
    """Smallest atom first, then always one that shares a variable, if there is one."""
    left, out, known = {a.name: set(a.vars) for a in cq.atoms}, [], set()
    while left:
        pool = [a for a in left if left[a] & known] or list(left)
        best = min(pool, key=lambda a: (sizes[a], a))
        out.append(best)
        known |= left.pop(best)
    return out


def local_join(parts: Mapping[str, DataFrame], cq: FullCQ, sizes: Mapping[str, int], hint: str = "merge") -> DataFrame:
    """Left-deep joins by name on ``machine`` and the shared variables, so that no exchange is added.

    The hint keeps Spark from broadcasting a side, which would bypass the load account.
    """
    order = join_order(cq, sizes)
    out, known = parts[order[0]], set(cq.atom(order[0]).vars)
    for name in order[1:]:
        own = cq.atom(name).vars
        out = out.join(parts[name].hint(hint), ["machine", *[x for x in own if x in known]])
        known |= set(own)
    return out


@dataclass(frozen=True)
class Totals:
    """An aggregate of the answers: ``n`` of them and the ``total`` of the variable ``over``, by ``by``, an SQL expression of the variable ``of``."""

    name: str
    by: str
    of: str
    over: str


def local_totals(parts: Mapping[str, DataFrame], cq: FullCQ, sizes: Mapping[str, int], totals: Totals, hint: str = "merge") -> DataFrame:
    """Counts and sums of all answers of each machine, without making them one by one.

    Tuples of an atom that agree on all that other atoms or the groups see are counted first; the
    local join meets one row for each such set, and counts multiply. A partial row for each machine and group.
    """
    small, group, value = {}, next(a.name for a in cq.atoms if totals.of in a.vars), next(a.name for a in cq.atoms if totals.over in a.vars)
    for a in cq.atoms:
        keep = ["machine", *[x for x in a.vars if len(cq.having(x)) > 1], *([F.expr(totals.by).alias(totals.name)] if a.name == group else [])]
        summed = [F.sum(totals.over).alias("_sum")] if a.name == value else []
        small[a.name] = parts[a.name].groupBy(*keep).agg(F.count("*").alias(f"_n_{a.name}"), *summed)
    joined = local_join(small, cq, sizes, hint)
    times = lambda names: reduce(lambda c, d: c * d, [F.col(f"_n_{a}") for a in names], F.lit(1).cast("long"))
    names = [a.name for a in cq.atoms]
    return joined.groupBy("machine", totals.name).agg(F.sum(times(names)).alias("n"), F.sum(times([a for a in names if a != value]) * F.col("_sum")).alias("total"))


def _range_of(column: np.ndarray, spans: np.ndarray, values: np.ndarray) -> np.ndarray:
    """For each span of rows, in which ``column`` is sorted, the rows that have the value: binary search in all spans at once."""
    out = np.empty_like(spans)
    for side in (0, 1):
        low, high = spans[:, 0].copy(), spans[:, 1].copy()
        while (open_ := low < high).any():
            mid = (low + high) // 2
            at = column[np.minimum(mid, len(column) - 1)]
            right = open_ & ((at < values) if side == 0 else (at <= values))
            low, high = np.where(right, mid + 1, low), np.where(open_ & ~right, mid, high)
        out[:, side] = low
    return out


def local_generic_join(parts: Mapping[str, DataFrame], cq: FullCQ, machines: int) -> DataFrame:
    """Variable by variable inside each machine: candidates of a variable are met by all its atoms at once.

    Work follows the worst-case output, not an intermediate join; payload columns are not kept.
    """
    vars_, atoms = cq.vars, [(a.name, [cq.vars.index(x) for x in sorted(a.vars, key=cq.vars.index)]) for a in cq.atoms]
    tagged = None
    for a in cq.atoms:
        ordered = sorted(a.vars, key=vars_.index)
        rows = parts[a.name].select("machine", F.lit(a.name).alias("_atom"), F.array(*[F.col(x).cast("long") for x in ordered]).alias("_key"))
        tagged = rows if tagged is None else tagged.unionAll(rows)

    # Level by level: rows of each atom are sorted by its variables in order, and every partial answer holds a
    # range of rows in each atom. The atom with the fewest rows left offers values, the others look them up.
    def run(table: pa.Table) -> pa.Table:
        names, keys = table.column("_atom"), table.column("_key")
        sorted_rows, spans = [], []
        for name, own in atoms:
            at = keys.filter(pc.equal(names, name)).combine_chunks()
            rows = np.asarray(at.flatten()).reshape(-1, len(own))
            sorted_rows.append(rows[np.lexsort(rows.T[::-1])])
            spans.append(np.array([[0, len(rows)]], np.int64))
        found = np.zeros((1, 0), np.int64)
        for i in range(len(vars_)):
            using = [(j, own.index(i)) for j, (_, own) in enumerate(atoms) if i in own]
            widths = np.stack([spans[j][:, 1] - spans[j][:, 0] for j, _ in using])
            least, parts = widths.argmin(0), []
            for k, (j, level) in enumerate(using):
                mine = np.flatnonzero(least == k)
                first, count = spans[j][mine, 0], widths[k][mine]
                of = np.repeat(mine, count)
                row = np.arange(count.sum()) + np.repeat(first - np.cumsum(count) + count, count)
                value = sorted_rows[j][row, level]
                # One offer for each distinct value of a range.
                new = np.ones(len(of), bool)
                new[1:] = (of[1:] != of[:-1]) | (value[1:] != value[:-1])
                parts.append((of[new], value[new]))
            of, value = (np.concatenate(c) for c in zip(*parts))
            alive, held = np.ones(len(of), bool), {}
            for j, level in using:
                held[j] = _range_of(sorted_rows[j][:, level], spans[j][of], value)
                alive &= held[j][:, 1] > held[j][:, 0]
            found = np.column_stack([found[of[alive]], value[alive]])
            spans = [held[j][alive] if j in held else span[of[alive]] for j, span in enumerate(spans)]
        times = np.prod([span[:, 1] - span[:, 0] for span in spans], axis=0)
        found = np.repeat(found, times, axis=0)
        machine = pa.array(np.full(len(found), table.column("machine")[0].as_py(), np.int32))
        return pa.table([machine, *[pa.array(np.ascontiguousarray(found[:, i])) for i in range(len(vars_))]], names=["machine", *vars_])

    return exchange(tagged, machines).groupBy("machine").applyInArrow(run, "machine int, " + ", ".join(f"{x} long" for x in vars_))


@dataclass
class Result:
    answers: DataFrame
    plan: Plan
    routed: dict[str, DataFrame]


HYBRID_ROWS = 1_000_000


def evaluate(
    cq: FullCQ,
    relations: Mapping[str, DataFrame],
    costs: Sequence[CostFunction],
    mode: str = "auto",
    sizes: Mapping[str, int] | None = None,
    strategy: str = "auto",
    local: str = "merge",
    hybrid: Sequence[str] = (),
    sub: int = 1,
    sub_by: Sequence[str] | None = None,
    classify: bool = False,
    totals: Totals | None = None,
    **options,
) -> Result:
    """Answers with a column ``machine`` and every variable; with ``totals``, only their count and sum by group.

    Sizes are counted unless given: one small aggregate for each atom. With ``classify``, a profile
    of every atom gives them, and says where keys are dense enough to be their own coordinates.
    Atoms in ``hybrid`` are broadcast instead of routed, up to ``HYBRID_ROWS`` rows each; every
    machine pays for them. ``sub`` cuts each machine's box into that many tasks, along the
    variables in ``sub_by`` if given; ``routed`` has each tuple once for a machine all the same.
    """
    notes = {}
    if classify:
        classes = profile.classify(cq, relations)
        sizes = sizes or {a: c.rows for a, c in classes.items()}
        options["coordinates"] = {x: coords.xx(options.get("seed", 1), options.get("grid_bits", pack.GRID_BITS)) for x in cq.vars} | profile.dense_coordinates(cq, classes) | dict(options.get("coordinates") or {})
        notes |= {f"class_{a}": c.kind for a, c in classes.items()}
    sizes = dict(sizes or {a.name: relations[a.name].count() for a in cq.atoms})
    if too_large := [a for a in hybrid if sizes[a] > HYBRID_ROWS]:
        raise ValueError(f"too large to broadcast: {too_large}")
    made = plan(cq, sizes, costs, mode, **options)
    made.notes |= notes
    inner = FullCQ(tuple(a for a in cq.atoms if a.name not in hybrid))
    routed = {a.name: route(relations[a.name], a, made.packing, made.coordinates, strategy) for a in inner.atoms}
    tasks, dealt = len(made.costs) * sub, routed
    if sub > 1:
        boxes = pack.subdivide(made.packing, inner, sizes, sub, sub_by)
        dealt = {a.name: route(relations[a.name], a, boxes, made.coordinates, strategy) for a in inner.atoms}
    if totals and (hybrid or local == "generic"):
        raise ValueError("totals are made by local joins of routed atoms")
    if totals:
        partial = local_totals({a: exchange(df, tasks) for a, df in dealt.items()}, inner, sizes, totals, local)
        answers = partial.groupBy(totals.name).agg(F.sum("n").alias("n"), F.sum("total").alias("total"))
        return Result(answers, made, routed)
    if local == "generic":
        answers = local_generic_join(dealt, inner, tasks)
    else:
        answers = local_join({a: exchange(df, tasks) for a, df in dealt.items()}, inner, sizes, local)
    known = set(inner.vars)
    for a in cq.atoms:
        if a.name in hybrid:
            answers = answers.join(F.broadcast(relations[a.name]), [x for x in a.vars if x in known])
            known |= set(a.vars)
    if sub > 1:
        answers = answers.withColumn("machine", F.floor(F.col("machine") / F.lit(sub)).cast("int"))
    return Result(answers, made, routed)


def evaluate_sql(spark, text: str, costs: Sequence[CostFunction], **options) -> Result:
    """A query whose relations are views; their columns are the variables, in order."""
    cq = parse_cq(text, allow_copies=True)
    relations = {}
    for a in cq.atoms:
        view = spark.table(a.name.split("__")[0])
        relations[a.name] = view.select(*[F.col(c).alias(x) for c, x in zip(view.columns, a.vars)]).dropna()
    return evaluate(cq, relations, costs, **options)
