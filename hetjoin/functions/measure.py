"""What a round cost: tuples, bits, load, copies. Routing alone decides all of it, so no join has to run."""

from __future__ import annotations

import math
import time
from collections.abc import Mapping, Sequence
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans import bounds
from ..plans.cost import CostFunction, as_column
from ..plans.pack import Packing
from ..plans.query import Atom, FullCQ
from .digest import digester


def received(routed: Mapping[str, DataFrame]) -> DataFrame:
    """machine, atom, tuples: partial counts, then at most a row for each machine and atom."""
    counted = [df.groupBy("machine").agg(F.count("*").alias("tuples")).select("machine", F.lit(a).alias("atom"), "tuples") for a, df in routed.items()]
    return reduce(DataFrame.unionAll, counted)


def received_by_seed(df: DataFrame, atom: Atom, packing: Packing, seeds: int, digits: int, chunk: int = 16_384) -> DataFrame:
    """seed, machine, tuples: what each machine would receive of ``df`` for every seed below ``seeds`` of ``coords.md5`` of so many bits.

    The cuts of all boxes part the atom's ranges into cells. Each task counts its tuples by seed and cell,
    adds cells up to boxes once, and hands on at most a row for each seed and machine.
    """
    used, cuts = packing.used(), [sorted({v for c in packing.used() for v in packing.boxes[c][x]}) for x in atom.vars]
    cell_of = [np.searchsorted(own, np.arange(1 << digits), "right") for own in cuts]
    shape = [len(own) + 1 for own in cuts]
    inside = np.zeros((math.prod(shape), len(used)), np.int64)
    for k, c in enumerate(used):
        box = np.ix_(*[np.arange(own.index(lo) + 1, own.index(hi) + 1) for own, (lo, hi) in zip(cuts, (packing.boxes[c][x] for x in atom.vars))])
        member = np.zeros(shape, np.int64)
        member[box] = 1
        inside[:, k] = member.ravel()
    padded, first = digester()
    names = list(atom.vars)

    def run(batches):
        counts = np.zeros((seeds, len(inside)), np.int64)

        def add(columns):
            blocks = [{room: padded(v, room) for room in {len(f"{s}:{x}:") for s in range(seeds)}} for x, v in zip(names, columns)]
            for s in range(seeds):
                cell = 0
                for x, block, cells, n in zip(names, blocks, cell_of, shape):
                    prefix = f"{s}:{x}:".encode()
                    cell = cell * n + cells[first(prefix, *block[len(prefix)]) >> np.uint32(32 - digits)]
                counts[s] += np.bincount(cell, minlength=len(inside))

        held, rows = [], 0
        for batch in batches:
            for start in range(0, batch.num_rows, chunk):
                piece = batch.slice(start, chunk)
                if rows and rows + piece.num_rows > chunk:
                    add([np.concatenate(v) for v in zip(*held)])
                    held, rows = [], 0
                held.append([piece.column(i).to_numpy(zero_copy_only=False) for i in range(len(names))])
                rows += piece.num_rows
        if rows:
            add([np.concatenate(v) for v in zip(*held)])
        tuples = counts @ inside
        at, k = np.nonzero(tuples)
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int64)), pa.array(np.array(used, np.int32)[k]), pa.array(tuples[at, k])], names=["seed", "machine", "tuples"])

    keyed = df.select(*[F.col(x).cast("long").alias(x) for x in names])
    return keyed.mapInArrow(run, "seed long, machine int, tuples long").groupBy("seed", "machine").agg(F.sum("tuples").alias("tuples"))


def bits(loads: DataFrame, cq: FullCQ, n: int, per_value: bool = False) -> DataFrame:
    """Adds bits: log2 n for each tuple, or for each of its values."""
    arity = F.create_map(*[x for a in cq.atoms for x in (F.lit(a.name), F.lit(len(a.vars) if per_value else 1))])
    return loads.withColumn("bits", F.col("tuples") * arity[F.col("atom")] * F.lit(math.log2(n)))


def cost(loads: DataFrame, costs: Sequence[CostFunction], amount: str = "tuples") -> DataFrame:
    """machine, amount, cost of all that each machine received."""
    per = loads.groupBy("machine").agg(F.sum(amount).cast("double").alias("amount"))
    return per.withColumn("cost", as_column(list(costs), F.col("amount"), F.col("machine")))


def load(loads: DataFrame, costs: Sequence[CostFunction], amount: str = "tuples") -> DataFrame:
    """The worst machine's cost, as one row."""
    return cost(loads, costs, amount).agg(F.max("cost").alias("load"))


def ratio(measured: float, bound: float) -> float:
    return measured / bound


def replication(loads: DataFrame, sizes: Mapping[str, int]) -> DataFrame:
    """Rows sent, and sent over rows there are."""
    return loads.agg(F.sum("tuples").alias("sent")).withColumn("replication", F.col("sent") / F.lit(float(sum(sizes.values()))))


def known(loads: DataFrame, sizes: Mapping[str, int], u: Mapping[str, float]) -> DataFrame:
    """machine and the most of the expected answers that it can know from its fractions of the atoms."""
    size = F.create_map(*[x for a, n in sizes.items() for x in (F.lit(a), F.lit(float(n)))])
    power = F.create_map(*[x for a, s in u.items() for x in (F.lit(a), F.lit(float(s)))])
    term = F.col("tuples") / size[F.col("atom")]
    # An atom of which a machine has nothing counts as nothing known, unless its power is zero.
    held = loads.groupBy("machine").agg(F.exp(F.sum(F.log(term) * power[F.col("atom")])).alias("known"), F.collect_set("atom").alias("_has"))
    needs = F.array(*[F.lit(a) for a, s in u.items() if s > 0])
    return held.select("machine", F.when(F.size(F.array_except(needs, "_has")) == 0, F.col("known")).otherwise(F.lit(0.0)).alias("known"))


def tail_trials(routed_for_seed, seeds: Sequence[int], shares: Mapping[tuple[int, str], float], sizes: Mapping[str, int], w: Sequence[float], v: float, delta: float) -> list[tuple[int, bool, float]]:
    """For each seed: whether some machine got over 1 + delta times its share of an atom, beside the bound."""
    out = []
    for s in seeds:
        rows = received(routed_for_seed(s)).collect()  # machines times atoms
        over = any(r["tuples"] > (1 + delta) * shares[r["machine"], r["atom"]] * sizes[r["atom"]] for r in rows)
        out.append((s, over, sum(bounds.tail(n, w, v, delta) for n in sizes.values())))
    return out


def runtime(df: DataFrame) -> dict[str, float]:
    """Seconds to compute all of ``df``, and the bytes that its stages shuffled and spilled to disk."""
    context = df.sparkSession.sparkContext

    def stages():
        made = context._jsc.sc().statusStore().stageList(None, False, False, context._gateway.new_array(context._jvm.double, 0), context._jvm.java.util.ArrayList())
        return [made.apply(i) for i in range(made.size())]

    last = max((s.stageId() for s in stages()), default=-1)
    start = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    took = time.perf_counter() - start
    context._jsc.sc().listenerBus().waitUntilEmpty()
    own = [s for s in stages() if s.stageId() > last]
    return {"seconds": took, "shuffle_bytes": float(sum(s.shuffleWriteBytes() for s in own)), "spill_bytes": float(sum(s.diskBytesSpilled() for s in own))}


def rollup(loads: DataFrame) -> DataFrame:
    """Totals by machine and atom, by machine, and over all."""
    return loads.rollup("machine", "atom").agg(F.sum("tuples").alias("tuples"))


def cube(loads: DataFrame) -> DataFrame:
    """The same, and totals by atom."""
    return loads.cube("machine", "atom").agg(F.sum("tuples").alias("tuples"))


def grouping_sets(loads: DataFrame, sets: Sequence[Sequence[str]]) -> DataFrame:
    """Totals over chosen sets of ``machine`` and ``atom``."""
    return loads.groupingSets([[F.col(c) for c in s] for s in sets], "machine", "atom").agg(F.sum("tuples").alias("tuples"))


def rank(loads: DataFrame) -> DataFrame:
    """Each machine's place by atom, percentile, the next larger count and the running share."""
    w = Window.partitionBy("atom").orderBy(F.desc("tuples"), "machine")
    run = w.rowsBetween(Window.unboundedPreceding, 0)
    total = F.sum("tuples").over(Window.partitionBy("atom"))
    return loads.select("*", F.rank().over(w).alias("rank"), F.percent_rank().over(w).alias("percent"), F.lag("tuples").over(w).alias("above"), (F.sum("tuples").over(run) / total).alias("running_share"))


def top(loads: DataFrame, n: int) -> DataFrame:
    return loads.orderBy(F.desc("tuples"), "machine", "atom").limit(n)
