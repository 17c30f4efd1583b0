"""Connected components of a graph of 64-bit ids: contraction within tasks, then alternating large-star and small-star steps."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import arrow_map, discard, to_batch, written

# Edges that one task contracts at a time.
LOCAL = 1 << 20


def contracted(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Nodes that are not the least of their component, with the least ones: labels sink along edges and jump to labels of labels."""
    ids, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    u, v = at[: len(a)], at[len(a) :]
    label = np.arange(len(ids))
    while len(u):
        low, high = np.minimum(label[u], label[v]), np.maximum(label[u], label[v])
        np.minimum.at(label, high, low)
        while (jumped := label[label]).tobytes() != label.tobytes():
            label = jumped
        apart = label[u] != label[v]
        u, v = u[apart], v[apart]
    other = np.flatnonzero(label != np.arange(len(ids)))
    return ids[other], ids[label[other]]


def _contract(batches):
    held: list[tuple[np.ndarray, np.ndarray]] = []
    for batch in batches:
        held.append(tuple(np.asarray(batch.column(i)) for i in (0, 1)))
        if sum(len(h[0]) for h in held) >= 2 * LOCAL:
            held = [contracted(*map(np.concatenate, zip(*held)))]
            if len(held[0][0]) >= LOCAL:
                yield to_batch(dict(zip("uv", map(pa.array, held.pop()))))
    if held:
        yield to_batch(dict(zip("uv", map(pa.array, contracted(*map(np.concatenate, zip(*held)))))))


def _mark(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)"))).first())


def components(links: DataFrame, local: int = LOCAL) -> DataFrame:
    """``links`` (a, b), from written tables, to (id, root): root is the smallest id that can be reached. Ids without links do not appear.

    Tasks first contract about ``local`` edges each to stars. Where that took several tasks, star
    steps follow: every step takes minima by partial aggregation and joins them back, so a node
    with very many links is never held in one place; each round is a written table.
    """
    tasks = max(1, -(-links.count() // local))
    edges = written(arrow_map(links.select("a", "b").where("a <> b").coalesce(tasks), _contract, "u long, v long"), "edges")
    if tasks > 1:
        edges = _stars(edges)
    roots = written(edges.select(F.col("u").alias("id"), F.col("v").alias("root")).unionAll(edges.select(F.col("v").alias("id"), F.col("v").alias("root")).distinct()), "roots")
    discard(edges)
    return roots


def _stars(edges: DataFrame) -> DataFrame:
    before = None
    while (after := _mark(edges)) != before:
        before = after
        both = edges.unionAll(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).unionAll(edges.join(least, "u").select("u", F.col("m").alias("v"))).where("u <> v").distinct()
        large = written(large, "edges")
        lowest = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(lowest, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").unionAll(lowest.select("u", F.col("m").alias("v"))).distinct()
        old, edges = edges, written(small.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "edges")
        discard(large, old)
    return edges
