"""Best-fit packing by minimum bin slack: each bin takes the fullest combination of lengths still there.

Only the histogram of piece lengths matters to the choice of combinations. It has at most
``capacity`` rows, so the driver plans on it; a combination is used as often as the counts
allow at once, so the number of steps depends on the number of lengths, not of documents.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .bpe import ended, fast_encoder, vocabulary_path
from .shared import arrow_map, small_batches, to_batch, written

CAPACITY = 1024


def fullest(counts: dict[int, int], first: int, capacity: int) -> dict[int, int]:
    """The combination with ``first`` in it that leaves the least room: subset sums as bits of an integer.

    Bit s of the set says that some of the lengths seen so far add up to s. Each length comes
    in groups of 1, 2, 4, ... copies; the sets before each group serve to trace the best sum back.
    """
    room = capacity - first
    mask, reach, steps = (1 << room + 1) - 1, 1, []
    for length in sorted((x for x, n in counts.items() if n > (x == first) and x <= room), reverse=True):
        left, group = min(counts[length] - (length == first), room // length), 1
        while left > 0:
            take = min(group, left)
            steps.append((length, take, reach))
            reach |= reach << length * take & mask
            left, group = left - take, group * 2
        if reach >> room & 1:
            break
    total, chosen = reach.bit_length() - 1, {first: 1}
    for length, take, before in reversed(steps):
        if not before >> total & 1:
            chosen[length] = chosen.get(length, 0) + take
            total -= length * take
    return chosen


def plan(histogram: dict[int, int], capacity: int = CAPACITY) -> list[tuple[int, dict[int, int]]]:
    """(bins, {length: copies in each}) until no piece is left; the longest piece is always placed."""
    counts, bins = {k: n for k, n in histogram.items() if n}, []
    while counts:
        chosen = fullest(counts, max(counts), capacity)
        times = min(counts[k] // n for k, n in chosen.items())
        bins.append((times, chosen))
        for k, n in chosen.items():
            counts[k] -= times * n
            if not counts[k]:
                del counts[k]
    return bins


def cut(lengths: np.ndarray, capacity: int) -> tuple[np.ndarray, ...]:
    """Row, number, start and length of the pieces of documents of these lengths: only the first piece may be shorter than ``capacity``."""
    parts = -(-lengths // capacity)
    row = np.repeat(np.arange(len(lengths)), parts)
    number = np.arange(len(row)) - np.repeat(np.cumsum(parts) - parts, parts)
    first = (lengths - (parts - 1) * capacity)[row]
    return row, number, np.where(number > 0, first + (number - 1) * capacity, 0), np.where(number > 0, capacity, first)


def pieces(docs: DataFrame, capacity: int = CAPACITY, path: str | None = None, engine: str = "tokenizers") -> DataFrame:
    """One row per piece, with its task and its place among that task's pieces of the same length."""
    path = path or vocabulary_path()

    def run(batches):
        task, seen = TaskContext.get().partitionId(), np.zeros(capacity + 1, np.int64)
        for batch in small_batches(batches, rows=2048, size=2 << 20):
            ids, begins = ended(batch.column(1), fast_encoder(path, engine))
            raw, total = ids.astype("<u4").tobytes(), np.diff(begins)
            row, k, start, length = cut(total, capacity)
            at = (begins[row] + start).tolist()
            crc = [zlib.crc32(raw[4 * a : 4 * (a + n)]) for a, n in zip(at, length.tolist())]
            order, counts = np.argsort(length, kind="stable"), np.bincount(length, minlength=capacity + 1)
            place = np.empty(len(row), np.int64)
            place[order] = np.arange(len(row)) + (seen - np.cumsum(counts) + counts)[length[order]]
            seen += counts
            yield to_batch({"doc_id": batch.column(0).take(pa.array(row)), "piece": pa.array(k.astype(np.int32)), "start": pa.array(start), "length": pa.array(length), "ids_crc32": pa.array(crc, pa.int64()), "task": pa.array(np.full(len(row), task, np.int32)), "place": pa.array(place)})

    return arrow_map(docs.select("doc_id", "text"), run, "doc_id long, piece int, start long, length long, ids_crc32 long, task int, place long")


def assign(cut_pieces: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """Gives every piece its sequence and offset. ``cut_pieces`` must be a written table of :func:`pieces`."""
    by_task = cut_pieces.groupBy("task", "length").agg(F.count("*").alias("_n"))
    bins = plan({r["length"]: r["n"] for r in cut_pieces.groupBy("length").agg(F.count("*").alias("n")).collect()}, capacity)
    slots: dict[int, list[tuple[int, int, int, int]]] = {}
    sequence, used = 0, {}
    for times, chosen in bins:
        offset = 0
        for length, copies in chosen.items():
            slots.setdefault(length, []).append((used.get(length, 0), copies, sequence, offset))
            used[length] = used.get(length, 0) + times * copies
            offset += length * copies
        sequence += times
    tables = {k: np.array(v, np.int64) for k, v in slots.items()}

    def place(batches):
        for batch in batches:
            rank, length = (np.asarray(batch.column(batch.schema.get_field_index(k))) for k in ("_rank", "length"))
            out = np.zeros((len(rank), 2), np.int64)
            for n in np.unique(length):
                at = np.flatnonzero(length == n)
                first, copies, base, offset = tables[int(n)][np.searchsorted(tables[int(n)][:, 0], rank[at], side="right") - 1].T
                copy = rank[at] - first
                out[at, 0], out[at, 1] = base + copy // copies, offset + copy % copies * n
            yield to_batch({k: batch.column(i) for i, k in enumerate(batch.schema.names[:5])} | {"sequence_id": pa.array(out[:, 0]), "offset": pa.array(out[:, 1])})

    before = by_task.select("task", "length", (F.sum("_n").over(Window.partitionBy("length").orderBy("task")) - F.col("_n")).alias("_before"))
    ranked = cut_pieces.join(before, ["task", "length"]).select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("_before") + F.col("place")).alias("_rank"))
    return arrow_map(ranked, place, "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")


def pack(docs: DataFrame, capacity: int = CAPACITY, path: str | None = None, engine: str = "tokenizers") -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset of every piece of every document (null text: empty).

    Repeated ids are documents of their own. An empty table gives no rows; other columns of the input play no part.
    """
    return assign(written(pieces(docs, capacity, path, engine), "pieces"), capacity)
