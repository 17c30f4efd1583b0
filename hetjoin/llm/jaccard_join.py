"""Exact Jaccard join of documents on five-word shingles.

Candidates come from prefixes: in one order of all shingles, two sets that reach the
similarity share at least k of the first n - ceil(0.8 n) + k elements of each (k is 8, or all
that small sets must share); pairs that share fewer are ruled out. The order is by hash, but
for shingles that very many documents have, which come last. Sizes are banded, and pairs
are tested in tiles (see :mod:`tiles`).
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import arrow_map, discard, small_batches, to_batch, written
from .tiles import PERCENT, SHARED, Bloom, linked_classes, shared_keys
from .wordhash import document_units, first_of_equal, packed_bitmaps, sorted_units

SKETCH, COMMON_SHARE, COMMON_LEAST, COMMON_MOST = 1 << 16, 2e-4, 24, 100_000


def sets(docs: DataFrame) -> tuple[DataFrame, np.ndarray]:
    """A written row (doc_id, own, n, sid, bits, doc) for every document (``own`` is a hash of id and text), and the sorted hashes of common shingles.

    Of documents with equal words, a task gives ``bits`` to the first it meets, and as a rule to that only.

    Every task also keeps a Misra-Gries summary of its shingles: ``SKETCH`` counters miss
    none whose share of the task's shingles is over 1 / SKETCH. Only the order of shingles
    depends on it, never the result.
    """

    def run(batches):
        keys, counts, seen = np.zeros(0, np.uint64), np.zeros(0, np.int64), 0
        done: set[int] = set()
        for batch in small_batches(batches):
            units = document_units(batch.column(1))
            sid, none, rows = units.sequence_ids(), units.count == 0, batch.num_rows
            full = np.flatnonzero(~none)
            values, starts, sizes = sorted_units(*units.shingles(), full)
            n = np.zeros(rows, np.int64)
            n[full] = sizes
            fresh = np.zeros(len(full), bool)
            for i, x in enumerate(sid[full].tolist()):
                if x not in done:
                    fresh[i] = True
                    done.add(x)
            if len(done) >= 1 << 18:
                done.clear()
            at = np.zeros(rows, np.int64)
            at[full] = np.arange(len(full))
            seen += rows
            yield to_batch({"doc_id": batch.column(0), "own": batch.column(2), "n": pa.array(n), "sid": pa.array(sid, mask=none), "bits": packed_bitmaps(values, starts, sizes, fresh).take(pa.array(at, mask=none)), "seen": pa.nulls(rows, pa.int64())})
            if len(values):
                new, how_many = np.unique(values[first_of_equal(values, starts)], return_counts=True)
                merged, inverse = np.unique(np.concatenate([keys, new]), return_inverse=True)
                total = np.zeros(len(merged), np.int64)
                np.add.at(total, inverse, np.concatenate([counts, how_many]))
                if len(total) > SKETCH:
                    total -= np.partition(total, len(total) - SKETCH - 1)[len(total) - SKETCH - 1]
                keys, counts = merged[total > 0], total[total > 0]
        often = counts >= max(4, seen * COMMON_SHARE / 2)
        k = int(often.sum())
        yield to_batch({"doc_id": pa.nulls(k, pa.int64()), "own": pa.nulls(k, pa.int64()), "n": pa.nulls(k, pa.int64()), "sid": pa.array(keys[often].view(np.int64)), "bits": pa.nulls(k, pa.binary()), "seen": pa.array(counts[often], pa.int64())})

    both = written(arrow_map(docs.select("doc_id", "text", F.xxhash64("doc_id", "text")), run, "doc_id long, own long, n long, sid long, bits binary, seen long"), "sets")
    rows = both.where("seen is null").select("doc_id", "own", "n", "sid", "bits", F.xxhash64("doc_id").alias("doc"))
    least = max(COMMON_LEAST, int(rows.count() * COMMON_SHARE))
    common = both.where("seen is not null").groupBy("sid").agg(F.sum("seen").alias("seen")).where(F.col("seen") >= least).orderBy(F.desc("seen"), "sid").limit(COMMON_MOST).toArrow()
    return rows, np.sort(common["sid"].to_numpy().astype(np.int64).view(np.uint64))


def prefixes(docs: DataFrame, common: np.ndarray) -> DataFrame:
    """(key, sid, n): the prefix of each distinct text in a task."""
    sent = docs.sparkSession.sparkContext.broadcast(common)

    def run(batches):
        late, done = sent.value, set()
        for batch in small_batches(batches):
            units = document_units(batch.column(0))
            sids, fresh = units.sequence_ids(), []
            for i, sid in enumerate(sids.tolist()):
                if units.count[i] and sid not in done:
                    done.add(sid)
                    fresh.append(i)
            if len(done) >= 1 << 18:
                done.clear()
            if not fresh:
                continue
            values, starts, n = sorted_units(*units.shingles(), np.array(fresh))
            first = first_of_equal(values, starts)
            values, of = values[first], np.repeat(np.arange(len(n)), n)
            is_late = late[np.minimum(np.searchsorted(late, values), len(late) - 1)] == values if len(late) else np.zeros(len(values), bool)
            # Place in the order: by hash, the common ones last.
            begins = np.cumsum(n) - n
            lates = np.cumsum(is_late)
            before = lates - is_late - (lates - is_late)[begins][of]
            place = np.arange(len(values)) - begins[of]
            place = np.where(is_late, n[of] - np.add.reduceat(is_late.astype(np.int64), begins)[of] + before, place - before)
            kept = place < np.minimum(n, n - -(-PERCENT * n // 100) + SHARED)[of]
            of = of[kept]
            yield to_batch({"key": pa.array(values[kept].view(np.int64)), "sid": pa.array(sids[np.array(fresh)][of]), "n": pa.array(n[of].astype(np.int32))})

    return arrow_map(docs.select("text"), run, "key long, sid long, n int")


def texts_of(docs: DataFrame):
    """(sid, text) of the documents whose hashed doc_id is in a Bloom filter."""
    chosen = docs.select(F.xxhash64("doc_id").alias("doc"), "text").where("text is not null")

    def give(bloom: Bloom) -> DataFrame:
        def run(batches):
            for batch in small_batches(batches):
                held = pa.array(np.flatnonzero(bloom.holds(np.asarray(batch.column(0)))))
                if not len(held):
                    continue
                texts = batch.column(1).take(held)
                yield to_batch({"sid": pa.array(document_units(texts).sequence_ids()), "text": texts})

        return arrow_map(chosen, run, "sid long, text string")

    return give


def _linked(docs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Rows of :func:`sets`, and (sid, root, component_id) of every class of equal texts."""
    rows, common = sets(docs)
    classes = written(rows.where("sid is not null").groupBy("sid").agg(F.min("doc_id").alias("least"), F.min("doc").alias("doc"), F.first("n").alias("n"), F.first("bits", True).alias("bits")), "classes")
    owners = classes.select("sid", "doc", "n", "bits", F.col("doc").alias("where"))
    keys = written(shared_keys(prefixes(docs, common)), "shared-keys")
    roots = linked_classes(keys, owners, texts_of(docs))
    rooted = classes.select("sid", "least").join(roots.select(F.col("id").alias("sid"), "root"), "sid", "left").withColumn("root", F.coalesce("root", "sid"))
    named = written(rooted.join(rooted.groupBy("root").agg(F.min("least").alias("component_id")), "root").select("sid", "root", "component_id"), "named-classes")
    discard(classes, roots)
    return rows, named


def join(docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles and component_id (smallest doc_id that links reach) for every row.

    Texts without words (null, empty, white space) have no shingles and are alone; equal texts are
    linked. Rows that repeat an id come out as often; a null id never names a component unless
    nothing else can. An empty table gives no rows; other columns of the input play no part. A
    text of any length is one set.
    """
    rows, named = _linked(docs)
    full = rows.where("sid is not null").join(named, "sid").select("doc_id", F.col("n").alias("n_shingles"), "component_id")
    return full.unionAll(rows.where("sid is null").select("doc_id", F.lit(0).cast("long").alias("n_shingles"), F.col("doc_id").alias("component_id")))


def one_of_each(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` that stay when one row of each group linked by similarity does: that of the smallest id, then hash of its text.

    Null ids come last. Of rows equal in id and text one stays; rows without words all do.
    """
    rows, named = _linked(docs)
    first = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "own")).alias("first")
    chosen = rows.where("sid is not null").join(named, "sid").groupBy("root").agg(first).select(F.col("first.own").alias("_own"), F.lit(False).alias("_all"))
    kept = written(chosen.unionAll(rows.where("sid is null").select("own", F.lit(True)).distinct()), "kept-rows")
    discard(rows, named)
    marked = docs.select(*[docs[c].alias(f"_{i}") for i, c in enumerate(docs.columns)], F.xxhash64(docs["doc_id"], docs["text"]).alias("_own"))
    # The join leaves rows of one document in one place, so no further exchange follows.
    joined = marked.join(kept.hint("merge"), "_own").withColumn("_each", F.when(F.col("_all"), F.monotonically_increasing_id()).otherwise(F.lit(0).cast("long")))
    return joined.dropDuplicates(["_own", "_each"]).select(*[F.col(f"_{i}").alias(c) for i, c in enumerate(docs.columns)])
