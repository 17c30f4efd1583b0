"""Substring dedup: near-equal paragraphs found by MinHash bands, verified exactly, and removed but for one.

Ten bands of three values find two paragraphs of similarity 0.8 with a chance of 0.9992, and
of similarity 0.5 with one of 0.74; all candidates are then tested on their shingle sets.

Then passages, in the texts without those paragraphs: a run of ``SPAN`` words that also stands
elsewhere, wherever lines end, is cut but for its first place. Each run of words is named by
the least of the hashes of its ``GRAM``-word parts. Equal runs have equal names, so only runs
whose name comes up at another place are hashed as a whole and compared.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .shared import arrow_map, discard, small_batches, to_batch, written
from .tiles import Bloom, linked_classes, one_key, shared_keys
from .wordhash import Units, document_units, mix, packed_bitmaps, powers, sorted_units, words

BANDS, ROWS_PER_BAND, MIN_WORDS, SEED = 10, 3, 25, 31
SPAN, GRAM = 51, 25
_BLOCK = 1 << 18


def recall(similarity: float, bands: int = BANDS, rows: int = ROWS_PER_BAND) -> float:
    """Chance that two sets of this similarity share a band."""
    return 1 - (1 - similarity**rows) ** bands


class Paragraphs:
    """Lines of a batch of texts as units, with the document row and line number of each."""

    def __init__(self, texts: list[str]):
        raw = [(t or "").encode() for t in texts]
        self.data = np.frombuffer(b"\n".join(raw), np.uint8)
        lengths = np.array([len(r) + 1 for r in raw], np.int64)
        docs = np.concatenate([[0], np.cumsum(lengths)])[:-1]
        starts = np.concatenate([[0], np.flatnonzero(self.data == 10) + 1])
        self.row = np.searchsorted(docs, starts, side="right") - 1
        self.number = np.arange(len(starts)) - np.searchsorted(starts, docs)[self.row]
        self.units = Units(self.data, np.append(starts, len(self.data)))
        self.starts = np.append(starts, len(self.data) + 1)

    def text(self, i: int) -> str:
        return self.data[self.starts[i] : self.starts[i + 1] - 1].tobytes().decode()


def place(sid, doc_id, text_hash, number) -> np.ndarray:
    parts = [np.asarray(x).astype(np.int64).view(np.uint64) for x in (sid, doc_id, text_hash, number)]
    out = np.zeros(len(parts[0]), np.uint64)
    for p in parts:
        out = mix(out * np.uint64(0x9E3779B97F4A7C15) + p)
    return out.view(np.int64)


def band_keys(values: np.ndarray, begins: np.ndarray, bands: int = BANDS, rows: int = ROWS_PER_BAND, seed: int = SEED) -> np.ndarray:
    """A row of band hashes for every set of shingle hashes; the sets lie one after another from ``begins`` on.

    Shingle hashes are well mixed, so an odd multiplier and a shift of high bits to low ones
    give each hash function an order of its own.
    """
    draws = np.random.default_rng(seed).integers(0, 1 << 63, bands * rows).astype(np.uint64) * np.uint64(2) + np.uint64(1)
    keys = np.empty((len(begins), bands), np.uint64)
    for b in range(bands):
        key = np.full(len(begins), b + 1, np.uint64)
        for draw in draws[b * rows : (b + 1) * rows]:
            turned = values * draw
            turned ^= turned >> np.uint64(32)
            turned *= draw
            key = mix(key * np.uint64(0x9E3779B97F4A7C15) + np.minimum.reduceat(turned, begins))
        keys[:, b] = key
    return keys.view(np.int64)


def paragraphs(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """A written row (doc_id, text_hash, number, sid, place, n, bits, keys) for every line of at least ``min_words`` words.

    ``n`` is the number of distinct shingles. Of lines with equal words, a task gives ``bits`` and ``keys``
    (band hashes) to the first it meets, and as a rule to that only.
    """

    def run(batches):
        done: set[int] = set()
        for batch in small_batches(batches):
            p = Paragraphs(batch.column(2).to_pylist())
            at = np.flatnonzero(p.units.count >= min_words)
            if not len(at):
                continue
            values, begins, n = sorted_units(*p.units.shingles(), at)
            sids = p.units.sequence_ids()[at]
            rows = pa.array(p.row[at])
            doc, text = (batch.column(c).take(rows) for c in (0, 1))
            fresh = np.zeros(len(at), bool)
            for i, s in enumerate(sids.tolist()):
                if s not in done:
                    fresh[i] = True
                    done.add(s)
            if len(done) >= 1 << 18:
                done.clear()
            keys = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(np.where(fresh, BANDS, 0))]).astype(np.int32)), pa.array(band_keys(values, begins)[fresh].ravel()))
            yield to_batch({"doc_id": doc, "text_hash": text, "number": pa.array(p.number[at].astype(np.int32)), "sid": pa.array(sids), "place": pa.array(place(sids, doc.fill_null(0), text, p.number[at])), "n": pa.array(n), "bits": packed_bitmaps(values, begins, n, fresh), "keys": keys})

    chosen = docs.select("doc_id", F.xxhash64("text"), "text").where("text is not null")
    return written(arrow_map(chosen, run, "doc_id long, text_hash long, number int, sid long, place long, n long, bits binary, keys array<long>"), "paragraphs")


def texts_of(docs: DataFrame, min_words: int = MIN_WORDS):
    """(sid, text) of the paragraphs whose document and place are in a Bloom filter."""
    text_hash = F.xxhash64("text")
    chosen = docs.select("doc_id", text_hash.alias("text_hash"), F.xxhash64("doc_id", text_hash).alias("doc"), "text").where("text is not null")

    def give(bloom: Bloom) -> DataFrame:
        def run(batches):
            for batch in small_batches(batches):
                batch = batch.take(pa.array(np.flatnonzero(bloom.holds(np.asarray(batch.column(2))))))
                if not batch.num_rows:
                    continue
                p = Paragraphs(batch.column(3).to_pylist())
                sids = p.units.sequence_ids()
                at = np.flatnonzero(p.units.count >= min_words)
                doc, text = (np.asarray(batch.column(c).fill_null(0)) for c in (0, 1))
                held = at[bloom.holds(place(sids[at], doc[p.row[at]], text[p.row[at]], p.number[at]))]
                yield to_batch({"sid": pa.array(sids[held]), "text": pa.array([p.text(i) for i in held.tolist()], pa.string())})

        return arrow_map(chosen, run, "sid long, text string")

    return give


def duplicates(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """(doc_id, text_hash, number, kept_doc): the paragraphs to remove, with the document that keeps the first of their group.

    A group is a component of similar paragraphs; its first by (doc_id, number) stays.
    """
    rows = paragraphs(docs, min_words)
    first = F.min(F.struct("doc_id", "number", "text_hash", "place")).alias("first")
    classes = written(rows.groupBy("sid").agg(first, F.count("*").alias("copies"), F.first("n").alias("n"), F.first("bits", True).alias("bits")), "classes")
    owners = classes.select("sid", F.xxhash64("first.doc_id", "first.text_hash").alias("doc"), F.col("first.place").alias("where"), "n", "bits")
    keys = written(shared_keys(rows.select(F.explode("keys").alias("key"), "sid", F.col("n").cast("int"))), "shared-keys")
    roots = linked_classes(keys, owners, texts_of(docs, min_words), sure=one_key)
    rooted = classes.select("sid", "first", "copies").join(roots.select(F.col("id").alias("sid"), "root"), "sid", "left").withColumn("root", F.coalesce("root", "sid"))
    groups = rooted.groupBy("root").agg(F.min("first").alias("keep"), F.sum("copies").alias("total")).where("total > 1")
    doomed = rooted.select("sid", "root").join(groups.select("root", "keep"), "root").select("sid", "keep")
    same = F.col("doc_id").eqNullSafe(F.col("keep.doc_id")) & (F.col("number") == F.col("keep.number")) & (F.col("text_hash") == F.col("keep.text_hash"))
    out = rows.select("doc_id", "text_hash", "number", "sid").join(doomed, "sid").where(~same).select("doc_id", "text_hash", "number", F.col("keep.doc_id").alias("kept_doc"))
    # What is removed, by document. Rows equal in id and text are treated alike.
    gone = written(out.groupBy(F.col("doc_id").alias("_id"), F.col("text_hash").alias("_hash")).agg(F.array_sort(F.collect_set("number")).alias("_gone"), F.collect_set("kept_doc").alias("_kept")), "removed-lines")
    discard(rows, classes, roots)
    return gone


def rolled(h: np.ndarray, size: int) -> np.ndarray:
    """A hash of every run of ``size`` word hashes, by its first word: differences of running sums of a polynomial."""
    out = np.zeros(max(0, len(h) - size + 1), np.uint64)
    up, down = powers(_BLOCK + size), powers(_BLOCK + size, inverse=True)
    for a in range(0, len(out), _BLOCK):
        part = h[a : a + _BLOCK + size - 1]
        sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(part * down[: len(part)], dtype=np.uint64)])
        out[a : a + _BLOCK] = (sums[size:] - sums[:-size]) * up[: len(part) - size + 1]
    return mix(out)


def least_of(x: np.ndarray, size: int) -> np.ndarray:
    """The least of every ``size`` neighbouring values."""
    width = 1
    while width < size:
        step = min(width, size - width)
        x, width = np.minimum(x[:-step], x[step:]), width + step
    return x


class Runs:
    """Runs of ``span`` words of a batch of texts, and their names."""

    def __init__(self, texts: pa.Array, span: int):
        self.units, self.span = document_units(texts), span
        # First words of runs that do not go past the end of their text.
        n = max(0, len(self.units.hashes) - span + 1)
        text = np.searchsorted(self.units.first, np.arange(n), side="right") - 1
        self.at = np.flatnonzero(self.units.first[text + 1] - np.arange(n) >= span) if n else np.zeros(0, np.int64)
        self.text = text[self.at]

    def names(self) -> np.ndarray:
        gram = min(GRAM, self.span)
        return least_of(rolled(self.units.hashes, gram), self.span - gram + 1)[self.at]

    def hashes(self) -> np.ndarray:
        return rolled(self.units.hashes, self.span)[self.at].view(np.int64)


def _offsets(counts: np.ndarray) -> pa.Array:
    return pa.array(np.concatenate([[0], np.cumsum(counts)]).astype(np.int32))


def _replaced(texts: pa.Array, rows: np.ndarray, new: list[str]) -> pa.Array:
    mask = np.zeros(len(texts), bool)
    mask[rows] = True
    return pc.replace_with_mask(texts, pa.array(mask), pa.array(new, texts.type))


def without_lines(docs: DataFrame, gone: DataFrame, span: int = SPAN) -> DataFrame:
    """A written row for each of ``docs``: its columns but ``text`` as _0, _1, ..., ``_doc`` (a hash of id and text), ``_id``,
    ``_text`` without the lines in ``gone``, and the names of that text's runs, each as often as stretches of runs have it."""
    same = docs["doc_id"].eqNullSafe(gone["_id"]) & (F.xxhash64(docs["text"]) == gone["_hash"])
    others = [docs[c].alias(f"_{i}") for i, c in enumerate(docs.columns) if c != "text"]
    chosen = docs.join(gone.hint("merge"), same, "left").select(*others, F.xxhash64(docs["doc_id"], docs["text"]).alias("_doc"), docs["doc_id"].alias("_id"), docs["text"].alias("_text"), "_gone", "_kept")
    schema = T.StructType([*chosen.schema.fields, T.StructField("_names", T.ArrayType(T.LongType()))])

    def run(batches):
        for batch in small_batches(batches):
            columns = {name: batch.column(i) for i, name in enumerate(batch.schema.names)}
            if len(rows := np.flatnonzero(np.asarray(columns["_gone"].is_valid()))):
                texts, lost = (columns[c].take(pa.array(rows)).to_pylist() for c in ("_text", "_gone"))
                columns["_text"] = _replaced(columns["_text"], rows, [without(t, [], g)[0] for t, g in zip(texts, lost)])
            runs = Runs(columns["_text"], span)
            names = runs.names()
            opens = np.flatnonzero(np.concatenate([[True], (names[1:] != names[:-1]) | (runs.text[1:] != runs.text[:-1])])) if len(names) else np.zeros(0, np.int64)
            columns["_names"] = pa.ListArray.from_arrays(_offsets(np.bincount(runs.text[opens], minlength=batch.num_rows)), pa.array(names[opens].view(np.int64)))
            yield to_batch(columns)

    return written(arrow_map(chosen, run, schema), "texts-without-lines")


def repeated_runs(texts: DataFrame, span: int = SPAN) -> DataFrame:
    """(_doc, _starts, _kept_runs): the first words of runs that stand at an earlier place too, and the documents of those.

    ``texts`` has _doc, _id, _text and _names. Places are ordered by document, hash of id and text, and word.
    Runs that overlap the first place themselves do not count.
    """
    shared = written(texts.select(F.explode("_names").alias("name")).groupBy("name").agg(F.count("*").alias("n")).where("n > 1").select("name"), "shared-names")
    bloom = Bloom(shared, "name")
    discard(shared)

    def run(batches):
        for batch in small_batches(batches):
            lists = batch.column(3)
            held = np.concatenate([[0], np.cumsum(bloom.holds(np.asarray(lists.flatten())))])
            ends = np.asarray(lists.offsets) - lists.offsets[0].as_py()
            batch = batch.take(pa.array(np.flatnonzero(held[ends[1:]] > held[ends[:-1]])))
            runs = Runs(batch.column(2), span)
            at = np.flatnonzero(bloom.holds(runs.names().view(np.int64)))
            rows = pa.array(runs.text[at])
            starts = runs.at[at] - runs.units.first[runs.text[at]]
            yield to_batch({"hash": pa.array(runs.hashes()[at]), "id": batch.column(0).take(rows), "doc": batch.column(1).take(rows), "start": pa.array(starts.astype(np.int32))})

    def later(batches):
        held = [np.zeros(1, np.int64)] * 5  # hash, document, whether it is null, row's hash and first word of the open run's first place
        started = False
        for batch in batches:
            if not batch.num_rows:
                continue
            null = np.asarray(batch.column(1).is_null().cast(pa.int8()))
            rows = [np.asarray(batch.column(i).fill_null(0)).astype(np.int64) for i in range(4)]
            rows = [*rows[:2], null.astype(np.int64), *rows[2:]]
            new = rows[0] != np.concatenate([held[0], rows[0][:-1]])
            new[0] |= not started
            started = True
            at = np.maximum.accumulate(np.where(new, np.arange(len(new)), -1))
            keep = [np.where(at >= 0, c[at], h) for c, h in zip(rows, held)]
            held = [c[-1:] for c in keep]
            inside = (rows[3] == keep[3]) & (rows[4] - keep[4] < span)
            out = np.flatnonzero(~inside)
            yield to_batch({"_doc": batch.column(2).take(pa.array(out)), "start": batch.column(3).take(pa.array(out)), "kept": pa.array(keep[1][out], mask=keep[2][out] == 1)})

    found = arrow_map(texts.where("size(_names) > 0").select("_id", "_doc", "_text", "_names"), run, "hash long, id long, doc long, start int")
    ordered = found.repartition("hash").sortWithinPartitions("hash", "id", "doc", "start")
    again = arrow_map(ordered, later, "_doc long, start int, kept long")
    return written(again.groupBy("_doc").agg(F.collect_set("start").alias("_starts"), F.collect_set("kept").alias("_kept_runs")), "repeated-runs")


def without(text: str, starts: list[int], lost: list[int], span: int = SPAN) -> tuple[str, list[tuple[int, int]]]:
    """The text without the ``lost`` lines and the runs of ``span`` words from ``starts`` on, and the first and last word of each cut.

    A word goes with the white space up to the next one in its line, a line with its last word.
    """
    if not starts:
        gone = set(lost)
        return "\n".join([line for number, line in enumerate(text.split("\n")) if number not in gone]), []
    data = np.frombuffer(text.encode(), np.uint8)
    at = words(data, np.zeros(0, np.int64))[0]
    edge = np.zeros(len(at) + 1, np.int64)
    np.add.at(edge, starts, 1)
    np.add.at(edge, np.array(starts) + span, -1)
    cut = np.cumsum(edge)[:-1] > 0
    ends = np.append(np.flatnonzero(data == 10), len(data))
    first = np.searchsorted(at, np.concatenate([[0], ends[:-1] + 1, [len(data) + 1]]))
    out, gone, raw, begin = [], set(lost), text.encode(), 0
    for number, end in enumerate(ends.tolist()):
        a, b = int(first[number]), int(first[number + 1])
        if number not in gone and not cut[a:b].any():
            out.append(raw[begin:end])
        elif number not in gone and not cut[a:b].all():
            stops = np.append(at[a + 1 : b], end)
            line = raw[begin : at[a]] + b"".join(raw[at[w] : stops[w - a]] for w in range(a, b) if not cut[w])
            out.append(line.rstrip(b" ") if cut[b - 1] else line)
        begin = end + 1
    turns = np.flatnonzero(np.diff(np.concatenate([[0], cut.astype(np.int8), [0]])))
    return b"\n".join(out).decode(), [(int(x), int(y) - 1) for x, y in zip(turns[::2], turns[1::2])]


def _with_removed(docs: DataFrame, min_words: int, span: int = SPAN) -> DataFrame:
    """The columns of ``docs`` but ``text`` as _0, _1, ..., the new ``_text``, ``_gone``, ``_kept``, ``_spans`` and ``_n_cut`` for each row."""
    gone = duplicates(docs, min_words)
    texts = without_lines(docs, gone, span)
    starts = repeated_runs(texts, span)
    discard(gone)
    kept = F.array_sort(F.array_distinct(F.concat(F.coalesce("_kept", F.array().cast("array<bigint>")), F.coalesce("_kept_runs", F.array().cast("array<bigint>")))))
    own = [f"_{i}" for i, c in enumerate(docs.columns) if c != "text"]
    joined = texts.drop("_names", "_id").join(starts.hint("merge"), "_doc", "left").select(*own, "_text", "_gone", kept.alias("_kept"), "_starts")
    schema = T.StructType([*joined.schema.fields[:-1], T.StructField("_spans", T.StringType()), T.StructField("_n_cut", T.LongType())])

    def run(batches):
        for batch in small_batches(batches):
            columns = {name: batch.column(i) for i, name in enumerate(batch.schema.names)}
            begins = columns.pop("_starts")
            spans, cut = [""] * batch.num_rows, np.zeros(batch.num_rows, np.int64)
            if len(rows := np.flatnonzero(np.asarray(begins.is_valid()))):
                done = [without(t, s, [], span) for t, s in zip(columns["_text"].take(pa.array(rows)).to_pylist(), begins.take(pa.array(rows)).to_pylist())]
                columns["_text"] = _replaced(columns["_text"], rows, [d[0] for d in done])
                for i, (_, words_) in zip(rows.tolist(), done):
                    spans[i], cut[i] = ",".join([f"{a}-{b}" for a, b in words_]), sum(b - a + 1 for a, b in words_)
            yield to_batch(columns | {"_spans": pa.array(spans, pa.string()), "_n_cut": pa.array(cut)})

    return arrow_map(joined, run, schema)


def dedup(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """doc_id, text without removed lines and passages, n_paragraphs, n_removed, removed (line numbers from 0), kept_in
    (document ids), n_cut_words and cut_words (first and last word of each cut passage, from 0, in the text without the removed lines).

    Every row comes back. Null texts stay null, an empty table gives no rows, other columns of the input play no part.
    A paragraph is a line of at least ``min_words`` words; shorter lines stay unless a repeated passage of ``SPAN``
    words or more holds them. Rows equal in id and text are treated as one document and lose the same words.
    """
    none = F.array().cast("array<int>")
    chosen = docs.select("doc_id", "text", F.when(F.col("text").isNull(), 0).otherwise(F.size(F.split("text", "\n", -1))).alias("size"))
    return _with_removed(chosen, min_words).select(
        F.col("_0").alias("doc_id"),
        F.col("_text").alias("text"),
        F.col("_2").alias("n_paragraphs"),
        F.size(F.coalesce("_gone", none)).alias("n_removed"),
        F.array_join(F.coalesce("_gone", none).cast("array<string>"), ",").alias("removed"),
        F.col("_kept").alias("kept_in"),
        F.col("_n_cut").alias("n_cut_words"),
        F.col("_spans").alias("cut_words"),
    )


def cleaned(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """The documents with repeated paragraphs and passages cut out; ``n_chars``, where present, follows. No row goes."""
    new = {"text": F.col("_text"), "n_chars": F.length("_text")}
    return _with_removed(docs, min_words).select(*[(new[c].cast(docs.schema[c].dataType) if c in new else F.col(f"_{i}")).alias(c) for i, c in enumerate(docs.columns)])
