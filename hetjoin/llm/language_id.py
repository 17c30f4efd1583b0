"""Language identification with hyperdimensional letter-trigram profiles.

Each letter has a random +-1 vector. A trigram is the product of its three letter vectors,
the first rotated by two places and the second by one, so that order counts; a text is the
sum of its trigrams, and a language the sum of its unit-length training texts. A text gets
the language whose prototype has the largest cosine with it.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .shared import arrow_map, small_batches, to_batch

SYMBOLS, DIMENSIONS, SEED, MOST_LANGUAGES = 64, 1024, 20240, 4096
UNDETERMINED = "und"
_SCALE, _TABLE_ROWS, _PIECE = 1 << 24, 16384, 1 << 20


@lru_cache(maxsize=1)
def _symbol_table() -> np.ndarray:
    """Code point to symbol: 0 for what is no letter, 1-26 for a-z, the rest hashed to 27-63."""
    table = np.zeros(0x110000, np.uint8)
    letters = np.fromiter((c for c in range(0x110000) if chr(c).isalpha()), np.int64)
    table[letters] = 27 + (letters * 2654435761 >> 12) % (SYMBOLS - 27)
    table[ord("a") : ord("z") + 1] = np.arange(1, 27)
    return table


def trigram_counts(text: str) -> tuple[np.ndarray, np.ndarray]:
    """Distinct trigram numbers of the lower-cased text and their counts; any run of other characters is one gap."""
    table, tail, found = _symbol_table(), np.zeros(1, np.uint8), []
    for at in range(0, len(text), _PIECE):
        piece = np.frombuffer(text[at : at + _PIECE].lower().encode("utf-32-le", "replace"), np.uint32)
        s = np.concatenate([tail, table[piece]])
        if at + _PIECE >= len(text):
            s = np.append(s, np.uint8(0))
        keep = np.ones(len(s), bool)
        keep[1:] = (s[1:] > 0) | (s[:-1] > 0)
        s = s[keep].astype(np.int32)
        found.append((s[:-2] * SYMBOLS + s[1:-1]) * SYMBOLS + s[2:])
        tail = s[-2:].astype(np.uint8)
    grams = np.concatenate(found) if found else np.zeros(0, np.int32)
    return np.unique(grams[grams > 0], return_counts=True)


class TrigramVectors:
    """Vectors of trigrams, made when first asked for; the table holds a bounded number of rows."""

    def __init__(self, dimensions: int = DIMENSIONS, seed: int = SEED):
        letters = np.random.default_rng(seed).integers(0, 2, (SYMBOLS, dimensions)).astype(np.float32) * 2 - 1
        self.by_place = [np.roll(letters, 2, axis=1), np.roll(letters, 1, axis=1), letters]
        self.rows = np.zeros((_TABLE_ROWS, dimensions), np.float32)
        self._clear()

    def _clear(self) -> None:
        self.slot, self.used = np.full(SYMBOLS**3, -1, np.int32), 0

    def bundle(self, grams: np.ndarray, weights: np.ndarray) -> np.ndarray:
        out = np.zeros(self.rows.shape[1], np.float64)
        for at in range(0, len(grams), _TABLE_ROWS // 2):
            g, w = grams[at : at + _TABLE_ROWS // 2], weights[at : at + _TABLE_ROWS // 2]
            new = g[self.slot[g] < 0]
            if self.used + len(new) > _TABLE_ROWS:
                self._clear()
                new = g
            if len(new):
                a, b, c = new // SYMBOLS**2, new // SYMBOLS % SYMBOLS, new % SYMBOLS
                self.rows[self.used : self.used + len(new)] = self.by_place[0][a] * self.by_place[1][b] * self.by_place[2][c]
                self.slot[new] = np.arange(self.used, self.used + len(new))
                self.used += len(new)
            out += w.astype(np.float32) @ self.rows[self.slot[g]]
        return out


def fit_prototypes(docs: DataFrame, dimensions: int = DIMENSIONS, seed: int = SEED) -> dict[str, np.ndarray]:
    """Language prototypes from all rows of ``docs`` (columns text, lang) with both values present.

    Every task adds up its texts' trigram weights per language and turns them into vectors
    once; only ``dimensions`` sums per language reach the driver, and over ``MOST_LANGUAGES`` labels are refused. Sums are of integers, so
    the result does not depend on the order of rows. Texts without letters add nothing.
    """

    def learn(batches):
        sums: dict[str, np.ndarray] = {}
        vectors = TrigramVectors(dimensions, seed)

        def out():
            for lang, hist in sums.items():
                grams = np.flatnonzero(hist)
                v = np.rint(vectors.bundle(grams, hist[grams]) * _SCALE).astype(np.int64)
                yield to_batch({"lang": pa.array([lang] * dimensions), "dim": pa.array(np.arange(dimensions, dtype=np.int32)), "total": pa.array(v)})
            sums.clear()

        for batch in small_batches(batches):
            for text, lang in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                grams, counts = trigram_counts(text)
                if len(grams):
                    if lang not in sums and len(sums) >= 64:
                        yield from out()
                    hist = sums.setdefault(lang, np.zeros(SYMBOLS**3))
                    hist[grams] += counts / np.sqrt((counts.astype(float) ** 2).sum())
        yield from out()

    rows = arrow_map(docs.select("text", "lang").where("text is not null and lang is not null"), learn, "lang string, dim int, total long").groupBy("lang", "dim").agg(F.sum("total").alias("total")).limit(MOST_LANGUAGES * dimensions + 1).collect()
    if len(rows) > MOST_LANGUAGES * dimensions:
        raise ValueError(f"over {MOST_LANGUAGES} different languages in the labels")
    found: dict[str, np.ndarray] = {}
    for r in rows:
        found.setdefault(r["lang"], np.zeros(dimensions))[r["dim"]] = r["total"]
    return {k: v / n for k, v in sorted(found.items()) if (n := np.linalg.norm(v)) > 0}


def labelled(docs: DataFrame, prototypes: dict[str, np.ndarray], keep: tuple[str, ...], body: str = "text", dimensions: int = DIMENSIONS, seed: int = SEED) -> DataFrame:
    """The columns ``keep`` as _0, _1, ..., with ``lang_pred`` and ``score``.

    ``und`` with score 0 where text is null or has no letter, or no prototype exists; equal
    cosines go to the alphabetically first language. Scores are cosines, negative ones 0.
    """
    names = sorted(prototypes)
    matrix = np.array([prototypes[k] for k in names]) if names else np.zeros((0, dimensions))
    at = keep.index(body) if body in keep else len(keep)

    def label(batches):
        vectors = TrigramVectors(dimensions, seed)
        for batch in small_batches(batches):
            langs, scores = [], []
            for text in batch.column(at).to_pylist():
                grams, counts = trigram_counts(text or "")
                best, score = UNDETERMINED, 0.0
                if len(grams) and names:
                    v = vectors.bundle(grams, counts)
                    if (norm := np.linalg.norm(v)) > 0:
                        cosines = np.round(matrix @ v / norm, 9)
                        best, score = names[int(cosines.argmax())], float(min(1.0, max(0.0, cosines.max())))
                langs.append(best)
                scores.append(score)
            kept = {f"_{i}": batch.column(i) for i in range(len(keep))}
            yield to_batch(kept | {"lang_pred": pa.array(langs, pa.string()), "score": pa.array(scores, pa.float64())})

    chosen = docs.select(*[docs[k].alias(f"_{i}") for i, k in enumerate(keep)], *([docs[body]] if at == len(keep) else []))
    return arrow_map(chosen, label, T.StructType([*chosen.schema.fields[: len(keep)], T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())]))


def predict(docs: DataFrame, prototypes: dict[str, np.ndarray], keep: tuple[str, ...] = ("doc_id",), body: str = "text", dimensions: int = DIMENSIONS, seed: int = SEED) -> DataFrame:
    """The columns ``keep`` with ``lang_pred`` and ``score`` of :func:`labelled`, which win over columns of these names."""
    found = labelled(docs, prototypes, keep, body, dimensions, seed)
    return found.select(*[F.col(f"_{i}").alias(k) for i, k in enumerate(keep) if k not in ("lang_pred", "score")], "lang_pred", "score")


def held_out(docs: DataFrame):
    """Column: the document is kept out of learning (crc32 of its id as text leaves 1 modulo 3)."""
    return F.coalesce(F.crc32(docs["doc_id"].cast("string")) % 3 == 1, F.lit(False))


def identify(docs: DataFrame) -> DataFrame:
    """Learns from the documents that are not held out and labels all: doc_id, held_out, lang_pred, score.

    Texts of any length are read whole. An empty table gives no rows; other columns of the input play no part, whatever their names.
    """
    prototypes = fit_prototypes(docs.where(~held_out(docs)))
    with_fold = docs.select("doc_id", held_out(docs).alias("held_out"), "text")
    return predict(with_fold, prototypes, keep=("doc_id", "held_out"))
