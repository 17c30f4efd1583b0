"""Byte-level BPE with a segment tree over the ranks of adjacent pairs.

The leaves of a piece's tree hold, for every living symbol, the rank of the pair that it
forms with its right neighbour, and its place; an inner node holds the smaller of its two.
The root is therefore the leftmost pair of lowest rank. A merge changes three leaves, each
in logarithmic time, and the piece is done when the root holds no pair.
"""

from __future__ import annotations

import hashlib
import json
import os
import re
import unicodedata
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from .shared import arrow_map, small_batches, to_batch

END_ID, DEFAULT_VOCABULARY = 2, "byte_bpe_50k.json"
# The white space of Unicode, as in the pattern of the vocabulary's pre-tokenizer.
WHITE_SPACE = "\\t-\\r \\x85\\xa0\\u1680\\u2000-\\u200a\\u2028\\u2029\\u202f\\u205f\\u3000"
_SEGMENT, _CACHED_CHARS, _CACHED_WORDS = 1 << 20, 48, 300_000


def vocabulary_path(name: str = DEFAULT_VOCABULARY) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


@lru_cache(maxsize=2)
def piece_pattern(end: int = 0x110000) -> re.Pattern:
    """Contractions, letter runs, number runs, other runs (each with a space before it) and white space.

    For texts whose characters all lie below ``end``; short classes match faster."""
    spans: dict[str, list[str]] = {"L": [], "N": []}
    start, kind = 0, ""
    for c in range(end + 1):
        k = unicodedata.category(chr(c))[0] if c < end else ""
        if k != kind:
            if kind in spans:
                spans[kind].append(f"\\U{start:08x}-\\U{c - 1:08x}")
            start, kind = c, k
    letters, numbers, space = "".join(spans["L"]), "".join(spans["N"]), WHITE_SPACE
    return re.compile(f"'(?:s|t|re|ve|m|ll|d)| ?[{letters}]+| ?[{numbers}]+| ?[^{space}{letters}{numbers}]+|[{space}]+(?![^{space}])|[{space}]+")


_safe_cut = re.compile(f"(?<=[^{WHITE_SPACE}]) ")


def segments(text: str, size: int = _SEGMENT):
    """Cuts a long text before spaces that follow another character; no piece ever spans such a place."""
    at = 0
    while len(text) - at > size:
        cut = _safe_cut.search(text, at + size)
        if not cut:
            break
        yield text[at : cut.start()]
        at = cut.start()
    yield text[at:]


def byte_letters() -> list[str]:
    """The printable character that stands for each byte in vocabulary files of this kind."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(rest)) for b in range(256)]


class BpeModel:
    """Encodes and decodes with the vocabulary, merges and added tokens of a tokenizers JSON file."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        letters = byte_letters()
        to_byte = {c: b for b, c in enumerate(letters)}
        vocabulary = spec["model"]["vocab"]
        self.added = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.size = 1 + max([*vocabulary.values(), *self.added.values()])
        self.dtype = np.dtype("<u2") if self.size <= 1 << 16 else np.dtype("<u4")
        self.byte_id = [vocabulary[c] for c in letters]
        self.bytes_of = [b""] * self.size
        for token, i in [*vocabulary.items(), *self.added.items()]:
            self.bytes_of[i] = bytes(to_byte[c] for c in token) if all(c in to_byte for c in token) else token.encode()
        self.merged, self.rank = [], {}
        for r, pair in enumerate(spec["model"]["merges"]):
            left, right = pair if isinstance(pair, list) else pair.split(" ")
            self.merged.append(vocabulary[left + right])
            self.rank[vocabulary[left] * self.size + vocabulary[right]] = r
        self.split_added = re.compile("(" + "|".join(map(re.escape, sorted(self.added, key=len, reverse=True))) + ")") if self.added else None
        self.text_of = [str(i) for i in range(self.size)]
        self.cache: dict[str, bytes] = {}

    def merge(self, data: bytes) -> list[int]:
        """Token ids of one piece."""
        n = len(data)
        symbol = [self.byte_id[b] for b in data]
        if n < 2:
            return symbol
        size = 1 << (n - 2).bit_length()
        rank, vocab, merged = self.rank.get, self.size, self.merged
        none = len(merged) * size
        tree = [none] * (2 * size)
        for i in range(n - 1):
            r = rank(symbol[i] * vocab + symbol[i + 1])
            if r is not None:
                tree[size + i] = r * size + i
        for i in range(size - 1, 0, -1):
            a, b = tree[2 * i], tree[2 * i + 1]
            tree[i] = a if a < b else b
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        while (top := tree[1]) < none:
            r, i = divmod(top, size)
            gone = after[i]
            symbol[i], symbol[gone] = merged[r], -1
            right = after[i] = after[gone]
            changed = [(gone, none)] if gone < size else []
            if right < n:
                before[right] = i
                r = rank(symbol[i] * vocab + symbol[right])
                changed.append((i, none if r is None else r * size + i))
            else:
                changed.append((i, none))
            if (left := before[i]) >= 0:
                r = rank(symbol[left] * vocab + symbol[i])
                changed.append((left, none if r is None else r * size + left))
            for leaf, value in changed:
                at = leaf + size
                if tree[at] == value:
                    continue
                tree[at] = value
                while at > 1:
                    other = tree[at ^ 1]
                    if other < value:
                        value = other
                    at >>= 1
                    if tree[at] == value:
                        break
                    tree[at] = value
        return [s for s in symbol if s >= 0]

    def _piece(self, piece: str) -> bytes:
        ids = np.array(self.merge(piece.encode()), self.dtype).tobytes()
        if len(piece) <= _CACHED_CHARS:
            if len(self.cache) >= _CACHED_WORDS:
                self.cache.clear()
            self.cache[piece] = ids
        return ids

    def id_arrays(self, text: str):
        """Token ids of a whole text, in arrays of bounded size."""
        known, pattern = self.cache.get, piece_pattern(0x110000 if _not_plain.search(text) else _PLAIN)
        for k, part in enumerate(self.split_added.split(text) if self.split_added else [text]):
            if k % 2:
                yield np.array([self.added[part]], self.dtype)
            elif part:
                for s in segments(part):
                    yield np.frombuffer(b"".join([known(p) or self._piece(p) for p in pattern.findall(s)]), self.dtype)

    def encode(self, text: str) -> list[int]:
        return [i for a in self.id_arrays(text) for i in a.tolist()]

    def decode(self, ids) -> str:
        return b"".join([self.bytes_of[i] for i in ids]).decode("utf-8", "replace")


@lru_cache(maxsize=2)
def model(path: str) -> BpeModel:
    return BpeModel(path)


class FastEncoder:
    """Ids only, as uint32 arrays, by a compiled encoder.

    ``engine`` is ``tokenizers``, the library itself, or ``tiktoken``, made from the same JSON
    vocabulary. With ``tokenizers``, a batch of texts is cut where no piece and no added token
    can span the cut (see :func:`part_starts`). Arrow finds the distinct parts of the batch; the
    ids of those that this worker has not met come from the library, and those of short ones are
    remembered, in an older and a newer half that take turns. Vocabularies without such safe
    places, and texts with added tokens in them, go through the library as a whole. Its threads
    are off: Spark has a task on every core.
    """

    def __init__(self, path: str, engine: str = "tokenizers"):
        self.path, self.engine = path, engine
        if engine == "tiktoken":
            import public_tokenizers
            import tiktoken

            own = model(path)
            self.size, self.added, self.split_added = own.size, own.added, own.split_added
            ranks = {own.bytes_of[i]: i for i in own.byte_id}
            for i in own.merged:
                ranks[own.bytes_of[i]] = i
            if own.merged != sorted(own.merged) or own.merged[0] <= max(own.byte_id):
                raise ValueError("ids of this vocabulary do not follow its merges; use engine='tokenizers'")
            self.inner = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
        else:
            os.environ["TOKENIZERS_PARALLELISM"] = "false"
            import tokenizers

            self.inner = tokenizers.Tokenizer.from_file(path)
            self.inner.no_truncation()
            self.inner.no_padding()
            self.size = 1 + max(self.inner.get_vocab(with_added_tokens=True).values())
            self.added = {t.content: i for i, t in self.inner.get_added_tokens_decoder().items()}
            self.merges = self.inner.model
            self.cuts = _cuts_safely(self.inner)
            self.letters = dict(enumerate(byte_letters()))
            self.known: dict[bytes, bytes] = {}
            self.older: dict[bytes, bytes] = {}
        self.dtype = np.dtype("<u2") if self.size <= 1 << 16 else np.dtype("<u4")

    def encode(self, text: str) -> np.ndarray:
        return self.encode_all(pa.array([text], pa.large_string()))[0]

    def encode_all(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts (null: empty) one after another, and where each text's begin, with the end of the last."""
        flat = pc.fill_null(texts, "").cast(pa.large_binary())
        offsets = np.frombuffer(flat.buffers()[1], np.int64)[flat.offset : flat.offset + len(flat) + 1]
        data = np.frombuffer(flat.buffers()[2] or b"", np.uint8)[offsets[0] : offsets[-1]]
        offsets = offsets - offsets[0]
        raw = data.tobytes()
        if self.engine == "tiktoken" or not self.cuts or any(t.encode() in raw for t in self.added):
            each = [self._whole(raw[a:b].decode()) for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist())]
            return np.concatenate([np.zeros(0, np.uint32), *each]), np.concatenate([[0], np.cumsum([len(x) for x in each])]).astype(np.int64)
        starts = part_starts(data, offsets)
        ends = np.append(starts, len(data)).astype(np.int64)
        parts = pa.Array.from_buffers(pa.large_binary(), len(starts), [None, pa.py_buffer(ends), pa.py_buffer(raw)])
        found, lengths = [np.zeros(0, self.dtype)], []
        blocks = np.unique(np.append(np.searchsorted(starts, np.arange(0, len(data), _SEGMENT * 4)), len(starts))).tolist()
        for a, b in zip(blocks, blocks[1:]):
            own = parts.slice(a, b - a).dictionary_encode()
            coded, at = self._ids_of(own.dictionary.to_pylist()), np.asarray(own.indices)
            sizes = np.array([len(x) for x in coded], np.int64) // self.dtype.itemsize
            each = sizes[at]
            stops = np.cumsum(each)
            rows = np.repeat((np.cumsum(sizes) - sizes)[at] - stops + each, each) + np.arange(stops[-1])
            found.append(np.frombuffer(b"".join(coded), self.dtype)[rows])
            lengths.append(each)
        stops = np.cumsum(np.concatenate([np.zeros(1, np.int64), *lengths]))
        return np.concatenate(found).astype(np.uint32), stops[np.searchsorted(starts, offsets)]

    def _whole(self, text: str) -> np.ndarray:
        if self.engine != "tiktoken":
            return np.array(self.inner.encode(text, add_special_tokens=False).ids, np.uint32)
        out = []
        for k, part in enumerate(self.split_added.split(text) if self.split_added else [text]):
            if k % 2:
                out.append(np.array([self.added[part]], np.uint32))
            elif part:
                for s in segments(part):
                    # One piece of over two segments has no safe cut; the tree takes it in n log n.
                    out.append(np.array(self.inner.encode_ordinary(s) if len(s) <= 2 * _SEGMENT else model(self.path).encode(s), np.uint32))
        return np.concatenate(out) if out else np.zeros(0, np.uint32)

    def _ids_of(self, parts: list[bytes]) -> list[bytes]:
        found = list(map(self.known.get, parts))
        if None in found:
            new = [i for i, ids in enumerate(found) if ids is None]
            if self.older:
                for i in new:
                    found[i] = self.older.get(parts[i])
                fresh = {parts[i]: found[i] for i in new if found[i] is not None}
                new = [i for i in new if found[i] is None]
            else:
                fresh = {}
            for i, ids in zip(new, self._by_library([parts[i] for i in new])):
                found[i] = ids
                if len(parts[i]) <= _CACHED_CHARS:
                    fresh[parts[i]] = ids
            if len(self.known) >= _CACHED_WORDS // 2:
                self.known, self.older = {}, self.known
            self.known.update(fresh)
        return found

    def _by_library(self, parts: list[bytes]) -> list[bytes]:
        """The library's merges of the pieces of each part.

        The pieces of most parts are found together, in one text with a line end after each
        part. Parts with white space within, and those with characters on whose class Unicode's
        versions may differ, are cut into pieces by the library, too.
        """
        texts = [p.decode() for p in parts]
        joined = [t for t in texts if _one_plain_run.fullmatch(t)]
        pieces = piece_pattern(_PLAIN).findall("\n".join(joined) + "\n")
        merge, ids, ends = self.merges.tokenize, [], []
        for piece in "\n".join(pieces).encode().decode("latin-1").translate(self.letters | {10: "\n"}).split("\n"):
            if piece:
                ids += [t.id for t in merge(piece)]
            else:
                ends.append(len(ids))
        # A line end between two others leaves two empty places.
        width, raw, ends = self.dtype.itemsize, np.array(ids, self.dtype).tobytes(), ends[::2]
        out = dict(zip(joined, [raw[a * width : b * width] for a, b in zip([0, *ends], ends)]))
        return [out[t] if t in out else np.array(self.inner.encode(t, add_special_tokens=False).ids, self.dtype).tobytes() for t in texts]


# Characters whose class no version of Unicode has changed.
_PLAIN = 0x250
_one_plain_run = re.compile(" ?[^\\t-\\r \\x85\\xa0\\u0250-\\U0010ffff]+")
_not_plain = re.compile("[\\u0250-\\U0010ffff]")
_letter, _mark, _white = (np.zeros(256, bool) for _ in range(3))
_letter[[*range(65, 91), *range(97, 123)]] = True
_mark[[*range(33, 48), *range(58, 65), *range(91, 97), *range(123, 127)]] = True
_white[[9, 10, 11, 12, 13, 32]] = True


def part_starts(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Bytes at which parts begin: places that no piece can span, in texts that begin at ``offsets``.

    These are a space or line end after anything but white space, an ASCII mark after an ASCII
    letter, and what follows a single line end, if that is no white space. Texts must be free
    of added tokens.
    """
    begin = np.zeros(len(data) + 1, bool)
    if len(data) > 1:
        before, own = data[:-1], data[1:]
        begin[1:-1] = _letter[before] & _mark[own]
        at = np.flatnonzero(((own == 32) | (own == 10)) & ~_white[before]) + 1
        last = data[at - 1]
        odd = np.flatnonzero(last >= 128)
        if len(odd):
            x, y, z = last[odd], data[np.maximum(at[odd] - 2, 0)], data[np.maximum(at[odd] - 3, 0)]
            white = ((y == 0xC2) & ((x == 0x85) | (x == 0xA0))) | ((z == 0xE1) & (y == 0x9A) & (x == 0x80)) | ((z == 0xE3) & (y == 0x80) & (x == 0x80))
            white |= (z == 0xE2) & (((y == 0x80) & ((x <= 0x8A) | (x == 0xA8) | (x == 0xA9) | (x == 0xAF))) | ((y == 0x81) & (x == 0x9F)))
            at = np.delete(at, odd[white])
        begin[at] = True
        line = at[data[at] == 10] + 1
        line = line[line < len(data)]
        # A printable ASCII character, or one of the letters and signs of the lead byte C3.
        line = line[((data[line] > 32) & (data[line] < 127)) | (data[line] == 0xC3)]
        begin[line] = True
        # The place before a text's first byte belongs to another text, so what was found there does not count.
        first = offsets[1:-1][offsets[1:-1] + 1 < len(data)]
        lone = first[data[first] == 10] + 1
        begin[lone[~np.isin(lone, offsets)]] = False
    begin[offsets] = True
    return np.flatnonzero(begin[:-1])


def _cuts_safely(inner) -> bool:
    """True if texts may be cut at the places of :func:`part_starts`: plain byte-level pre-tokenizing,
    nothing before it, and added tokens that neither hold nor strip white space."""
    before = inner.pre_tokenizer
    plain = type(before).__name__ == "ByteLevel" and not before.add_prefix_space and before.use_regex
    bare = not any(t.lstrip or t.rstrip or t.single_word or re.search(r"\s", t.content) for t in inner.get_added_tokens_decoder().values())
    return bool(plain and bare and inner.normalizer is None)


@lru_cache(maxsize=2)
def fast_encoder(path: str, engine: str = "tokenizers") -> FastEncoder:
    return FastEncoder(path, engine)


def ended(texts: pa.Array, encoder: FastEncoder) -> tuple[np.ndarray, np.ndarray]:
    """Ids of all texts, each followed by the end id, and where each text's begin, with the end of the last."""
    ids, begins = encoder.encode_all(texts)
    return np.insert(ids, begins[1:], np.uint32(END_ID)), begins + np.arange(len(begins))


def round_trip(docs: DataFrame, path: str | None = None) -> DataFrame:
    """Encodes every text (null: empty), decodes the ids, and returns doc_id, n_tokens and both SHA-256 digests.

    Long texts are worked on in segments. An empty table gives no rows, repeated ids come out as
    often; other columns of the input play no part.
    """
    path = path or vocabulary_path()

    def run(batches):
        bpe = model(path)
        for batch in small_batches(batches):
            counts, coded, decoded = [], [], []
            for text in batch.column(1).to_pylist():
                n, ids_hash, pieces = 0, hashlib.sha256(), []
                for ids in bpe.id_arrays(text or ""):
                    if len(ids):
                        values = ids.tolist()
                        ids_hash.update(("," * (n > 0) + ",".join([bpe.text_of[i] for i in values])).encode())
                        pieces.append(b"".join([bpe.bytes_of[i] for i in values]))
                        n += len(values)
                counts.append(n)
                coded.append(ids_hash.hexdigest())
                decoded.append(hashlib.sha256(b"".join(pieces).decode("utf-8", "replace").encode()).hexdigest())
            yield to_batch({"doc_id": batch.column(0), "n_tokens": pa.array(counts, pa.int64()), "ids_sha256": pa.array(coded), "decoded_sha256": pa.array(decoded)})

    return arrow_map(docs.select("doc_id", "text"), run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
