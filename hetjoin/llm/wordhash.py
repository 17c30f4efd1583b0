"""Word and shingle hashes of whole batches of texts, computed on their UTF-8 bytes."""

from __future__ import annotations

import numpy as np

SHINGLE = 5
_BASE = np.uint64(0x9E3779B97F4A7C15)
_PART = 2 << 20
_space = np.zeros(256, bool)
_space[[9, 10, 11, 12, 13, 32]] = True
_value = np.arange(256, dtype=np.uint64) + np.uint64(1)
_value[65:91] += np.uint64(32)  # A-Z as a-z
_value[_space] = 0
_powers = {False: np.ones(1, np.uint64), True: np.ones(1, np.uint64)}
# Odd multipliers by place within a shingle.
_place = np.random.default_rng(9).integers(0, 1 << 62, SHINGLE + 1).astype(np.uint64) * np.uint64(2) + np.uint64(1)


def mix(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def powers(n: int, inverse: bool = False) -> np.ndarray:
    """Powers of the base modulo 2^64, or of its inverse."""
    known = _powers[inverse]
    if len(known) < n:
        base = pow(int(_BASE), -1, 1 << 64) if inverse else int(_BASE)
        grown = np.full(max(n, 2 * len(known)), np.uint64(base))
        grown[0] = 1
        known = _powers[inverse] = np.cumprod(grown, dtype=np.uint64)
    return known


def _words(data: np.ndarray, breaks: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    space = _space[data]
    begin = np.empty(len(data), bool)
    begin[0] = True
    begin[1:] = space[:-1]
    begin[breaks[breaks < len(data)]] = True
    begin &= ~space
    at = np.flatnonzero(begin)
    if not len(at):
        return at, np.zeros(0, np.uint64)
    place = np.arange(len(data), dtype=np.int64) - at[np.maximum(np.cumsum(begin) - 1, 0)]
    place[space] = 0
    return at, mix(np.add.reduceat(_value[data] * powers(int(place.max()) + 1)[place], at))


def words(data: np.ndarray, breaks: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Byte place and 64-bit hash of every word; no word goes past one of ``breaks``. Works in parts cut at white space."""
    found, at = [], 0
    while at < len(data):
        end = at + _PART
        while end < len(data):
            cut = np.flatnonzero(_space[data[end : end + 65536]])
            if len(cut):
                end += int(cut[0])
                break
            end += 65536
        end = min(end, len(data))
        start, hashes = _words(data[at:end], breaks[(breaks >= at) & (breaks < end)] - at)
        found.append((start + at, hashes))
        at = end
    if not found:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    return np.concatenate([f[0] for f in found]), np.concatenate([f[1] for f in found])


class Units:
    """Word counts, sequence hashes and shingle hashes of texts, or parts of texts, that lie one after another in a buffer."""

    def __init__(self, data: np.ndarray, starts: np.ndarray):
        """``starts``: where each unit begins, and the end of the last one."""
        self.starts = starts
        at, self.hashes = words(data, starts[:-1]) if len(data) else (np.zeros(0, np.int64), np.zeros(0, np.uint64))
        self.data, self.at = data, at
        self.first = np.searchsorted(at, starts)
        self.count = np.diff(self.first)

    def lines(self) -> np.ndarray:
        """The number of line ends in the buffer before each word."""
        return np.searchsorted(np.flatnonzero(self.data == 10), self.at)

    def sequence_ids(self) -> np.ndarray:
        """A hash of each unit's words in order; 0 for units without words."""
        out, full = np.zeros(len(self.count), np.uint64), np.flatnonzero(self.count)
        if len(full):
            place = np.arange(len(self.hashes)) - np.repeat(self.first[:-1][full], self.count[full])
            out[full] = mix(np.add.reduceat(self.hashes * powers(int(self.count.max()))[place], self.first[:-1][full]) + self.count[full].astype(np.uint64))
        return out.view(np.int64)

    def shingles(self) -> tuple[np.ndarray, np.ndarray]:
        """Hashes of all shingles, unit by unit, with repeats, and where each unit's begin. Units with fewer words have one."""
        h, n = self.hashes, len(self.hashes)
        each = np.where(self.count >= SHINGLE, self.count - SHINGLE + 1, np.minimum(self.count, 1))
        begins = np.concatenate([[0], np.cumsum(each)])
        if not begins[-1]:
            return np.zeros(0, np.uint64), begins
        rolled = np.zeros(n, np.uint64)
        for k in range(SHINGLE):
            rolled[: n - k] += h[k:] * _place[k] if k < n else np.uint64(0)
        rows = np.arange(begins[-1]) - np.repeat(begins[:-1], each) + np.repeat(self.first[:-1], each)
        out = mix(rolled[rows])
        for i in np.flatnonzero((self.count > 0) & (self.count < SHINGLE)):
            own = h[self.first[i] : self.first[i + 1]]
            out[begins[i]] = mix((own * _place[: len(own)]).sum(keepdims=True) + _place[SHINGLE : SHINGLE + 1] * np.uint64(len(own)))[0]
        return out, begins


def document_units(texts) -> Units:
    """Units of a pyarrow string array; null is empty."""
    import pyarrow as pa
    import pyarrow.compute as pc

    flat = pc.fill_null(texts, "").cast(pa.large_binary())
    offsets = np.frombuffer(flat.buffers()[1], np.int64)[flat.offset : flat.offset + len(flat) + 1]
    data = np.frombuffer(flat.buffers()[2] or b"", np.uint8)[offsets[0] : offsets[-1]]
    return Units(data, offsets - offsets[0])


def sorted_units(shingles: np.ndarray, begins: np.ndarray, chosen: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The shingles of the chosen units (none of them empty), sorted within each, where each unit's begin, and the numbers of distinct ones."""
    lengths = (begins[1:] - begins[:-1])[chosen]
    starts = np.cumsum(lengths) - lengths
    values = shingles[np.arange(int(lengths.sum())) + np.repeat(begins[:-1][chosen] - starts, lengths)]
    for a, b in zip(starts.tolist(), (starts + lengths).tolist()):
        values[a:b].sort()
    return values, starts, np.add.reduceat(first_of_equal(values, starts), starts, dtype=np.int64) if len(starts) else np.zeros(0, np.int64)


def first_of_equal(values: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """For sorted units: whether a value is the first of its kind in its unit."""
    first = np.ones(len(values), bool)
    first[1:] = values[1:] != values[:-1]
    first[starts] = True
    return first


def packed_bitmaps(values: np.ndarray, starts: np.ndarray, n: np.ndarray, chosen: np.ndarray):
    """A bitmap for each chosen unit, null for the others: one bit for each element by the first bits of
    its hash, in a width of two to four times the number of elements, at least 64."""
    import pyarrow as pa

    exponent = np.where(chosen, np.maximum(6, np.frexp(2.0 * n)[1]), 0).astype(np.int64)
    width = np.where(chosen, np.left_shift(1, exponent), 0)
    ends = np.cumsum(width)
    lengths = np.diff(np.append(starts, len(values)))
    held = np.repeat(chosen, lengths)
    shift = np.repeat(64 - exponent, lengths)[held].astype(np.uint64)
    bits = np.zeros(int(ends[-1]) if len(ends) else 0, bool)
    bits[np.repeat(ends - width, lengths)[held] + (values[held] >> shift).astype(np.int64)] = True
    offsets = np.concatenate([[0], ends // 8]).astype(np.int32)
    valid = np.packbits(chosen, bitorder="little").tobytes()
    return pa.Array.from_buffers(pa.binary(), len(chosen), [pa.py_buffer(valid), pa.py_buffer(offsets), pa.py_buffer(np.packbits(bits).tobytes())])


def shingle_set(text: str) -> np.ndarray:
    """The sorted distinct shingle hashes of one text."""
    data = np.frombuffer(text.encode(), np.uint8)
    return np.unique(Units(data, np.array([0, len(data)])).shingles()[0])
