"""MD5 of short texts, many at once."""

from __future__ import annotations

import math
from collections.abc import Callable

import numpy as np

ROUND_ADDS = [int(abs(math.sin(i + 1)) * 2**32) & 0xFFFFFFFF for i in range(64)]
ROUND_TURNS = [7, 12, 17, 22] * 4 + [5, 9, 14, 20] * 4 + [4, 11, 16, 23] * 4 + [6, 10, 15, 21] * 4
START = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)


def digester() -> tuple[Callable, Callable]:
    """``padded`` and ``first``, as closures, so that Python workers need no package of ours.

    ``padded(values, room)`` makes the text of each whole number, ``room`` bytes in, a padded block: (words, lengths).
    ``first(prefix, words, lengths)`` puts a prefix of ``room`` bytes there and gives the first 32 bits of each digest.
    Texts of up to 55 bytes.
    """

    def padded(values, room):
        import pyarrow as pa

        texts = pa.array(values, pa.int64()).cast(pa.string())
        _, offsets, data = texts.buffers()
        at = np.frombuffer(offsets, np.int32)[: len(texts) + 1]
        sizes, data = np.diff(at), np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(1, np.uint8)
        longest = int(sizes.max(initial=0))
        block = np.zeros((len(texts), -(-(room + longest + 1) // 4) * 4), np.uint8)
        for j in range(longest + 1):
            block[:, room + j] = np.where(j < sizes, data[np.minimum(at[:-1] + j, len(data) - 1)], np.where(j == sizes, 128, 0))
        return [np.ascontiguousarray(w) for w in block.view("<u4").T], ((sizes + room) * 8).astype(np.uint32)

    def first(prefix, words, lengths):
        head = np.frombuffer(prefix + b"\0" * (-len(prefix) % 4), "<u4")
        whole = len(prefix) // 4
        message = [int(h) if i < whole else words[i] | h for i, h in enumerate(head)] + words[len(head) :]
        message += [0] * (14 - len(message)) + [lengths, 0]
        a, b, c, d = (np.full(len(lengths), v, np.uint32) for v in START)
        f, turned = np.empty_like(a), np.empty_like(a)
        # The last three of 64 steps do not touch the first word.
        for i in range(61):
            if i < 16:
                np.bitwise_xor(c, d, out=f), np.bitwise_and(f, b, out=f), np.bitwise_xor(f, d, out=f)
                word = message[i]
            elif i < 32:
                np.bitwise_xor(b, c, out=f), np.bitwise_and(f, d, out=f), np.bitwise_xor(f, c, out=f)
                word = message[(5 * i + 1) % 16]
            elif i < 48:
                np.bitwise_xor(b, c, out=f), np.bitwise_xor(f, d, out=f)
                word = message[(3 * i + 5) % 16]
            else:
                np.invert(d, out=f), np.bitwise_or(f, b, out=f), np.bitwise_xor(f, c, out=f)
                word = message[7 * i % 16]
            np.add(a, f, out=a)
            if isinstance(word, int):
                np.add(a, np.uint32((word + ROUND_ADDS[i]) & 0xFFFFFFFF), out=a)
            else:
                np.add(a, word, out=a), np.add(a, np.uint32(ROUND_ADDS[i]), out=a)
            np.left_shift(a, np.uint32(ROUND_TURNS[i]), out=turned), np.right_shift(a, np.uint32(32 - ROUND_TURNS[i]), out=a)
            np.bitwise_or(a, turned, out=a), np.add(a, b, out=a)
            a, b, c, d = d, a, b, c
        return (b + np.uint32(START[0])).byteswap()

    return padded, first
