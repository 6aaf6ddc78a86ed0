"""md5 of very many short texts at once: the 52 upper bits of the digests, as sets.md5_number takes them."""

from __future__ import annotations

import hashlib
import math

import numpy as np

#: Texts that are worked on at a time (their words stay in a core's cache), and bytes up to which a text is one block.
LANES, ONE_BLOCK = 16_384, 55
_ADD = [int(abs(math.sin(i + 1)) * 2**32) for i in range(64)]
_TURN = [(7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)]
_FROM = [lambda i: i, lambda i: (5 * i + 1) % 16, lambda i: (3 * i + 5) % 16, lambda i: 7 * i % 16]
_BEGIN = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)


def upper_bits(words: list[np.ndarray | int]) -> np.ndarray:
    """The upper 52 bits of the digests of one padded block each: 16 words, arrays of one length or a number that all have."""
    n = max(len(w) for w in words if isinstance(w, np.ndarray))
    a, b, c, d = (np.full(n, x, np.uint32) for x in _BEGIN)
    f, t = np.empty(n, np.uint32), np.empty(n, np.uint32)
    for i in range(64):
        kind = i >> 4
        if kind == 0:
            np.bitwise_xor(c, d, out=f)
            np.bitwise_and(f, b, out=f)
            np.bitwise_xor(f, d, out=f)
        elif kind == 1:
            np.bitwise_xor(b, c, out=f)
            np.bitwise_and(f, d, out=f)
            np.bitwise_xor(f, c, out=f)
        elif kind == 2:
            np.bitwise_xor(b, c, out=f)
            np.bitwise_xor(f, d, out=f)
        else:
            np.invert(d, out=f)
            np.bitwise_or(f, b, out=f)
            np.bitwise_xor(f, c, out=f)
        np.add(f, a, out=f)
        word = words[_FROM[kind](i)]
        if isinstance(word, np.ndarray):
            np.add(f, word, out=f)
            word = 0
        np.add(f, np.uint32((_ADD[i] + int(word)) & 0xFFFFFFFF), out=f)
        turn = _TURN[kind][i & 3]
        np.left_shift(f, np.uint32(turn), out=t)
        np.right_shift(f, np.uint32(32 - turn), out=f)
        np.bitwise_or(f, t, out=f)
        np.add(f, b, out=f)
        a, b, c, d, f = d, f, b, c, a
    a += np.uint32(_BEGIN[0])
    b += np.uint32(_BEGIN[1])
    # The digest begins with a and b, lowest byte first.
    return (a.byteswap().astype(np.int64) << 20) | (b.byteswap() >> np.uint32(12)).astype(np.int64)


def md5_upper(texts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Upper 52 bits of md5 of texts of ONE_BLOCK bytes at most: rows of 64 bytes, of which the first sizes[i] count."""
    return md5_slices(texts.ravel(), 64 * np.arange(len(texts)), sizes)


def md5_slices(data: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Upper 52 bits of md5 of the slices of some bytes."""
    out, data = np.empty(len(starts), np.int64), np.concatenate([data, np.zeros(64, np.uint8)])
    for i in np.nonzero(sizes > ONE_BLOCK)[0].tolist():
        out[i] = md5_upper_one(data[starts[i] : starts[i] + sizes[i]].tobytes())
    short = np.nonzero(sizes <= ONE_BLOCK)[0]
    for at in range(0, len(short), LANES):
        some = short[at : at + LANES]
        size = sizes[some]
        width = 4 * (int(size.max()) // 4 + 1)
        rows = np.lib.stride_tricks.sliding_window_view(data, width)[starts[some]]
        rows *= np.arange(width, dtype=np.uint8) < size.astype(np.uint8)[:, None]
        rows[np.arange(len(rows)), size] = 0x80
        words = np.ascontiguousarray(rows.view("<u4").T)
        out[some] = upper_bits([*words, *[0] * (14 - len(words)), (8 * size).astype(np.uint32), 0])
    return out


def md5_upper_one(text: bytes) -> int:
    return int.from_bytes(hashlib.md5(text).digest()[:8], "big") >> 12
