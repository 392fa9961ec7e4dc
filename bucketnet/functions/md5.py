"""The first four bytes of md5 for many short texts at once: h32 inside a task."""

from __future__ import annotations

import hashlib

import numpy as np

SHIFTS = ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21))
SINES = (np.abs(np.sin(np.arange(1, 65))) * 2**32).astype(np.uint64).astype(np.uint32)
START = tuple(map(np.uint32, (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)))
SHORT = 55  # bytes of a text that is one block
CHUNK = 4096


def _one_block(m: np.ndarray) -> np.ndarray:
    """The first word of the digest of padded blocks: m has 16 rows of words, a column a block."""
    n = m.shape[1]
    a, b, c, d = (np.full(n, x) for x in START)
    f, t = np.empty(n, np.uint32), np.empty(n, np.uint32)
    for i in range(61):  # the last three steps don't reach the first word
        turn = i // 16
        if turn == 0:
            np.bitwise_xor(c, d, out=f)
            np.bitwise_and(f, b, out=f)
            np.bitwise_xor(f, d, out=f)
            g = i
        elif turn == 1:
            np.bitwise_xor(b, c, out=f)
            np.bitwise_and(f, d, out=f)
            np.bitwise_xor(f, c, out=f)
            g = (5 * i + 1) % 16
        elif turn == 2:
            np.bitwise_xor(b, c, out=f)
            np.bitwise_xor(f, d, out=f)
            g = (3 * i + 5) % 16
        else:
            np.invert(d, out=f)
            np.bitwise_or(f, b, out=f)
            np.bitwise_xor(f, c, out=f)
            g = 7 * i % 16
        np.add(f, a, out=f)
        np.add(f, SINES[i], out=f)
        np.add(f, m[g], out=f)
        s = SHIFTS[turn][i % 4]
        np.left_shift(f, np.uint32(s), out=t)
        np.right_shift(f, np.uint32(32 - s), out=f)
        np.bitwise_or(f, t, out=f)
        np.add(f, b, out=a)  # a's place is free: it is the new b
        a, b, c, d = d, a, b, c
    return b + START[0]


def h32_many(data: np.ndarray, at: np.ndarray, size: np.ndarray, prefix: np.ndarray | None = None) -> np.ndarray:
    """h32 (uint32) of data[at : at + size] for each of at, size, behind its row of prefix; data and prefix are bytes as uint8."""
    out, p = np.empty(len(at), np.uint32), 0 if prefix is None else prefix.shape[1]
    room = SHORT - p
    long = np.flatnonzero(size > room)
    for lo in range(0, len(at) if room >= 0 else 0, CHUNK):
        a, n = at[lo : lo + CHUNK], np.minimum(size[lo : lo + CHUNK], room)
        m, width = np.zeros((len(a), 64), np.uint8), int(n.max(initial=0))
        if p:
            m[:, :p] = prefix[lo : lo + CHUNK]
        if width:
            places = np.arange(width)
            m[:, p : p + width] = np.where(places < n[:, None], data[np.minimum(a[:, None] + places, len(data) - 1)], 0)
        m[np.arange(len(a)), p + n] = 0x80
        words = np.ascontiguousarray(m.view("<u4").T)
        words[14] = 8 * (p + n)
        out[lo : lo + CHUNK] = _one_block(words).byteswap()
    for i in long:
        out[i] = int.from_bytes(hashlib.md5((prefix[i].tobytes() if p else b"") + data[at[i] : at[i] + size[i]].tobytes()).digest()[:4], "big")
    return out
