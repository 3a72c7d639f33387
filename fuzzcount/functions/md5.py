"""The draws of `digest.num` for many texts at once: one block of md5 over NumPy arrays.

Texts are a prefix a row and a suffix a column.  Only the first word of the digest is drawn, so the last three
of its 64 steps are left out; texts that need more than one block go through `hashlib`.
"""

from __future__ import annotations

import hashlib
import math

import numpy as np

#: Fixed values of md5 (RFC 1321): shifts, sine table, start.
_SHIFTS = ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21))
_SINES = [int(abs(math.sin(i + 1)) * 2**32) for i in range(64)]
_START = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)
#: Bytes of one block beside the end mark and the length, and texts that are drawn in one go (arrays stay in the cache).
_FITS, _AT_ONCE = 55, 1 << 15


def _block(length: int, rows: np.ndarray, at: int) -> np.ndarray:
    out = np.zeros((len(rows), 64), np.uint8)
    out[:, at : at + length] = rows
    return out


def _mixed(kind: int, b: np.ndarray, c: np.ndarray, d: np.ndarray, out: np.ndarray | None) -> np.ndarray:
    if kind == 0:
        out = np.bitwise_xor(c, d, out=out)
        return np.bitwise_xor(np.bitwise_and(out, b, out=out), d, out=out)
    if kind == 1:
        out = np.bitwise_xor(b, c, out=out)
        return np.bitwise_xor(np.bitwise_and(out, d, out=out), c, out=out)
    if kind == 2:
        return np.bitwise_xor(np.bitwise_xor(b, c, out=out), d, out=out)
    return np.bitwise_xor(np.bitwise_or(np.invert(d, out=out), b, out=out), c, out=out)


def _first_word(words: list[np.ndarray | int], shape: tuple[int, int]) -> np.ndarray:
    """The first eight hex digits of the digests, as numbers; a word is a number or an array that broadcasts to `shape`."""
    a, b, c, d = (np.full(shape, v, np.uint32) for v in _START)
    mixed, high = np.empty(shape, np.uint32), np.empty(shape, np.uint32)
    for i in range(61):
        kind = i // 16
        word = words[(i, 5 * i + 1, 3 * i + 5, 7 * i)[kind] % 16]
        mixed = _mixed(kind, b, c, d, mixed)
        mixed += a
        if isinstance(word, int):
            mixed += np.uint32((word + _SINES[i]) & 0xFFFFFFFF)
        else:
            mixed += word
            mixed += np.uint32(_SINES[i])
        turn = _SHIFTS[kind][i % 4]
        np.right_shift(mixed, np.uint32(32 - turn), out=high)
        np.left_shift(mixed, np.uint32(turn), out=mixed)
        mixed |= high
        np.add(mixed, b, out=a)
        a, b, c, d = d, a, b, c
    return (b + np.uint32(_START[0])).byteswap()


def draws(prefixes: list[bytes], suffixes: list[bytes]) -> np.ndarray:
    """(prefixes, suffixes) numbers below 2^32: what `num` draws from each prefix followed by each suffix."""
    out = np.empty((len(prefixes), len(suffixes)), np.uint32)
    lengths, ends = np.fromiter(map(len, prefixes), np.int64, len(prefixes)), np.array([len(s) for s in suffixes])
    for long in np.unique(lengths):
        rows = np.flatnonzero(lengths == long)
        head = np.frombuffer(b"".join(prefixes[r] for r in rows), np.uint8).reshape(len(rows), long)
        for short in np.unique(ends):
            columns = np.flatnonzero(ends == short)
            size = int(long + short)
            if size > _FITS:
                for r in rows:
                    for c in columns:
                        out[r, c] = int(hashlib.md5(prefixes[r] + suffixes[c]).hexdigest()[:8], 16)
                continue
            tail = np.frombuffer(b"".join(suffixes[c] for c in columns), np.uint8).reshape(len(columns), short)
            tails = _block(short, tail, long)
            tails[:, size] = 0x80
            tails[:, 56:58] = size * 8 & 255, size * 8 >> 8
            tails = tails.view("<u4")
            same = (tails == tails[0]).all(0)
            few = max(1, _AT_ONCE // len(columns))
            for first in range(0, len(rows), few):
                part = slice(first, first + few)
                heads = _block(long, head[part], 0).view("<u4")
                words = []
                for w in range(16):
                    own = heads[:, w : w + 1] if 4 * w < long else None
                    tail = int(tails[0, w]) if same[w] else tails[None, :, w]
                    words.append(tail if own is None else own | tail if not same[w] else own | np.uint32(tail))
                out[np.ix_(rows[part], columns)] = _first_word(words, (len(heads), len(columns)))
    return out
