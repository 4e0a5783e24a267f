"""The package's md5 prefixes over whole arrays: equal to `h60` of texts that join a word, a small number and an integer by #."""

from __future__ import annotations

import hashlib
import math

import numpy as np

SHIFTS = np.repeat([[7, 12, 17, 22], [5, 9, 14, 20], [4, 11, 16, 23], [6, 10, 15, 21]], 4, axis=0).reshape(4, 4, 4)[:, 0, :]
SINES = [int(abs(math.sin(i + 1)) * 2**32) for i in range(64)]
START = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)
POWERS = np.array([10**i for i in range(1, 20)], np.uint64)
#: Texts hashed at a time, so that all numbers of a step stay in a core's cache; fewer than the second are hashed one by one.
STEP, FEW = 1 << 14, 1 << 9


def _compress(block: np.ndarray, used: int) -> tuple[np.ndarray, np.ndarray]:
    """The first two words of the md5 of texts of one block each; block: (16, n) words, of which those from `used` to the length are zero."""
    n = block.shape[1]
    a, b, c, d = (np.full(n, s, np.uint32) for s in START)
    f, t = np.empty(n, np.uint32), np.empty(n, np.uint32)
    for i in range(64):
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
        np.add(f, np.uint32(SINES[i]), out=f)
        if g < used or g == 14:
            np.add(f, block[g], out=f)
        s = int(SHIFTS[turn, i % 4])
        np.left_shift(f, np.uint32(s), out=t)
        np.right_shift(f, np.uint32(32 - s), out=f)
        np.bitwise_or(f, t, out=f)
        np.add(f, b, out=f)
        # the oldest number's array takes the next result
        a, d, c, b, f = d, c, b, f, a
    return a + np.uint32(START[0]), b + np.uint32(START[1])


def _words(word: bytes, level: np.ndarray, size: int, negative: bool, whole: np.ndarray, digits: int) -> tuple[np.ndarray, int]:
    """(words, length) of the texts word#level#number with their closing bit: levels of `size` digits, numbers of `digits` digits, given without their sign."""
    at = len(word) + 1
    length = at + size + 1 + negative + digits
    used = length // 4 + 1
    text = np.zeros((4 * used, len(whole)), np.uint8)
    text[:at] = np.frombuffer(word + b"#", np.uint8)[:, None]
    for i in range(size):
        text[at + i] = level // 10 ** (size - 1 - i) % 10 + 48
    text[at + size] = ord("#")
    if negative:
        text[at + size + 1] = ord("-")
    for i in range(length - 1, length - 1 - digits, -1):
        rest = whole // np.uint64(10)
        text[i] = whole - rest * np.uint64(10)
        text[i] += 48
        whole = rest
    text[length] = 0x80
    return np.stack([np.ascontiguousarray(text[4 * w : 4 * w + 4].T).view("<u4").ravel() for w in range(used)]), length


def h60_numbers(word: str, level: np.ndarray, number: np.ndarray) -> np.ndarray:
    """The first 60 bits of the md5 of word#level#number for each pair of a level (0 or more) and a signed number of 64 bits."""
    name, out = word.encode(), np.empty(len(number), np.int64)
    level = np.asarray(level, np.int64)
    for start in range(0, len(number), STEP):
        v, x = level[start : start + STEP], number[start : start + STEP]
        sizes = np.searchsorted(POWERS, v.view(np.uint64), side="right") + 1
        # a text of one block has 55 bytes at most
        if len(x) < FEW or len(name) + int(sizes.max()) + 22 > 55:
            out[start : start + STEP] = [int(hashlib.md5(b"%s#%d#%d" % (name, i, j)).hexdigest()[:15], 16) for i, j in zip(v.tolist(), x.tolist(), strict=True)]
            continue
        whole = np.abs(x).view(np.uint64)
        kind = (sizes * 2 + (x < 0)) * 32 + np.searchsorted(POWERS, whole, side="right") + 1
        block, used = np.zeros((16, len(x)), np.uint32), 0
        for k in np.unique(kind).tolist():
            pick = np.flatnonzero(kind == k)
            words, length = _words(name, v[pick], k >> 6, bool(k >> 5 & 1), whole[pick], k & 31)
            block[: len(words), pick] = words
            block[14, pick] = 8 * length
            used = max(used, len(words))
        first, second = _compress(block, used)
        # the text's first 15 hexadecimal digits, read from the left
        out[start : start + STEP] = (first.byteswap().astype(np.int64) << 28) | (second.byteswap() >> np.uint32(4)).astype(np.int64)
    return out
