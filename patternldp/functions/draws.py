"""The draws of ``noise`` in numpy, many at once: md5 of short keys with one 32-bit lane for each key."""

from __future__ import annotations

import hashlib
import math

import numpy as np

TWO_52 = float(2**52)
_SHIFTS = ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21))
_SINES = [int(abs(math.sin(i + 1)) * 2**32) for i in range(64)]
LANES = 1 << 14  # keys done together, so that the lanes stay in the cache
LONGEST = 55  # bytes of a key that fit one block


def _md5_head(words: list[np.ndarray | int], n: int) -> np.ndarray:
    """The first 52 bits of md5 of ``n`` blocks; each of the 16 ``words`` is an array in uint32, or one number for all."""
    a0, b0 = np.uint32(0x67452301), np.uint32(0xEFCDAB89)
    a, b, c, d = (np.full(n, x, np.uint32) for x in (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476))
    f, high = np.empty(n, np.uint32), np.empty(n, np.uint32)
    for i in range(64):
        r = i // 16
        if r == 0:
            np.bitwise_xor(c, d, out=f)
            f &= b
            f ^= d
            g = i
        elif r == 1:
            np.bitwise_xor(b, c, out=f)
            f &= d
            f ^= c
            g = (5 * i + 1) % 16
        elif r == 2:
            np.bitwise_xor(b, c, out=f)
            f ^= d
            g = (3 * i + 5) % 16
        else:
            np.invert(d, out=f)
            f |= b
            f ^= c
            g = 7 * i % 16
        f += a
        word = words[g]
        if isinstance(word, np.ndarray):
            f += word
            f += np.uint32(_SINES[i])
        else:
            f += np.uint32((_SINES[i] + word) % 2**32)
        s = _SHIFTS[r][i % 4]
        np.left_shift(f, np.uint32(s), out=high)
        f >>= np.uint32(32 - s)
        f |= high
        f += b
        a, d, c, b, f = d, c, b, f, a
    # The digest is little-endian, its hexadecimal text is read from the first byte on.
    return ((a + a0).byteswap().astype(np.uint64) << np.uint64(20)) | ((b + b0).byteswap().astype(np.uint64) >> np.uint64(12))


def _width(x: np.ndarray) -> np.ndarray:
    return np.searchsorted(10 ** np.arange(1, 19, dtype=np.int64), x, side="right") + 1


def hashed(*key: str | int | np.ndarray) -> np.ndarray:
    """``noise.hashed`` of keys whose parts are constants or arrays (of one length) of whole numbers from 0."""
    arrays = [np.asarray(p, np.int64) for p in key if isinstance(p, np.ndarray)]
    if any((x < 0).any() for x in arrays):
        raise ValueError("numbers in keys must not be negative")
    out = np.empty(len(arrays[0]), np.int64)
    for lo in range(0, len(out), 16 * LANES):
        _by_shape(key, [x[lo : lo + 16 * LANES] for x in arrays], out[lo : lo + 16 * LANES])
    return out


def _by_shape(key: tuple, arrays: list[np.ndarray], out: np.ndarray) -> None:
    """Keys of one length are done together."""
    widths = [_width(x) for x in arrays]
    shape = sum(w * 32**i for i, w in enumerate(widths))
    kinds = np.unique(shape).tolist()
    for s in kinds:
        own = slice(None) if len(kinds) == 1 else np.flatnonzero(shape == s)
        parts = [x[own] for x in arrays]
        got = np.empty(len(parts[0]), np.int64)
        for lo in range(0, len(got), LANES):
            got[lo : lo + LANES] = _one_shape(key, [x[lo : lo + LANES] for x in parts], [s // 32**i % 32 for i in range(len(arrays))])
        out[own] = got


def hashed_any(seeds: np.ndarray, purpose: str, ids: np.ndarray) -> np.ndarray:
    """``hashed(seeds, purpose, ids)`` one by one, for negative numbers."""
    return np.array([int(hashlib.md5(f"{s}:{purpose}:{i}".encode()).hexdigest()[:13], 16) for s, i in zip(seeds.tolist(), ids.tolist())], np.int64)


def _one_shape(key: tuple, arrays: list[np.ndarray], widths: list[int]) -> np.ndarray:
    n, rest = len(arrays[0]), iter(zip(arrays, widths))
    fixed, digits, at = bytearray(64), [], 0
    for i, p in enumerate(key):
        if i:
            fixed[at : at + 1] = b":"
            at += 1
        if isinstance(p, np.ndarray):
            x, width = next(rest)
            digits.append((x.astype(np.uint32) if width < 10 else x.astype(np.uint64), at, width))
            at += width
        else:
            text = str(p).encode()
            fixed[at : at + len(text)] = text
            at += len(text)
        if at > LONGEST:
            raise ValueError(f"a key of {at} bytes and more is longer than a block")
    fixed[at] = 128
    fixed[56:58] = (8 * at).to_bytes(2, "little")
    words: list[np.ndarray | int] = [int.from_bytes(fixed[4 * i : 4 * i + 4], "little") for i in range(16)]
    for x, start, width in digits:
        ten = x.dtype.type(10)
        for j in range(start + width - 1, start - 1, -1):
            tens = x // ten
            digit = (x - tens * ten).astype(np.uint32, copy=False)
            digit += np.uint32(48)
            digit <<= np.uint32(8 * (j % 4))
            word = words[j // 4]
            words[j // 4] = np.bitwise_or(digit, word, out=digit) if isinstance(word, np.ndarray) else np.bitwise_or(digit, np.uint32(word), out=digit)
            x = tens
    return _md5_head(words, n).astype(np.int64)


def uniform(*key: str | int | np.ndarray) -> np.ndarray:
    """In (0, 1), the same as ``noise.uniform``."""
    return (hashed(*key).astype(np.float64) + 0.5) / TWO_52
