"""Words, lines and hashed word windows of many texts at once, on UTF-8 bytes with numpy.

A word is a maximal run of bytes outside 0x20 and 0x09-0x0D, which for UTF-8 equals the pattern
``[^\\x20\\x09-\\x0D]+`` on characters.  Hashes are 64-bit; equality of two windows means equality of hashes.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np

PIECE = 1 << 20

_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_BYTE = np.random.default_rng(20240229).integers(1, 2**63, 256, dtype=np.int64).astype(np.uint64) | np.uint64(1)
_R = np.uint64(0x9E3779B97F4A7C15)
_R_INV = np.uint64(pow(0x9E3779B97F4A7C15, -1, 2**64))
_M1, _M2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
_powers: dict[str, np.ndarray] = {}


def _power(base: np.uint64, name: str, n: int) -> np.ndarray:
    have = _powers.get(name)
    if have is None or len(have) < n:
        size = max(n, PIECE + 4096)
        steps = np.full(size, base, np.uint64)
        steps[0] = 1
        have = np.cumprod(steps, dtype=np.uint64)
        if size <= 4 * PIECE:
            _powers[name] = have
    return have[:n]


def mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(30))) * _M1
    h = (h ^ (h >> np.uint64(27))) * _M2
    return h ^ (h >> np.uint64(31))


def _hash_piece(b: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    gap = _SPACE[b]
    edge = np.flatnonzero(np.diff(np.concatenate(([True], gap, [True])).astype(np.int8)))
    start, end = edge[0::2], edge[1::2]
    total = np.zeros(len(b) + 1, np.uint64)
    np.cumsum(_BYTE[b] * _power(_R, "up", len(b)), out=total[1:])
    h = (total[end] - total[start]) * _power(_R_INV, "down", len(b) + 1)[start]
    return mix(h + (end - start).astype(np.uint64)), start, end


def word_hashes(blob: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hash and start of each word of a byte array, in order; works in pieces so that memory stays bounded."""
    if not len(blob):
        return np.empty(0, np.uint64), np.empty(0, np.int64)
    hs, starts, at = [], [], 0
    while at < len(blob):
        to = min(len(blob), at + PIECE)
        while to < len(blob) and not _SPACE[blob[to - 1]]:
            more = np.flatnonzero(_SPACE[blob[to : to + PIECE]])
            to = to + int(more[0]) + 1 if len(more) else min(len(blob), to + PIECE)
        h, s, _ = _hash_piece(blob[at:to])
        hs.append(h)
        starts.append(s + at)
        at = to
    return np.concatenate(hs), np.concatenate(starts)


def chunks(texts: Sequence[str | None], limit: int = PIECE) -> Iterator[tuple[int, int]]:
    """Row ranges of about ``limit`` characters; a longer text stands alone."""
    lo = size = 0
    for i, t in enumerate(texts):
        n = len(t) if t else 0
        if size and size + n > limit:
            yield lo, i
            lo, size = i, 0
        size += n + 1
    if lo < len(texts):
        yield lo, len(texts)


@dataclass
class Words:
    blob: np.ndarray  # the texts' bytes, each followed by a line feed
    begin: np.ndarray  # where each text begins; one more at the end
    hash: np.ndarray  # of each word
    first: np.ndarray  # index of each text's first word; one more at the end

    @property
    def count(self) -> np.ndarray:
        return np.diff(self.first)

    def per_text(self, flags: np.ndarray) -> np.ndarray:
        total = np.zeros(len(flags) + 1, np.int64)
        np.cumsum(flags, out=total[1:])
        return total[self.begin[1:]] - total[self.begin[:-1]]


def split(texts: Sequence[str | None], lower: bool = False) -> Words:
    enc = [t.encode("utf-8", "surrogatepass") if t else b"" for t in texts]
    begin = np.zeros(len(enc) + 1, np.int64)
    np.cumsum([len(e) + 1 for e in enc], out=begin[1:])
    blob = np.frombuffer(b"\n".join(enc) + b"\n", np.uint8)
    if lower:
        blob = _LOWER[blob]
    h, start = word_hashes(blob)
    return Words(blob, begin, h, np.searchsorted(start, begin))


def windows(words: Words, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hash of each window of ``k`` words that lies within one text, and the index of its first window by text."""
    n = len(words.hash)
    count = np.maximum(words.count - (k - 1), 0)
    first = np.zeros(len(count) + 1, np.int64)
    np.cumsum(count, out=first[1:])
    if n < k:
        return np.empty(0, np.uint64), first
    h = np.zeros(n - k + 1, np.uint64)
    for j in range(k):
        h = h * _R + words.hash[j : n - k + 1 + j]
    h = mix(h + np.uint64(k))
    at = np.repeat(words.first[:-1] - first[:-1], count) + np.arange(first[-1])
    return h[at], first


def shingle_sets(texts: Sequence[str | None], k: int, lower: bool = True) -> list[np.ndarray]:
    """Sorted distinct hashes of the ``k``-word shingles of each text; fewer words form one shingle, none an empty set."""
    words = split(texts, lower)
    h, first = windows(words, k)
    out = []
    for i, n in enumerate(words.count):
        if n >= k:
            s = np.sort(h[first[i] : first[i + 1]])
            out.append(s[np.concatenate(([True], s[1:] != s[:-1]))])
        elif n:
            v = np.zeros(1, np.uint64)
            for w in words.hash[words.first[i] : words.first[i + 1]]:
                v = v * _R + w
            out.append(mix(v + np.uint64(n)))
        else:
            out.append(np.empty(0, np.uint64))
    return out
