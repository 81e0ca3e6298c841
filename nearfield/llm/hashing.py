"""Vectorised hashing of words and word shingles, and min-wise signatures of shingle sets."""

from __future__ import annotations

from functools import lru_cache

import numpy as np

_U = np.uint64
_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_ODD = 0x9E3779B97F4A7C15
_BASE = 0xD6E8FEB86659FD93
_INVERSE = pow(_BASE, -1, 2**64)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection on 64 bits that spreads every input bit (a public multiply-xor-shift finaliser)."""
    x = x ^ (x >> _U(32))
    x = x * _U(0xD6E8FEB86659FD93)
    x = x ^ (x >> _U(32))
    x = x * _U(0xC2B2AE3D27D4EB4F)
    return x ^ (x >> _U(29))


#: Bytes that are hashed at a time, and how far before that a place to cut is sought.
PIECE, BACK = 1 << 18, 1 << 14


@lru_cache(maxsize=1)
def _powers(size: int) -> tuple[np.ndarray, np.ndarray]:
    out = []
    for base in (_BASE, _INVERSE):
        p = np.full(size, base, _U)
        p[0] = 1
        out.append(np.multiply.accumulate(p))
    return out[0], out[1]


def _cuts(a: np.ndarray) -> list[int]:
    """Ends of the pieces: behind white space where there is some near, so that only long words are cut."""
    ends, at = [], 0
    while at < len(a):
        end = min(at + PIECE, len(a))
        if end < len(a):
            space = np.flatnonzero(_SPACE[a[max(at, end - BACK) : end]])
            end = max(at, end - BACK) + int(space[-1]) + 1 if space.size else end
        ends.append(end)
        at = end
    return ends


def word_hashes(data: bytes, prefixes: tuple[int, ...] = ()) -> np.ndarray:
    """A 64-bit hash for each run of non-space bytes, in order; after them those of longer words' first bytes.

    A long text is taken in pieces, so what is held beside it does not grow with it but for the hashes.
    """
    a = np.frombuffer(data, np.uint8)
    words: list[np.ndarray] = []
    firsts: list[list[np.ndarray]] = [[] for _ in prefixes]
    value, length = 0, 0  # of a word that the last piece did not end
    at = 0
    for end in _cuts(a):
        piece = a[at:end]
        inside = np.zeros(piece.size + 2, np.int8)
        inside[1:-1] = ~_SPACE[piece]
        turns = np.flatnonzero(np.diff(inside))
        starts, ends = turns[::2], turns[1::2]
        power, inverse = _powers(PIECE + 1)
        total = np.zeros(piece.size + 1, _U)
        np.cumsum((piece.astype(_U) + _U(1)) * power[: piece.size], out=total[1:])
        sums, lengths = (total[ends] - total[starts]) * inverse[starts], (ends - starts).astype(_U)
        fresh = np.ones(starts.size, bool)
        if length:
            if starts.size and starts[0] == 0:
                sums[0] = _U((value + int(sums[0]) * pow(_BASE, length, 2**64)) % 2**64)
                lengths[0] += _U(length)
                fresh[0] = False
            else:
                words.append(mix(np.array([(value + length) % 2**64], _U)))
        for found, k in zip(firsts, prefixes, strict=True):
            first = starts[fresh & (ends - starts > k)]
            found.append(mix((total[first + k] - total[first]) * inverse[first] - _U(k)))
        value, length = 0, 0
        if end < len(a) and ends.size and ends[-1] == piece.size:  # goes on in the next piece
            value, length = int(sums[-1]), int(lengths[-1])
            sums, lengths = sums[:-1], lengths[:-1]
        words.append(mix(sums + lengths))
        at = end
    out = words + [x for found in firsts for x in found]
    return np.concatenate(out) if len(out) > 1 else out[0] if out else np.zeros(0, _U)


def shingle_set(text: str | None, k: int) -> np.ndarray:
    """Sorted distinct 64-bit hashes of a text's k-word shingles, A-Z lower-cased.

    With fewer words than k, the whole sequence is the one shingle; without words the set is empty.
    """
    words = word_hashes((text or "").encode("utf-8", "surrogatepass").lower())
    n = words.size
    if not n:
        return words
    width = min(k, n)
    out = np.full(n - width + 1, width, _U)
    for i in range(width):
        out = out * _U(_ODD) + words[i : n - width + 1 + i]
    return np.unique(mix(out))


class MinHasher:
    """``size`` universal hash functions over 32-bit values; the least value under each is the signature."""

    def __init__(self, size: int, seed: int = 1):
        draw = np.random.default_rng(seed)
        self.size = size
        self.a = (draw.integers(0, 2**31, size, dtype=np.uint32) * np.uint32(2) + np.uint32(1))[:, None]
        self.b = draw.integers(0, 2**32, size, dtype=np.uint32)[:, None]

    def signature(self, shingles: np.ndarray) -> np.ndarray:
        """uint32 array; of an empty set, all ones in every bit."""
        if not shingles.size:
            return np.full(self.size, 2**32 - 1, np.uint32)
        x = (shingles >> _U(32)).astype(np.uint32)
        out = np.full(self.size, 2**32 - 1, np.uint32)
        for at in range(0, x.size, 1024):
            np.minimum(out, (self.a * x[None, at : at + 1024] + self.b).min(axis=1), out=out)
        return out


def band_keys(signature: np.ndarray, rows: int) -> np.ndarray:
    """One signed 64-bit key for each band of ``rows`` signature values; the band's number is part of the key."""
    bands = signature.reshape(-1, rows).astype(_U)
    key = np.arange(1, len(bands) + 1, dtype=_U) * _U(_ODD)
    for i in range(rows):
        key = mix(key * _U(_BASE) + bands[:, i])
    return key.view(np.int64)
