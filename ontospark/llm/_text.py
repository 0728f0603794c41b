"""Words, word hashes and shingles of raw UTF-8 bytes, vectorised with numpy.

A word is a maximal run of bytes outside {0x20, 0x09-0x0D}. Hashes are 64-bit: a polynomial
over bytes (odd multiplier, modulo 2^64) followed by a full-avalanche finaliser.
"""

from __future__ import annotations

import numpy as np

SEPARATOR = np.zeros(256, bool)
SEPARATOR[[9, 10, 11, 12, 13, 32]] = True
LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
_BASE = 0x9E3779B97F4A7C15
_INVERSE = pow(_BASE, -1, 1 << 64)
PIECE = 1 << 22
_GAPS = SEPARATOR.astype(np.uint8).tobytes()
_powers = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit values in which each input bit moves every output bit."""
    x = x ^ (x >> np.uint64(30))
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def _grow(n: int) -> None:
    while len(_powers[0]) < n:
        have = len(_powers[0])
        for k, base in enumerate((_BASE, _INVERSE)):
            step = np.uint64(pow(base, have, 1 << 64))
            _powers[k] = np.concatenate([_powers[k], _powers[k] * step])


def spans(raw: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The bytes as an array, and where each word starts and ends."""
    b = np.frombuffer(raw, np.uint8)
    gap = np.ones(len(b) + 2, np.int8)
    gap[1:-1] = SEPARATOR[b]
    turn = np.diff(gap)
    return b, np.flatnonzero(turn == -1), np.flatnonzero(turn == 1)


def spans_of(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """spans() of all texts, joined by one separator, and the number of each text's words."""
    raw = b"\n".join(texts)
    gap = np.frombuffer(b"\1" + raw.translate(_GAPS) + b"\1", np.uint8)
    turn = np.flatnonzero(gap[1:] != gap[:-1])
    starts, ends = turn[::2].copy(), turn[1::2].copy()
    stops = np.cumsum([len(x) + 1 for x in texts], dtype=np.int64) - 1
    return np.frombuffer(raw, np.uint8), starts, ends, np.diff(np.searchsorted(starts, stops), prepend=0)


def _hash_piece(b: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    _grow(len(b) + 1)
    total = np.zeros(len(b) + 1, np.uint64)
    np.cumsum((b + np.uint64(1)) * _powers[0][: len(b)], out=total[1:])
    h = (total[ends] - total[starts]) * _powers[1][starts]
    return mix(h ^ (ends - starts).astype(np.uint64))


def word_hashes(b: np.ndarray, starts: np.ndarray, ends: np.ndarray, piece: int = PIECE) -> np.ndarray:
    """One 64-bit hash for each word; long texts are cut between words, so memory stays bounded."""
    if len(b) <= piece:
        return _hash_piece(b, starts, ends)
    out, lo = [], 0
    while lo < len(starts):
        base = starts[lo]
        hi = max(lo + 1, int(np.searchsorted(ends, base + piece, "right")))
        out.append(_hash_piece(b[base : ends[hi - 1]], starts[lo:hi] - base, ends[lo:hi] - base))
        lo = hi
    return np.concatenate(out) if out else np.zeros(0, np.uint64)


def hashed_words(raw: bytes) -> np.ndarray:
    return word_hashes(*spans(raw))


def grams(h: np.ndarray, n: int, seed: int = 0x2545F4914F6CDD1D) -> np.ndarray:
    """Hash of every run of n words, by doubling; empty if there are fewer words."""
    if len(h) < n:
        return np.zeros(0, np.uint64)
    out, width, block, left = None, 1, h, n
    done = 0
    while left:
        if left & 1:
            shift = np.uint64(pow(seed, done, 1 << 64))
            part = block[done : done + len(h) - n + 1] * shift
            out = part if out is None else out + part
            done += width
        left >>= 1
        if left:
            block = block[:-width] + block[width:] * np.uint64(pow(seed, width, 1 << 64))
            width *= 2
    return mix(out)


def shingle_set(raw: bytes, n: int) -> np.ndarray:
    """Sorted distinct n-word shingles; with fewer words the whole sequence is the only one; no word, no shingle."""
    h = hashed_words(raw)
    if not len(h):
        return h
    return np.unique(grams(h, min(n, len(h))) + np.uint64(min(n, len(h))))


def sliding_min(x: np.ndarray, width: int) -> np.ndarray:
    """Least value of each window, by doubling."""
    have = 1
    while have * 2 <= width:
        x = np.minimum(x[:-have], x[have:])
        have *= 2
    return np.minimum(x[: len(x) - (width - have)], x[width - have :]) if width > have else x
