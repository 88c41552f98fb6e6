"""Word-shingle sets of texts as 64-bit hashes, computed over whole Arrow batches of bytes with NumPy.

A-Z are lower-cased; words are runs of bytes other than ASCII white space; a shingle is five words in a row, or the whole sequence of a text with
fewer words. A word's hash chains its bytes, eight at a time, through a bijection of 64-bit numbers (words above LONG bytes: a cryptographic digest), so that no pattern of
letters makes words collide but by chance; a shingle's is a polynomial in its words' hashes, scrambled.
"""

from __future__ import annotations

import hashlib

import numpy as np

LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32  # A-Z as a-z
LONG = 64
SPACE = np.zeros(256, bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True
STEP = np.uint64(0x9E3779B97F4A7C15)
WIDTH = 5
_FACTORS = np.array([pow(int(STEP), k, 2**64) for k in range(WIDTH)], np.uint64)


def scramble(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that spreads every bit (the finaliser of a public hash function)."""
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xFF51AFD7ED558CCD)
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


CHUNK = 1 << 22
KEPT = np.array([(1 << 8 * k) - 1 for k in range(8)] + [2**64 - 1], np.uint64)


def lanes(data: np.ndarray) -> np.ndarray:
    """At each place of a byte string the eight bytes from there on as one number, zeros standing past the end."""
    return np.ndarray((len(data),), "<u8", np.concatenate([data, np.zeros(8, np.uint8)]).tobytes(), strides=(1,))


def stretch_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hashes of stretches of a byte string."""
    size = ends - starts
    h = scramble(size.astype(np.uint64) * STEP + np.uint64(1))
    eight = lanes(data)
    own, at, left = np.flatnonzero(size <= LONG), starts, size
    if len(own) < len(size):
        raw = data.tobytes()
        for i in np.flatnonzero(size > LONG).tolist():
            h[i] = int.from_bytes(hashlib.blake2b(raw[starts[i] : ends[i]], digest_size=8).digest(), "little")
        at, left = at[own], left[own]
    while len(own):
        h[own] = scramble(h[own] * STEP + (eight[at] & KEPT[np.minimum(left, 8)]))
        more = np.flatnonzero(left > 8)
        own, at, left = own[more], at[more] + 8, left[more] - 8
    return h


def word_hashes(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(first byte, hash) of each word of a byte string."""
    white = SPACE[data]
    edge = np.diff(np.concatenate([[1], white.view(np.int8), [1]]))
    starts, ends = np.flatnonzero(edge == -1), np.flatnonzero(edge == 1)
    return starts, stretch_hashes(LOWER[data], starts, ends) if len(starts) else np.zeros(0, np.uint64)


def shingles(words: np.ndarray) -> np.ndarray:
    """Sorted distinct shingles of one text's word hashes."""
    n = len(words)
    if n == 0:
        return np.zeros(0, np.uint64)
    if n < WIDTH:
        return scramble(np.array([(words * _FACTORS[:n]).sum(dtype=np.uint64) + np.uint64(n)], np.uint64))
    x = words[: n - WIDTH + 1] * _FACTORS[0]
    for k in range(1, WIDTH):
        x = x + words[k : n - WIDTH + 1 + k] * _FACTORS[k]
    return np.unique(scramble(x))


def text_sets(column) -> list[np.ndarray]:
    """The shingle set of each text of an Arrow string array; nulls give empty sets."""
    out = []
    for text in column:
        raw = text.as_buffer() if text.is_valid else None
        if raw is None or not raw.size:
            out.append(np.zeros(0, np.uint64))
            continue
        data = np.frombuffer(raw, np.uint8)
        if len(data) <= CHUNK:
            out.append(shingles(word_hashes(data)[1]))
            continue
        parts, at = [], 0
        while at < len(data):  # a long text in parts that end between words
            to = min(len(data), at + CHUNK)
            while to < len(data) and not SPACE[data[to]]:
                more = np.flatnonzero(SPACE[data[to : to + CHUNK]])
                to = to + int(more[0]) if len(more) else min(len(data), to + CHUNK)
            parts.append(word_hashes(data[at:to])[1])
            at = to
        out.append(shingles(np.concatenate(parts)))
    return out
