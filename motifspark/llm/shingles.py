"""Word and shingle hashes of many texts at once, in numpy.

Words are runs of bytes without ASCII white space, A-Z in lower case.  A word's hash is a
polynomial over its bytes modulo 2**64 with a final mix, a long word's a cryptographic
digest; a shingle's is a mix of the hashes of its words in order.  Shingles are compared by
these 64 bits: two that differ agree with a chance of one in 2**64.
"""

from __future__ import annotations

import hashlib

import numpy as np

U = np.uint64
_RNG = np.random.Generator(np.random.PCG64(20240229))
LETTER = _RNG.integers(1, 1 << 63, 256, dtype=np.uint64) * U(2) + U(1)
FACTOR = _RNG.integers(1, 1 << 63, 64, dtype=np.uint64) * U(2) + U(1)
BASE = U(0x9E3779B97F4A7C15)
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
CHUNK = 1 << 18  # bytes hashed together
LONG = 64  # bytes of a word that the polynomial takes
SPACE = np.zeros(256, dtype=bool)
SPACE[[9, 10, 11, 12, 13, 32]] = True


def mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> U(33))) * U(0xFF51AFD7ED558CCD)
    x = (x ^ (x >> U(33))) * U(0xC4CEB9FE1A85EC53)
    return x ^ (x >> U(33))


def powers(n: int) -> np.ndarray:
    out = np.full(n, BASE, dtype=np.uint64)
    out[:1] = 1
    return np.cumprod(out, dtype=np.uint64)


def word_spans(buf: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First byte and end byte of every word."""
    solid = ~SPACE[buf]
    edge = np.zeros(len(buf) + 1, dtype=bool)
    edge[off] = True
    before = np.concatenate(([False], solid[:-1])) if len(buf) else solid
    after = np.concatenate((solid[1:], [False])) if len(buf) else solid
    return np.flatnonzero(solid & (~before | edge[:-1])), np.flatnonzero(solid & (~after | edge[1:])) + 1


def span_hashes(buf: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each span of bytes.

    Up to LONG bytes a polynomial modulo 2**64 with random coefficients and a final mix; long ones, of
    which polynomials modulo a power of two can be led to agree, by a cryptographic digest.
    """
    if not len(start):
        return np.zeros(0, dtype=np.uint64)
    size = end - start
    short = np.minimum(size, LONG)
    heads = np.concatenate(([0], np.cumsum(short)))
    power, out = powers(LONG), np.empty(len(start), dtype=np.uint64)
    a = 0
    while a < len(start):  # some words at a time: the intermediates take many bytes a byte
        b = max(a + 1, int(np.searchsorted(heads, heads[a] + CHUNK, "right")) - 1)
        own = heads[a:b] - heads[a]
        local = np.arange(heads[b] - heads[a]) - np.repeat(own, short[a:b])
        letters = buf[np.repeat(start[a:b], short[a:b]) + local]
        out[a:b] = np.add.reduceat(LETTER[letters] * power[local], own)
        a = b
    out = mix(out ^ (size.astype(np.uint64) * FACTOR[63]))
    for k in np.flatnonzero(size > LONG).tolist():
        out[k] = int.from_bytes(hashlib.blake2b(buf[start[k] : end[k]].tobytes(), digest_size=8).digest(), "little")
    return out


def word_hashes(buf: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hash of every word, A-Z as a-z, and per text the number of its first word (one more at the end)."""
    start, end = word_spans(buf, off)
    return span_hashes(LOWER[buf], start, end), np.searchsorted(start, off)


def grams(words: np.ndarray, k: int) -> np.ndarray:
    """Hashes of the runs of k words (k up to 32); fewer than k words give none."""
    n = len(words) - k + 1
    if n <= 0:
        return np.zeros(0, dtype=np.uint64)
    out = np.full(n, k, dtype=np.uint64) * FACTOR[62]
    for j in range(k):
        out += words[j : j + n] * FACTOR[j]
    return mix(out)


def shingle_set(words: np.ndarray, k: int = 5) -> np.ndarray:
    """Sorted distinct shingle hashes as int64; with fewer words the whole sequence is one, without words there is none."""
    return np.unique(grams(words, min(k, len(words))).view(np.int64)) if len(words) else np.zeros(0, dtype=np.int64)
