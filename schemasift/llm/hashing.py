"""Vectorised XXH64 of many byte ranges, and word shingles of UTF-8 texts as such ranges."""

from __future__ import annotations

import numpy as np

U = np.uint64
#: The primes of XXH64. Fixed values.
P1, P2, P3, P4, P5 = U(0x9E3779B185EBCA87), U(0xC2B2AE3D27D4EB4F), U(0x165667B19E3779F9), U(0x85EBCA77C2B2AE63), U(0x27D4EB2F165667C5)


def _rotl(x: np.ndarray, r: int) -> np.ndarray:
    return (x << U(r)) | (x >> U(64 - r))


def _round(acc: np.ndarray, lane: np.ndarray) -> np.ndarray:
    return _rotl(acc + lane * P2, 31) * P1


def wide(data: np.ndarray) -> np.ndarray:
    """At each byte the next eight bytes as one little-endian number; data is read as if zeros followed."""
    padded = np.concatenate([data, np.zeros(16, np.uint8)])
    return np.array(np.ndarray((len(data) + 8,), "<u8", padded, 0, (1,)))


def xxh64(data: np.ndarray, start: np.ndarray, length: np.ndarray, seed: int = 42) -> np.ndarray:
    """The XXH64 of data[start : start + length] for every range."""
    words = wide(data)
    begin = [U(x & (1 << 64) - 1) for x in (seed + int(P1) + int(P2), seed + int(P2), seed, seed - int(P1), seed + int(P5))]
    order = np.argsort(length, kind="stable")
    at, n = start[order].astype(np.int64), length[order].astype(np.int64)
    h = np.full(len(n), begin[4], np.uint64)
    long_ = int(np.searchsorted(n, 32))
    if long_ < len(n):
        a, stripes = at[long_:].copy(), n[long_:] // 32
        v = [np.full(len(a), x, np.uint64) for x in begin[:4]]
        for k in range(int(stripes.max())):
            m = int(np.searchsorted(stripes, k, side="right"))
            for j in range(4):
                v[j][m:] = _round(v[j][m:], words[a[m:] + 8 * j])
            a[m:] += 32
        x = _rotl(v[0], 1) + _rotl(v[1], 7) + _rotl(v[2], 12) + _rotl(v[3], 18)
        for j in range(4):
            x = (x ^ _round(np.zeros_like(v[j]), v[j])) * P1 + P4
        h[long_:], at[long_:] = x, a
    h += n.astype(np.uint64)
    rest = n % 32
    for k in range(3):
        some = np.flatnonzero(rest >= 8 * (k + 1))
        h[some] = _rotl(h[some] ^ _round(np.zeros(len(some), np.uint64), words[at[some] + 8 * k]), 27) * P1 + P4
    at = at + rest // 8 * 8
    some = np.flatnonzero(rest % 8 >= 4)
    h[some] = _rotl(h[some] ^ ((words[at[some]] & U(0xFFFFFFFF)) * P1), 23) * P2 + P3
    at[some] += 4
    for k in range(3):
        some = np.flatnonzero(rest % 4 > k)
        h[some] = _rotl(h[some] ^ ((words[at[some] + k] & U(0xFF)) * P5), 11) * P1
    h ^= h >> U(33)
    h *= P2
    h ^= h >> U(29)
    h *= P3
    h ^= h >> U(32)
    out = np.empty_like(h)
    out[order] = h
    return out


def mix(x: np.ndarray, salt: int) -> np.ndarray:
    """Another well-spread number for each of x."""
    x = x + U(salt * 0x9E3779B97F4A7C15 & (2**64 - 1))
    x = (x ^ (x >> U(30))) * U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


_BLANK = np.isin(np.arange(256), [0x20, *range(0x09, 0x0E)])
_LOWER = np.array([b + 32 if 65 <= b <= 90 else b for b in range(256)], np.uint8)


def shingles(data: np.ndarray, offsets: np.ndarray, words: int, seed: int = 42) -> tuple[np.ndarray, np.ndarray]:
    """(XXH64 of each shingle, shingles of each text). Words are runs of bytes outside blanks, A-Z in lower case, joined by one
    blank; a text with fewer words is one shingle of all of them, one without any has none."""
    texts = len(offsets) - 1
    if not len(data):
        return np.zeros(0, np.uint64), np.zeros(texts, np.int64)
    word = ~_BLANK[data]
    first = np.zeros(len(data) + 1, bool)
    first[offsets] = True
    before = np.concatenate(([False], word[:-1])) & ~first[:-1]
    after = np.concatenate((word[1:], [False])) & ~first[1:]
    start, end = np.flatnonzero(word & ~before), np.flatnonzero(word & ~after) + 1
    keep = word | (np.concatenate(([False], word[:-1])) & ~word)
    place = np.concatenate(([0], np.cumsum(keep)))
    plain = np.where(word, _LOWER[data], np.uint8(0x20))[keep]
    at = np.searchsorted(start, offsets)
    n = np.diff(at)
    made = np.where(n >= words, n - words + 1, np.minimum(n, 1))
    head = np.repeat(at[:-1], made) + _within(made)
    tail = np.minimum(head + words, np.repeat(at[1:], made)) - 1
    begin = place[start[head]] if len(head) else np.zeros(0, np.int64)
    finish = place[end[tail] - 1] + 1 if len(head) else begin
    return xxh64(plain, begin, finish - begin, seed), made


def _within(counts: np.ndarray) -> np.ndarray:
    """0, 1, ... inside each group."""
    total = int(counts.sum())
    return np.arange(total) - np.repeat(np.cumsum(counts) - counts, counts)


def bit_votes(hashes: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """How many of each text's hashes have each of the 64 bits set; eight bit counters share a number, 255 hashes at a time."""
    out = np.zeros((len(counts), 64), np.int64)
    some = np.flatnonzero(counts)
    if not len(some):
        return out
    n = counts[some]
    runs = -(-n // 255)
    begins = np.repeat(np.cumsum(n) - n, runs) + 255 * _within(runs)
    row = np.cumsum(runs) - runs
    for b in range(8):
        lanes = (hashes >> U(b)) & U(0x0101010101010101)
        part = np.add.reduceat(lanes, begins).view(np.uint8).reshape(-1, 8)
        out[some, b::8] = np.add.reduceat(part.astype(np.int64), row, axis=0)
    return out
