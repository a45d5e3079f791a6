"""Column-wise construction of a collection's Burrows-Wheeler transform and common prefixes.

Round j puts the suffix of length j of every string in its place: the strings' next symbols are merged into those known,
which stay in order of symbol and place and so give every new suffix its rank, and a common prefix is one symbol more than the
least among those between the two suffixes' tails. Each round reads the arrays of the one before and writes new ones; which
string and length a suffix has is read at the end, by one walk from each string's end to its start.
"""

from __future__ import annotations

from typing import NamedTuple

import numpy as np

U = np.uint64


class Collection(NamedTuple):
    #: In the order of suffixes: the symbol before each (0: none, else byte + 1), common prefix with the suffix before, string, length.
    before: np.ndarray
    shared: np.ndarray
    string: np.ndarray
    length: np.ndarray


def range_min(values: np.ndarray, lo: np.ndarray, hi: np.ndarray, space: np.ndarray) -> np.ndarray:
    """The least of values[lo..hi] for every pair with hi >= lo; space: bytes for a row of values for each power of two."""
    level = np.frexp((hi - lo + 1).astype(np.float64))[1].astype(np.int64) - 1
    n, top = len(values), int(level.max()) if len(level) else 0
    flat = space[: (top + 1) * n]
    table = flat.reshape(top + 1, n)
    table[0] = values
    for k in range(top):
        np.minimum(table[k, : n - (1 << k)], table[k, 1 << k :], out=table[k + 1, : n - (1 << k)])
    return np.minimum(flat[level * n + lo], flat[level * n + hi + 1 - (1 << level)])


def build(data: np.ndarray, offsets: np.ndarray) -> Collection:
    """data[offsets[i] : offsets[i + 1]] are the strings, of up to 255 bytes each, as parts of UTF-8 texts: no byte is 255."""
    m, lengths = len(offsets) - 1, np.diff(offsets)
    longest, low = int(lengths.max()) if m else 0, np.int64((1 << 32) - 1)
    size = m + int(lengths.sum())
    space = np.empty(size * size.bit_length(), np.uint8)  # one buffer for all rounds: fresh pages would cost more than the work on them
    # a suffix whose symbol is known is one number, symbol above place; in their order the k-th comes before suffix m + k
    shared, place, known = np.zeros(m, np.uint8), np.arange(m), np.zeros(0, np.int64)
    for j in range(1, longest + 1):
        active = np.flatnonzero(lengths >= j)
        mine = (data[offsets[active + 1] - j].astype(np.int64) + 1) << 32 | place[active]
        order = np.argsort(mine)
        mine, active = mine[order], active[order]
        new = np.searchsorted(known, mine) + np.arange(len(mine))
        old = np.ones(len(known) + len(mine), bool)
        old[new] = False
        every = np.empty(len(old), np.int64)
        every[old], every[new] = known, mine
        asked = ~old
        asked[1:] |= ~old[:-1]
        asked = np.flatnonzero(asked)
        inner = asked[asked > 0]
        one, two = every[inner - 1], every[inner]
        same = one >> 32 == two >> 32
        inner, one, two = inner[same], one[same] & low, two[same] & low
        at = m + new
        stay = np.ones(m + len(every), bool)
        stay[at] = False
        common = np.empty(len(stay), np.uint8)
        common[stay] = shared
        common[m + asked] = 0
        if inner.size:
            common[m + inner] = range_min(shared, one + 1, two, space) + np.uint8(1)
        # places move up by the new suffixes before them
        moved = np.repeat(np.arange(len(at) + 1), np.diff(np.concatenate(([0], at - np.arange(len(at)), [len(shared)]))))
        every += moved[every & low]
        shared, known, place[active] = common, every, at
    n, tail = len(shared), known & low
    before, next_, string, length = np.zeros(n, np.uint8), np.zeros(n, np.int64), np.empty(n, np.int64), np.empty(n, np.uint8)
    before[tail], next_[tail] = known >> 32, m + np.arange(len(known))
    at, who = np.arange(m), np.arange(m)
    for j in range(longest + 1):
        string[at], length[at] = who, j
        more = lengths[who] > j
        at, who = next_[at[more]], who[more]
    return Collection(before, shared, string, length)


def seen_before(data: np.ndarray, offsets: np.ndarray, owner: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """(string, start) of every substring of the width that also is in a string of a smaller owner."""
    c = build(data, offsets)
    group = np.cumsum(c.shared < width) - 1
    full = np.flatnonzero(c.length >= width)
    if not full.size:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    group, string = group[full], c.string[full]
    begin = np.flatnonzero(np.concatenate(([True], group[1:] != group[:-1])))
    least = np.minimum.reduceat(owner[string], begin)
    late = owner[string] > np.repeat(least, np.diff(np.concatenate((begin, [len(group)]))))
    string = string[late].astype(np.int64)
    return string, np.diff(offsets)[string] - c.length[full][late].astype(np.int64)
