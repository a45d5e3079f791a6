"""SimHash near-duplicates by multi-index hashing.

A fingerprint is cut into segments. Each is a table of its own: a fingerprint is stored under its segment's value and looked up
under every value in a small Hamming ball around it: either all values within the radius, or, where a fingerprint knows by
how many votes its bits were won, those that differ in its weakest bits. All that meet under a value are compared over
the complete fingerprint.

Stored and probing entries travel in packed blocks to the partition of their value. A partition compares what meets in it
and returns a spanning forest of its links, so its output is at most a row per fingerprint however large a group of copies
is, and members that it has already joined are not compared again. Values that very many fingerprints are stored under are dealt
over a grid of blocks (each stored part meets each probing part) so no task's work is set by one value.

Cases: null texts count as empty; a text without words has fingerprint zero and is linked like any other; repeated rows
share a fingerprint; null ids belong to components and never name one; long texts are read whole; an empty table gives an
empty result; other columns are passed on only where the caller asks for them.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from itertools import combinations
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import components, durable, release, slices
from .hashing import bit_votes, mix, shingles

U = np.uint64
#: Entries that one partition gets on average, and stored entries of one value beyond which it is dealt over a grid.
PART_ENTRIES, HOT = 250_000, 20_000


class Segment(NamedTuple):
    word: int
    shift: int
    bits: int
    #: Radius of the full ball, or -1 to differ in weak bits only.
    radius: int


class Scheme(NamedTuple):
    shingle: int
    words: int
    segments: tuple[Segment, ...]
    #: Greatest distance of a link, over all words.
    distance: int
    distinct: bool = False
    #: Weak bits of a segment: so many are changed alone, so many in pairs.
    alone: int = 0
    paired: int = 0


#: The contract's links: 64 bits, distance 2. If both halves of two fingerprints differ, one bit of each does; else one half is equal.
CONTRACT = Scheme(3, 1, (Segment(0, 0, 32, 1), Segment(0, 32, 32, 0)), 2)
#: The same links between fingerprints of five-word shingle sets.
FIVE = CONTRACT._replace(shingle=5, distinct=True)


def fingerprints(df: DataFrame, scheme: Scheme, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, node, fp, weak): the fingerprint as little-endian words, its number (the fingerprint itself if it is one word), and
    each segment's weakest bits, weakest first."""
    kind = dict(df.dtypes)[key]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fp, weak, node = [], [], []
            for _, _, data, at in slices(batch.column(1)):
                h, n = shingles(data, at, scheme.shingle)
                if scheme.distinct and len(h):
                    own = np.repeat(np.arange(len(n)), n)
                    _, first = np.unique(mix(h, 1) + own.astype(np.uint64) * U(0xD6E8FEB86659FD93), return_index=True)
                    first.sort()
                    h, n = h[first], np.bincount(own[first], minlength=len(n))
                words, margins = [], []
                for w in range(scheme.words):
                    lead = 2 * bit_votes(h if not w else mix(h, w), n) - n[:, None]
                    words.append(np.packbits(lead > 0, axis=1, bitorder="little").view("<u8")[:, 0])
                    margins.append(np.abs(lead))
                rows = np.stack(words, 1)
                fp += [r.tobytes() for r in rows]
                number = rows[:, 0]
                for w in range(1, scheme.words):
                    number = mix(number, 1) ^ rows[:, w]
                node.append(number.view(np.int64))
                if scheme.alone:
                    order = np.stack([np.argsort(margins[s.word][:, s.shift : s.shift + s.bits], 1, kind="stable")[:, : scheme.alone] for s in scheme.segments], 1).astype(np.uint8)
                    weak += [r.tobytes() for r in order]
                else:
                    weak += [b""] * len(rows)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.concatenate(node) if node else [], pa.int64()), pa.array(fp, pa.binary()), pa.array(weak, pa.binary())], [key, "node", "fp", "weak"])

    return df.select(F.col(key), F.col(text)).mapInArrow(run, f"`{key}` {kind}, node long, fp binary, weak binary")


def entries(fp: np.ndarray, weak: np.ndarray | None, scheme: Scheme) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray]]:
    """(segment, value, row, stored) of all entries of fingerprints (rows of words). Of two values that differ in one bit of a full
    ball, the one without the bit probes, so a pair meets once; entries that are stored probe too."""
    rows = np.arange(len(fp))
    for k, s in enumerate(scheme.segments):
        value = (fp[:, s.word] >> U(s.shift)) & U((1 << s.bits) - 1)
        yield k, value, rows, np.ones(len(rows), bool)
        if s.radius == 1:
            for b in range(s.bits):
                off = np.flatnonzero((value >> U(b)) & U(1) == 0)
                yield k, value[off] | U(1 << b), off, np.zeros(len(off), bool)
        elif s.radius < 0:
            flips = [U(1) << weak[:, k, i].astype(np.uint64) for i in range(scheme.alone)]
            for change in [*flips, *(flips[i] | flips[j] for i, j in combinations(range(scheme.paired), 2))]:
                yield k, value ^ change, rows, np.zeros(len(rows), bool)


def number_of(segment: int, value: np.ndarray) -> np.ndarray:
    return mix(value + U(segment << 40), 9)


class Joined:
    """Which of the fingerprints of a partition are already in one component."""

    def __init__(self, n: int):
        self.root = np.arange(n)

    def add(self, a: np.ndarray, b: np.ndarray) -> None:
        a, b = self.root[a], self.root[b]
        while (apart := np.flatnonzero(a != b)).size:
            a, b = a[apart], b[apart]
            low, high = np.minimum(a, b), np.maximum(a, b)
            to = np.arange(len(self.root))
            np.minimum.at(to, high, low)
            while not np.array_equal(again := to[to], to):
                to = again
            self.root = to[self.root]
            a, b = to[a], to[b]


def meet(number: np.ndarray, who: np.ndarray, stored: np.ndarray, probing: np.ndarray, fp: np.ndarray, limit: int, pairs_at_once: int = 1 << 20) -> np.ndarray:
    """The root of each fingerprint (row of fp) after all links among entries of equal number."""
    joined = Joined(len(fp))
    order = np.lexsort((~stored, number))
    number, who, stored, probing = number[order], who[order], stored[order], probing[order]
    begin = np.flatnonzero(np.concatenate(([True], number[1:] != number[:-1])))
    size = np.diff(np.concatenate((begin, [len(number)])))
    held = np.add.reduceat(stored.astype(np.int64), begin) if len(begin) else size
    some = np.flatnonzero((held > 0) & (size > 1))
    work = held[some] * size[some]
    few = some[work <= 4096]
    for part in np.array_split(few, max(1, int(work[work <= 4096].sum()) // pairs_at_once)):
        n = held[part] * size[part]
        if not n.sum():
            continue
        within = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
        base, wide_ = np.repeat(begin[part], n), np.repeat(size[part], n)
        a, b = base + within // wide_, base + within % wide_
        right = probing[b] & (who[a] != who[b])
        a, b = who[a[right]], who[b[right]]
        near = np.zeros(len(a), np.int64)
        for w in range(fp.shape[1]):
            near += np.bitwise_count(fp[a, w] ^ fp[b, w])
        joined.add(a[near <= limit], b[near <= limit])
    for g in some[work > 4096]:
        t, p = who[begin[g] : begin[g] + held[g]], who[begin[g] : begin[g] + size[g]][probing[begin[g] : begin[g] + size[g]]]
        for i in range(0, len(t), 64):
            mine = t[i : i + 64]
            others = p
            if (joined.root[mine] == joined.root[mine[0]]).all():  # what is joined with all of them already can add nothing
                others = p[joined.root[p] != joined.root[mine[0]]]
            for j in range(0, len(others), 16384):
                some_others = others[j : j + 16384]
                near = np.zeros((len(mine), len(some_others)), np.int16)
                for w in range(fp.shape[1]):
                    near += np.bitwise_count(fp[mine, w][:, None] ^ fp[some_others, w][None])
                x, y = np.nonzero(near <= limit)
                joined.add(mine[x], some_others[y])
    return joined.root


def links(distinct: DataFrame, scheme: Scheme, hot: int = HOT) -> DataFrame:
    """(a, b): links that join the same nodes as all pairs of fingerprints within the distance that meet; distinct: (node, fp, weak)."""
    total = distinct.count()
    per = sum(1 + (s.bits // 2 if s.radius == 1 else 0) + (scheme.alone + scheme.paired * (scheme.paired - 1) // 2 if s.radius < 0 else 0) for s in scheme.segments)
    parts = max(1, -(-total * per // PART_ENTRIES))
    parts = max(parts, distinct.sparkSession.sparkContext.defaultParallelism)

    def unpack(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray, np.ndarray | None]:
        fp = np.frombuffer(b"".join(batch.column(1).to_pylist()), "<u8").reshape(-1, scheme.words)
        weak = np.frombuffer(b"".join(batch.column(2).to_pylist()), np.uint8).reshape(-1, len(scheme.segments), scheme.alone) if scheme.alone else None
        return np.array(batch.column(0).to_numpy(zero_copy_only=False), np.int64), fp, weak

    def stored_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            _, fp, _ = unpack(batch)
            all_ = np.concatenate([number_of(k, (fp[:, s.word] >> U(s.shift)) & U((1 << s.bits) - 1)) for k, s in enumerate(scheme.segments)])
            value, n = np.unique(all_, return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(value.view(np.int64)), pa.array(n.astype(np.int64))], ["number", "n"])

    # at most total * segments / hot values; the bound grows with the table, so their number stays below 10,000
    bound = max(hot, total * len(scheme.segments) // 10_000)
    busy = {}
    if total > bound:
        counted = distinct.select("node", "fp", "weak").mapInArrow(stored_counts, "number long, n long").groupBy("number").agg(F.sum("n").alias("n"))
        busy = {r["number"]: -(-r["n"] // bound) for r in counted.where(F.col("n") > bound).collect()}

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hot_numbers = np.array(sorted(busy), np.int64)
        grid = np.array([busy[x] for x in hot_numbers.tolist()], np.int64)
        for batch in (b.slice(i, 4096) for b in batches for i in range(0, b.num_rows, 4096)):
            node, fp, weak = unpack(batch)
            got = [(number_of(k, value), row, stored, np.ones(len(row), bool)) for k, value, row, stored in entries(fp, weak, scheme)]
            number, row, stored, probing = (np.concatenate(x) for x in zip(*got, strict=True))
            if len(hot_numbers):
                at = np.minimum(np.searchsorted(hot_numbers, number.view(np.int64)), len(hot_numbers) - 1)
                is_hot = hot_numbers[at] == number.view(np.int64)
                parts_ = [(number[~is_hot], row[~is_hot], stored[~is_hot], probing[~is_hot])]
                for h in np.unique(at[is_hot]):
                    own, g = np.flatnonzero(is_hot & (at == h)), int(grid[h])
                    cell = (mix(node[row[own]].view(np.uint64), 5) % U(g)).astype(np.int64)
                    for i in range(g):
                        for j in range(g):
                            s, p = stored[own] & (cell == i), cell == j
                            use = s | p
                            parts_.append((mix(number[own[use]], 100 + i * g + j), row[own[use]], s[use], p[use]))
                number, row, stored, probing = (np.concatenate(x) for x in zip(*parts_, strict=True))
            part = (number % U(parts)).astype(np.int64)
            order = np.argsort(part, kind="stable")
            cut = np.searchsorted(part[order], np.arange(parts + 1))
            out = []
            for p in np.flatnonzero(np.diff(cut)):
                at = order[cut[p] : cut[p + 1]]
                out.append((int(p), number[at].tobytes(), node[row[at]].tobytes(), (stored[at] + 2 * probing[at]).astype(np.uint8).tobytes(), fp[row[at]].tobytes()))
            cols = list(zip(*out, strict=True)) if out else [[]] * 5
            yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int32()), *(pa.array(c, pa.binary()) for c in cols[1:])], ["part", "number", "node", "kind", "fp"])

    def link(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got: list[list[bytes]] = [[], [], [], []]
        for batch in batches:
            for k in range(4):
                got[k] += batch.column(k + 1).to_pylist()
        number, node = np.frombuffer(b"".join(got[0]), np.uint64), np.frombuffer(b"".join(got[1]), np.int64)
        kind, fp = np.frombuffer(b"".join(got[2]), np.uint8), np.frombuffer(b"".join(got[3]), "<u8").reshape(-1, scheme.words)
        if not len(number):
            return
        nodes, first, who = np.unique(node, return_index=True, return_inverse=True)
        root = meet(number, who, (kind & 1) > 0, (kind & 2) > 0, fp[first], scheme.distance)
        linked = np.flatnonzero(root != np.arange(len(root)))
        yield pa.RecordBatch.from_arrays([pa.array(nodes[linked]), pa.array(nodes[root[linked]])], ["a", "b"])

    packed = distinct.select("node", "fp", "weak").mapInArrow(pack, "part int, number binary, node binary, kind binary, fp binary")
    return packed.repartition(parts, "part").mapInArrow(link, "a long, b long")


def grouped(df: DataFrame, scheme: Scheme, key: str = "doc_id", text: str = "text", hot: int = HOT) -> DataFrame:
    """(key, fp, component_id) of every row; component_id is the smallest id in reach."""
    every = durable(fingerprints(df, scheme, key, text), "simhash")
    distinct = durable(every.groupBy("node").agg(F.min(key).alias("least"), F.min("fp").alias("fp"), F.min("weak").alias("weak")), "simhash-distinct")
    rooted = components(links(distinct, scheme, hot), "simhash-links").withColumnRenamed("node", "n")
    named = distinct.select("node", "least").join(rooted, F.col("node") == F.col("n"))
    least = named.groupBy("root").agg(F.min("least").alias("component_id")).withColumnRenamed("root", "r")
    found = durable(named.join(least, F.col("root") == F.col("r")).select("node", "component_id"), "simhash-roots").withColumnRenamed("node", "f")
    release(df.sparkSession)
    alone = distinct.select(F.col("node").alias("m"), "least").join(found, F.col("m") == F.col("f"), "left").select("m", F.coalesce("component_id", "least").alias("component_id"))
    return every.select(key, "node").join(alone, F.col("node") == F.col("m")).select(key, "node", "component_id")


def contract(df: DataFrame) -> DataFrame:
    """(doc_id, fingerprint, component_id): fingerprints of 64 bits as 16 hex digits, links at 2 differing bits or fewer."""
    return grouped(df, CONTRACT).select("doc_id", F.lower(F.lpad(F.hex("node"), 16, "0")).alias("fingerprint"), "component_id")


def keep_one(df: DataFrame, similarity: float = 0.8, shingle: int = 5, key: str = "doc_id", text: str = "text") -> DataFrame:
    """The rows of df without near copies of rows with smaller ids: fingerprints within two bits, completed to all links of
    the similarity and confirmed by complete shingle sets (``nearcopies``)."""
    from .nearcopies import keep_one as completed  # which builds on this module

    return completed(df, similarity, shingle, key, text)
