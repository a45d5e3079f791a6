"""Benchmark decontamination with spaced seeds.

Masks over consecutive words leave some places out, so a word that was changed there doesn't hide a match. Hashes of every
masked window of a benchmark item are joined with those of the documents; around each hit the item and the text are
laid on each other and words are compared, changed words included. A document leaks an item when some window of
``WINDOW`` words of the item (all of it, if it is shorter, and at least ``SHORTEST``) agrees in 0.8 of its places or more; the
report extends it to the longest such stretch.

The benchmark is the stated query set: the index of its distinct texts is made once, in blocks of a measured size, and goes to
every worker, one pass over the documents for each block, so a benchmark of any size is handled exactly and no document is
shuffled.

Cases: null and empty texts, and items below the shortest length, match nothing; repeated documents and items are
judged each by itself; rows with null ids are judged and reported like others; long texts are read whole; an empty
table gives an empty result; other columns are not read, and ``clean`` passes them on.
"""

from __future__ import annotations

import re
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import durable, lean, small

#: Places compared by each mask. The first hits every window of 13 places with 2 changed ones; with the second, for items of 8 to
#: 12 words only, so does every window of those lengths with as many changed places as 0.8 allows.
MASKS = [(0, 1, 3, 6, 7), (0, 1, 2, 5)]
WINDOW, SHORTEST, TENTHS = 13, 8, 8
#: Text bytes of the benchmark in one block.
BLOCK_BYTES = 32 << 20
#: Meetings of a document's windows with entries that are laid out at once.
AT_ONCE = 1 << 20
WORD = re.compile(r"\w+")


def needed(words: int) -> int:
    """Places that must agree in a window."""
    return -(-words * TENTHS // 10)


class Index:
    """Word numbers of a block of items, and their masked windows, sorted by hash; made once and sent to the workers."""

    def __init__(self, items: list[tuple[object, str]]):
        self.ids, self.items, self.number = [], [], {}
        for key, text in items:
            words = WORD.findall((text or "").lower())
            if len(words) >= SHORTEST:
                self.ids.append(key)
                self.items.append(np.array([self.number.setdefault(w, len(self.number) + 1) for w in words], np.int32))
        got: list[list[np.ndarray]] = [[np.zeros(0, np.uint64)], *([np.zeros(0, np.int32)] for _ in range(3))]
        for m, mask in enumerate(MASKS):
            for i, words in enumerate(self.items):
                if m and len(words) >= WINDOW:
                    continue
                h = seed_hashes(words, mask)
                for k, x in enumerate((h, np.full(len(h), m, np.int32), np.full(len(h), i, np.int32), np.arange(len(h), dtype=np.int32))):
                    got[k].append(x)
        hashes, mask, item, at = map(np.concatenate, got)
        order = np.argsort(hashes, kind="stable")
        self.hashes, self.mask, self.item, self.at = hashes[order], mask[order], item[order], at[order]
        self.masks = {*mask.tolist()}


def seed_hashes(words: np.ndarray, mask: tuple[int, ...]) -> np.ndarray:
    n = len(words) - mask[-1]
    if n <= 0:
        return np.zeros(0, np.uint64)
    h = np.full(n, sum(1 << p for p in mask), np.uint64)
    for p in mask:
        h = (h ^ words[p : p + n].astype(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
        h ^= h >> np.uint64(29)
    return h


def best_stretch(same: np.ndarray) -> tuple[int, int, int] | None:
    """(start, end, agreeing) of the longest stretch that agrees in 0.8 of its places and holds such a window."""
    window = min(WINDOW, len(same))
    total = np.concatenate(([0], np.cumsum(same)))
    got = total[window:] - total[:-window]
    if window < SHORTEST or got.max() < needed(window):
        return None
    score = 10 * total - TENTHS * np.arange(len(total))  # a stretch qualifies if score doesn't fall from start to end
    low = np.minimum.accumulate(score)
    best = (0, 0)
    for end in range(len(same), 0, -1):
        if end <= best[1] - best[0]:
            break
        start = int(np.searchsorted(-low, -score[end], side="left"))
        if end - start > best[1] - best[0]:
            best = (start, end)
    start, end = best
    while end > start and not same[end - 1]:
        end -= 1
    while start < end and not same[start]:
        start += 1
    return start, end, int(total[end] - total[start])


def leaks_in(text: str, index: Index) -> list[tuple[int, int, int, int, int, int]]:
    """(item, item words, agreeing, compared, first word in the item, first word in the text), the best place of each item."""
    words = WORD.findall(text.lower())
    if len(words) < SHORTEST:
        return []
    number = np.fromiter(map(index.number.get, words, [0] * len(words)), np.int64, len(words))
    laid: set[tuple[int, int]] = set()
    found = np.zeros((0, 2), np.int64)
    for m, mask in enumerate(MASKS):
        n = len(number) - mask[-1]
        if n <= 0 or m not in index.masks:
            continue
        known = number[: n] > 0
        for p in mask[1:]:
            known &= number[p : p + n] > 0
        if not (at := np.flatnonzero(known)).size:
            continue
        h = np.full(len(at), sum(1 << p for p in mask), np.uint64)
        for p in mask:
            h = (h ^ number[at + p].astype(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
            h ^= h >> np.uint64(29)
        lo = np.searchsorted(index.hashes, h, side="left")
        hit = np.flatnonzero(index.hashes[np.minimum(lo, len(index.hashes) - 1)] == h)
        if len(hit):
            held = np.searchsorted(index.hashes, h[hit], side="right") - lo[hit]
            end = np.cumsum(held)
            # the entries of all hits, in runs of a bounded number of them; those of one item and shift count once
            for run in np.array_split(np.arange(len(hit)), 1 + int(end[-1]) // AT_ONCE):
                each = held[run]
                entry = np.repeat(lo[hit[run]], each) + np.arange(int(each.sum())) - np.repeat(np.cumsum(each) - each, each)
                own = index.mask[entry] == m
                found = np.unique(np.concatenate((found, np.stack((index.item[entry], np.repeat(at[hit[run]], each) - index.at[entry]), 1)[own])), axis=0)
    laid.update(map(tuple, found.tolist()))
    best: dict[int, tuple[int, int, int, int, int, int]] = {}
    for i, shift in sorted(laid):
        item = index.items[i]
        lo, hi = max(0, -shift), min(len(item), len(number) - shift)
        if hi - lo < min(WINDOW, len(item)):
            continue
        if found := best_stretch(item[lo:hi] == number[lo + shift : hi + shift]):
            start, end, same = found
            row = (i, len(item), same, end - start, lo + start, lo + start + shift)
            if i not in best or row[3] > best[i][3]:
                best[i] = row
    return list(best.values())


def indexes(benchmark: DataFrame, item_text: str, limit: int = BLOCK_BYTES) -> Iterator[Index]:
    """The distinct texts of the items, in blocks of a measured size; a text's digest stands for it."""
    texts = durable(benchmark.where(F.col(item_text).isNotNull()).select(F.col(item_text).alias("t")).distinct().select("t", F.md5("t").alias("digest")), "leaks-items")
    total = texts.agg(F.sum(F.octet_length("t"))).first()[0] or 0
    bins = 1 + 8 * total // limit
    place = F.pmod(F.xxhash64("t"), F.lit(bins))
    blocks, held = [[]], 0
    for r in sorted(texts.groupBy(place.alias("bin")).agg(F.sum(F.octet_length("t")).alias("n")).collect()):  # eight rows a block
        if blocks[-1] and held + r["n"] > limit:
            blocks.append([])
            held = 0
        blocks[-1].append(r["bin"])
        held += r["n"]
    for block in blocks:
        index = Index([(r["digest"], r["t"]) for r in texts.where(place.isin(block)).orderBy("digest").collect()])
        if len(index.hashes):
            yield index


def find_leaks(docs: DataFrame, benchmark: DataFrame, key: str = "doc_id", text: str = "text", item: str = "item_id", item_text: str = "text") -> DataFrame:
    """(key, item, item_words, matched, compared, identity, item_start, doc_start) of every leaked pair."""
    spark, kind = docs.sparkSession, dict(docs.dtypes)[key]
    names = ["item_words", "matched", "compared", "identity", "item_start", "doc_start"]
    schema = f"k {kind}, digest string, item_words int, matched int, compared int, identity double, item_start int, doc_start int"
    out = spark.createDataFrame([], schema)
    for index in indexes(benchmark, item_text):
        shared = spark.sparkContext.broadcast(index)

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            lean()
            index = shared.value
            for b in batches:
                rows = defaultdict(list)
                for k in range(b.num_rows):
                    for i, n, same, compared, item_at, at in leaks_in(b.column(1)[k].as_py() or "", index):
                        for name, v in (("k", k), ("i", index.ids[i]), ("n", n), ("m", same), ("c", compared), ("s", same / compared), ("a", item_at), ("d", at)):
                            rows[name].append(v)
                if rows:
                    keys = b.column(0).take(pa.array(rows["k"], pa.int64()))
                    ints = [pa.array(rows[c], pa.int32()) for c in "nmc"]
                    yield pa.RecordBatch.from_arrays([keys, pa.array(rows["i"]), *ints, pa.array(rows["s"], pa.float64()), pa.array(rows["a"], pa.int32()), pa.array(rows["d"], pa.int32())], ["k", "digest", *names])

        out = out.union(docs.select(F.col(key), F.col(text)).mapInArrow(run, schema))
    # repeated items share a text, which was looked for once
    items = durable(benchmark.where(F.col(item_text).isNotNull()).select(F.col(item).alias("i"), F.md5(item_text).alias("d")), "leaks-ids")
    return out.join(small(items, 64), F.col("digest") == F.col("d")).select(F.col("k").alias(key), F.col("i").alias(item), *names)


def clean(docs: DataFrame, benchmark: DataFrame, text: str = "text", item_text: str = "text") -> DataFrame:
    """The rows of docs that leak no item, whatever their ids: each is judged by its own text, and none is shuffled."""
    schema, at = docs.schema, docs.columns.index(text)
    for index in indexes(benchmark, item_text):
        shared = docs.sparkSession.sparkContext.broadcast(index)

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            lean()
            for b in (b.slice(i, 1024) for b in batches for i in range(0, b.num_rows, 1024)):
                yield b.filter(pa.array([not leaks_in(t.as_py() or "", shared.value) for t in b.column(at)], pa.bool_()))

        docs = docs.mapInArrow(run, schema)
    return docs
