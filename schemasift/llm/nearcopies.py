"""Near copies: the SimHash operator's links, completed to all links of an exact Jaccard similarity of word shingles.

SimHash fingerprints within two bits are found by multi-index hashing (``simhash``); each such link is confirmed by the complete
shingle sets. Texts at a similarity of 0.8 differ in ten of 64 bits, too many for small Hamming balls, so the links that
fingerprints can't show come from bands of MinHashes: two texts meet if all hashes of any band agree. The bands are
so many that a pair at the threshold itself fails to meet with a probability of 4e-12; whoever meets and isn't joined yet is
compared by the complete sets, so what is below the threshold is never linked. Texts with equal sets are one node.

Each group of equal bands first compares its least member with all others. Members of groups that are still apart may share a
passage and little else, and would give all their pairs; so they meet anew by prefixes: with shingles ordered by how many of
these members hold them, rarest first, two sets at the threshold share one of the first n - ceil(0.8 n) + 1 of each. Any
order would do, so counts are kept in a table of fixed size. A pair must also be able to reach the threshold by its sizes, by
the places of the shared shingle, and by its bitmaps: each shingle flips one bit, so as many bits as two bitmaps differ in are
shingles that only one of the sets has. These groups are resolved in rounds: some members outside a group's largest component
(pivots) are compared with all others that they are not joined with, and leave. All of it is aggregates and joins, so no task
holds a group, and hot ones split in AQE's skew join.

Cases: null texts count as empty; texts without words have equal (empty) sets; of repeated rows one stays; rows without an id
always stay and never replace another; one id may stand on several texts; long texts are read whole; an empty table gives an
empty result; other columns are passed on as they are.
"""

from __future__ import annotations

from collections.abc import Iterator
from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import simhash
from .common import PLACE, components, drop_durable, durable, numbered, release, slices, small
from .hashing import bit_votes, mix, shingles

U = np.uint64
#: MinHashes of a band, and bands: at similarity 0.8 a pair meets in none with (1 - 0.8 ** 4) ** 50.
ROWS, BANDS = 4, 50
#: Pivots of the first round over prefixes, which ends all groups but large ones; each round after it has eight times more.
LISTED = 32
#: Numbers that shingles are counted under for their order.
COUNTED = 1 << 18
#: The 64-bit words of a set's bitmap.
WORDS = ("w0", "w1", "w2", "w3")
TURN = mix(np.arange(ROWS * BANDS, dtype=np.uint64), 31) | U(1)
SHIFT = mix(np.arange(ROWS * BANDS, dtype=np.uint64), 32)


def bands(h: np.ndarray, n: np.ndarray) -> np.ndarray:
    """(texts, BANDS): the value of each band of each text; h: the shingles of all texts, n of each, none of them 0."""
    begin = np.cumsum(n) - n
    out = np.zeros((len(n), BANDS), np.uint64)
    for k in range(ROWS * BANDS):
        least = np.minimum.reduceat(h * TURN[k] + SHIFT[k], begin)
        out[:, k // ROWS] = mix(out[:, k // ROWS] ^ least, k)
    return mix(out + np.arange(BANDS, dtype=np.uint64), 7)


def distinct_shingles(data: np.ndarray, at: np.ndarray, shingle: int) -> tuple[np.ndarray, np.ndarray]:
    """(sorted distinct shingles of each text, how many each has)."""
    h, n = shingles(data, at, shingle)
    own = np.repeat(np.arange(len(n)), n)
    order = np.lexsort((h, own))
    h, own = h[order], own[order]
    new = np.ones(len(h), bool)
    new[1:] = (h[1:] != h[:-1]) | (own[1:] != own[:-1])
    return h[new], np.bincount(own[new], minlength=len(n))


def lists(values: np.ndarray, n: np.ndarray) -> pa.ListArray:
    return pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(n))), pa.int32()), pa.array(values.view(np.int64)))


def marks(df: DataFrame, shingle: int, key: str, text: str) -> DataFrame:
    """(id, place, node, size, fp, bands): the number of the shingle set (0 if empty), its size, SimHash and bands (none if empty)."""
    kind = dict(df.dtypes)[key]
    names = ["id", *PLACE, "node", "size", "fp", "bands"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo, hi, data, at in slices(batch.column(3)):
                h, n = distinct_shingles(data, at, shingle)
                some = np.flatnonzero(n)
                node, band, held = np.zeros(len(n), U), np.zeros(0, U), np.where(n > 0, BANDS, 0)
                if len(some):
                    begin = (np.cumsum(n) - n)[some]
                    node[some] = mix(np.add.reduceat(mix(h, 3), begin) ^ mix(np.bitwise_xor.reduceat(mix(h, 4), begin), 5), 6)
                    band = bands(h, n[some]).ravel()
                fp = np.packbits(2 * bit_votes(h, n) > n[:, None], axis=1, bitorder="little")
                own = [batch.column(k).slice(lo, hi - lo) for k in range(3)]
                yield pa.RecordBatch.from_arrays([*own, pa.array(node.view(np.int64)), pa.array(n, pa.int64()), pa.array([x.tobytes() for x in fp], pa.binary()), lists(band, held)], names)

    return df.select(F.col(key), *PLACE, F.col(text)).mapInArrow(run, f"id {kind}, {PLACE[0]} string, {PLACE[1]} long, node long, size long, fp binary, bands array<long>")


def shingle_sets(df: DataFrame, shingle: int, text: str) -> DataFrame:
    """(node, s): the set of each row; df has its node."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo, hi, data, at in slices(batch.column(1)):
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo), lists(*distinct_shingles(data, at, shingle))], ["node", "s"])

    return df.select("node", F.col(text)).mapInArrow(run, "node long, s array<long>")


def bitmaps(h: np.ndarray, n: np.ndarray) -> np.ndarray:
    """(WORDS, texts): a bitmap of each text, in which every one of its shingles has flipped one bit."""
    out, some = np.zeros((len(WORDS), len(n)), U), np.flatnonzero(n)
    if len(some):
        bit = mix(h, 9) % U(64 * len(WORDS))
        for k in range(len(WORDS)):
            out[k, some] = np.bitwise_xor.reduceat(np.where(bit // U(64) == U(k), U(1) << bit % U(64), U(0)), (np.cumsum(n) - n)[some])
    return out


def shingle_counts(df: DataFrame, shingle: int, text: str) -> np.ndarray:
    """(COUNTED,): how many sets of the rows hold a shingle of each number; its size doesn't depend on the rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(COUNTED, np.int64)
        for batch in batches:
            for _, _, data, at in slices(batch.column(0)):
                total += np.bincount((distinct_shingles(data, at, shingle)[0] % U(COUNTED)).astype(np.int64), minlength=COUNTED)
        some = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(some, pa.int64()), pa.array(total[some])], ["k", "n"])

    got = df.select(text).mapInArrow(run, "k long, n long").groupBy("k").agg(F.sum("n").alias("n")).toArrow()
    counts = np.zeros(COUNTED, np.int64)
    counts[got.column(0).to_numpy()] = got.column(1).to_numpy()
    return counts


def prefixes(df: DataFrame, share: Fraction, shingle: int, text: str) -> DataFrame:
    """(number, node, size, place, the words of the bitmap): the shingles among the first size - ceil(share * size) + 1 of each
    row's set, and their places."""
    names = ["number", "node", "size", "place", *WORDS]
    counts = df.sparkSession.sparkContext.broadcast(shingle_counts(df, shingle, text))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo, hi, data, at in slices(batch.column(1)):
                h, n = distinct_shingles(data, at, shingle)
                node = batch.column(0).slice(lo, hi - lo).to_numpy(zero_copy_only=False)
                own = np.repeat(np.arange(len(n)), n)
                h = h[np.lexsort((h, counts.value[(h % U(COUNTED)).astype(np.int64)], own))]
                place = np.arange(len(h)) - np.repeat(np.cumsum(n) - n, n)
                held = n + (-n * share.numerator // share.denominator) + 1
                kept = place < held[own]
                out = [mix(h[kept], 8).view(np.int64), node[own[kept]], n[own[kept]], place[kept], *bitmaps(h, n).view(np.int64)[:, own[kept]]]
                yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in out], names)

    return df.select("node", F.col(text)).mapInArrow(run, ", ".join(f"{name} long" for name in names))


class Confirmed:
    """Compares pairs of nodes by their sets, which are made from the texts of one row of each node that is asked for."""

    def __init__(self, docs: DataFrame, distinct: DataFrame, share: Fraction, shingle: int, text: str):
        self.docs, self.share, self.shingle, self.text = docs, share, shingle, text
        self.first = distinct.select("node", *(F.col(f"first.{c}").alias(f"f{c}") for c in PLACE))

    def rows(self, wanted: DataFrame) -> DataFrame:
        """One row of each node; wanted: a written table of places that ``first`` gives to nodes."""
        return self.docs.join(small(wanted, 300), (F.col(PLACE[0]) == F.col(f"f{PLACE[0]}")) & (F.col(PLACE[1]) == F.col(f"f{PLACE[1]}")))

    def places(self, nodes: DataFrame) -> DataFrame:
        return durable(self.first.join(nodes, "node", "left_semi"), "near-wanted")

    def enough(self, common: Column, one: Column, two: Column) -> Column:
        """Whether sets of two sizes that share so many shingles have the similarity: same / (x + y - same) >= share."""
        return common * (self.share.numerator + self.share.denominator) >= (one + two) * self.share.numerator

    def differing(self, one: str, two: str, sizes: Column) -> Column:
        """Whether bitmaps differ in so few bits that sets of that many shingles together can have the similarity."""
        bits = sum((F.bit_count(F.col(f"{one}{w}").bitwiseXOR(F.col(f"{two}{w}"))) for w in WORDS), F.lit(0))
        return bits * (self.share.numerator + self.share.denominator) <= sizes * (self.share.denominator - self.share.numerator)

    def __call__(self, pairs: DataFrame) -> DataFrame:
        """(a, b) of the pairs (a written table) that have the similarity."""
        wanted = self.places(pairs.select(F.col("a").alias("node")).union(pairs.select("b")).distinct())
        sets = durable(shingle_sets(self.rows(wanted), self.shingle, self.text), "near-sets")
        one, two = sets.select(F.col("node").alias("a"), F.col("s").alias("x")), sets.select(F.col("node").alias("b"), F.col("s").alias("y"))
        met = pairs.select("a", "b").join(one, "a").join(two, "b")
        found = durable(met.where(self.enough(F.size(F.array_intersect("x", "y")), F.size("x"), F.size("y"))).select("a", "b"), "near-links")
        drop_durable(wanted), drop_durable(sets), drop_durable(pairs)
        return found


def joined(found: DataFrame, roots: DataFrame) -> DataFrame:
    """roots, with the components that links of found join made one; both are written tables, which are removed."""
    of = lambda side: roots.select(F.col("node").alias(side), F.col("root").alias(f"r{side}"))
    ends = found.join(of("a"), "a", "left").join(of("b"), "b", "left").select(F.coalesce("ra", "a").alias("a"), F.coalesce("rb", "b").alias("b"))
    ends = durable(ends.where("a <> b").distinct(), "near-ends")
    merged = durable(components(ends, "near-components"), "near-merged")
    to = merged.select(F.col("node").alias("from"), F.col("root").alias("to"))
    moved = roots.join(to, F.col("root") == F.col("from"), "left").select("node", F.coalesce("to", "root").alias("root"))
    now = durable(moved.union(merged.join(roots, "node", "left_anti").select("node", "root")), "near-roots")
    drop_durable(found), drop_durable(roots), drop_durable(ends), drop_durable(merged)
    return now


def apart(left: DataFrame, roots: DataFrame) -> DataFrame:
    """The members of groups (a written table, which is removed) that more than one component is left of, with their roots."""
    named = left.join(roots.withColumnRenamed("node", "m"), F.col("node") == F.col("m"), "left").select(left["*"], F.coalesce("root", "node").alias("root"))
    several = named.groupBy("number").agg(F.min("root").alias("lo"), F.max("root").alias("hi")).where("lo < hi").select("number")
    now = durable(named.join(several, "number"), "near-apart")
    drop_durable(left)
    return now


def roots_of(distinct: DataFrame, confirmed: Confirmed, listed: int = LISTED) -> DataFrame:
    """(node, root) of every node that has a link of the similarity, as all such links join them.
    distinct: (node, size, fp, bands, first)."""
    by_bits = simhash.links(distinct.select("node", "fp", F.lit(b"").alias("weak")), simhash.FIVE)
    entries = distinct.select("node", "size", F.explode("bands").alias("number"))
    # groups of two nodes or more, as an aggregate that is combined in the tasks first; the least node meets all others
    shared = entries.groupBy("number").agg(F.min(F.struct("node", "size")).alias("p"), F.max("node").alias("top")).where("p.node < top").select("number", "p")
    left = durable(entries.join(shared, "number").where("node <> p.node"), "near-left")
    sized = confirmed.enough(F.least("size", "p.size"), F.col("size"), F.col("p.size"))
    pairs = left.where(sized).select(F.col("p.node").alias("a"), F.col("node").alias("b")).union(by_bits.select(F.least("a", "b"), F.greatest("a", "b")))
    found = confirmed(durable(pairs.distinct(), "near-pairs"))
    roots = durable(components(found, "near-components"), "near-roots")
    drop_durable(found)
    left = apart(left.select("number", "node"), roots)
    wanted = confirmed.places(left.select("node").distinct())
    drop_durable(left)
    if wanted.isEmpty():
        return roots
    # from here on groups are of a shingle in the prefixes of the members that are still apart in some band
    every = durable(prefixes(confirmed.rows(wanted), confirmed.share, confirmed.shingle, confirmed.text), "near-prefixes")
    drop_durable(wanted)
    several = every.groupBy("number").agg(F.min("node").alias("lo"), F.max("node").alias("hi")).where("lo < hi").select("number")
    left = durable(every.join(several, "number"), "near-left")
    drop_durable(every)
    while True:
        now = apart(left, roots)
        if now.isEmpty():
            drop_durable(now)
            return roots
        # a group is done when one component is left of it: only members outside its largest one need be pivots
        sizes = now.groupBy("number", "root").agg(F.count(F.lit(1)).alias("n"))
        largest = sizes.groupBy("number").agg(F.max_by("root", F.struct("n", "root")).alias("big"))
        pivot = durable(least(now.join(largest, "number").where("root <> big"), listed), "near-pivots")
        other = pivot.select("number", F.struct("node", "size", "place", "root", *WORDS).alias("p"))
        reach = confirmed.enough(F.least(F.col("size") - F.col("place"), F.col("p.size") - F.col("p.place")), F.col("size"), F.col("p.size"))
        near = confirmed.differing("", "p.", F.col("size") + F.col("p.size"))
        met = now.join(other, (now["number"] == other["number"]) & (F.col("root") != F.col("p.root")) & reach & near)
        pairs = durable(met.select(F.least("node", "p.node").alias("a"), F.greatest("node", "p.node").alias("b")).distinct(), "near-pairs")
        left = durable(now.join(pivot.select("number", "node"), ["number", "node"], "left_anti").drop("root"), "near-left")
        drop_durable(now), drop_durable(pivot)
        found = confirmed(pairs)
        if not found.isEmpty():
            roots = joined(found, roots)
        listed *= 8


def least(rows: DataFrame, n: int) -> DataFrame:
    """The n rows of each number with the least nodes, by salted top lists, so no task sorts a whole group."""
    salted = rows.withColumn("salt", F.pmod(F.xxhash64("node"), F.lit(64)))
    top = salted.withColumn("r", F.row_number().over(Window.partitionBy("number", "salt").orderBy("node"))).where(F.col("r") <= n)
    return top.withColumn("r", F.row_number().over(Window.partitionBy("number").orderBy("node"))).where(F.col("r") <= n).drop("salt", "r", "big")


def keep_one(df: DataFrame, similarity: float = 0.8, shingle: int = 5, key: str = "doc_id", text: str = "text", listed: int = LISTED) -> DataFrame:
    """The rows of df without those that are linked, directly or by others, to a row with a smaller id; of equal ids in a group
    the row that stands first stays."""
    docs = numbered(df)
    every = durable(marks(docs, shingle, key, text), "near-every")
    place = F.struct(*PLACE)
    named = F.struct("id", *PLACE)
    distinct = durable(every.groupBy("node").agg(F.min(F.when(F.col("id").isNotNull(), named)).alias("least"), F.min(place).alias("first"), F.first("size").alias("size"), F.first("fp").alias("fp"), F.first("bands").alias("bands")), "near-distinct")
    confirmed = Confirmed(docs, distinct, Fraction(str(similarity)), shingle, text)
    roots = roots_of(distinct, confirmed, listed).withColumnRenamed("node", "m")
    own = distinct.select("node", "least").join(roots, F.col("node") == F.col("m"), "left").select("node", "least", F.coalesce("root", "node").alias("root"))
    stays = own.groupBy("root").agg(F.min("least").alias("stays"))
    own = durable(own.select("node", "root").join(stays, "root").select("node", "stays").where("stays IS NOT NULL"), "near-named")
    release(df.sparkSession)
    same = (F.col(PLACE[0]) == F.col(f"stays.{PLACE[0]}")) & (F.col(PLACE[1]) == F.col(f"stays.{PLACE[1]}"))
    gone = durable(every.select("id", *PLACE, "node").where("id IS NOT NULL").join(own, "node").where(~same).select(*(F.col(c).alias(f"g{c}") for c in PLACE)), "near-gone")
    return docs.join(small(gone, 256), (F.col(PLACE[0]) == F.col(f"g{PLACE[0]}")) & (F.col(PLACE[1]) == F.col(f"g{PLACE[1]}")), "left_anti").select(*df.columns)
