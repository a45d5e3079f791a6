"""Minimax contiguous sharding of atomic groups.

Rows of one text form a group that stays whole. Groups stand in the order of their digests; the smallest capacity for
which a greedy walk needs no more than the given number of shards is found by binary search, and the cuts are made there.
A group larger than an even share gets a shard of its own first, so that it doesn't set everyone's capacity.

The driver sees totals of 65,536 digest ranges, the largest groups (one per shard at most) and the groups of the few
ranges where a cut can fall; never the groups or rows of all documents. Row slots come from counts by (shard, range, part)
and a row number inside each, where groups with many rows are dealt over parts.

Cases: a null text counts as empty (size 1); repeated rows are rows of their own and share a group; null ids sort first;
an empty table gives an empty result; fewer groups than shards leave shards empty; other columns are not read.
"""

from __future__ import annotations

from bisect import bisect_right
from collections.abc import Sequence
from itertools import accumulate

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import durable

RANGES = 1 << 16


def greedy_cuts(ends: Sequence[int], capacity: int, shards: int) -> list[int] | None:
    """Item counts at which a greedy walk closes each shard; None where ``shards`` aren't enough. ends: prefix sums."""
    cuts, at, base = [], 0, 0
    while at < len(ends):
        if len(cuts) == shards:
            return None
        to = bisect_right(ends, base + capacity, lo=at)
        if to == at:
            return None
        cuts.append(to)
        at, base = to, ends[to - 1]
    return cuts


def smallest_capacity(sizes: Sequence[int], shards: int) -> tuple[int, list[int]]:
    """The least capacity with which a greedy walk fits, and its cuts."""
    ends = list(accumulate(sizes))
    if not ends:
        return 0, []
    lo, hi = max(max(sizes), -(-ends[-1] // shards)), ends[-1]
    while lo < hi:
        mid = (lo + hi) // 2
        lo, hi = (lo, mid) if greedy_cuts(ends, mid, shards) is not None else (mid + 1, hi)
    return lo, greedy_cuts(ends, lo, shards)


def _ranges_with_cuts(totals: list[tuple[int, int]], largest: int, shards: int) -> set[int]:
    """The ranges in which the cuts of the best capacity can fall: between a greedy walk with the least capacity that is
    possible, which stops at range ends, and the fullest shards that the best walk over whole ranges allows."""
    ids, sizes = [r for r, _ in totals], [b for _, b in totals]
    ends = list(accumulate(sizes))
    low_capacity, high_capacity = max(largest, -(-ends[-1] // shards)), smallest_capacity(sizes, shards)[0]
    wanted: set[int] = set()
    low = 0
    for j in range(1, shards):
        at = bisect_right(ends, low + low_capacity)
        low = max(low, ends[at - 1] if at else 0)
        first, last = bisect_right(ends, low), bisect_right(ends, min(j * high_capacity, ends[-1] - 1))
        wanted.update(ids[first : last + 1])
    return wanted


def shard(df: DataFrame, shards: int = 8, key: str = "doc_id", text: str = "text", law: str = "bytes") -> DataFrame:
    """(key, size, text_crc32, law, shard, slot, grown_shard) of every row; sizes near equal."""
    plain = F.coalesce(F.col(text).cast("string"), F.lit(""))
    base = durable(df.select(F.col(key).alias("k"), (F.octet_length(plain) + 1).cast("long").alias("size"), F.crc32(plain.cast("binary")).alias("crc"), F.md5(plain.cast("binary")).alias("digest")), "shard-base")
    base = base.withColumn("range", F.conv(F.substring("digest", 1, 4), 16, 10).cast("int"))
    groups = durable(base.groupBy("range", "digest").agg(F.sum("size").alias("bytes"), F.count(F.lit(1)).alias("n")), "shard-groups")
    rows = groups.agg(F.sum("n")).first()[0] or 0
    totals = {r["range"]: r["bytes"] for r in groups.groupBy("range").agg(F.sum("bytes").alias("bytes")).collect()}
    top = groups.orderBy(F.desc("bytes"), "digest").limit(shards + 1).collect()

    left, giants = shards, []
    rest = sum(totals.values())
    for g in top:
        if left > 1 and g["bytes"] * left > rest:
            giants.append(g["digest"])
            totals[g["range"]] -= g["bytes"]
            rest, left = rest - g["bytes"], left - 1
    largest = next((g["bytes"] for g in top if g["digest"] not in giants), 0)
    ordered = sorted((r, b) for r, b in totals.items() if b)
    bounds: list[str] = []
    if ordered and left > 1:
        opened = _ranges_with_cuts(ordered, largest, left)
        inside = groups.where(F.col("range").isin(sorted(opened)) & ~F.col("digest").isin(giants)).select("digest", "bytes").orderBy("digest").collect()
        items = sorted([(g["digest"], g["bytes"]) for g in inside] + [(f"{r:04x}~", b) for r, b in ordered if r not in opened])
        _, cuts = smallest_capacity([b for _, b in items], left)
        bounds = [items[c - 1][0] for c in cuts[:-1]]
    number = F.lit(len(giants))
    for b in bounds:
        number = number + (F.col("digest") > b).cast("int")
    for i, g in enumerate(giants):
        number = F.when(F.col("digest") == g, F.lit(i)).otherwise(number)

    per_part = max(1000, rows // 20_000)  # so at most 20,000 groups are dealt, over 40,000 parts
    many = groups.where(F.col("n") > per_part).select("digest", F.ceil(F.col("n") / per_part).alias("parts"))
    placed = base.join(F.broadcast(many), "digest", "left").withColumn("part", F.coalesce(F.pmod(F.xxhash64("k"), F.col("parts")), F.lit(0))).withColumn("shard", number.cast("int"))
    counts = placed.groupBy("shard", "range", "part").agg(F.count(F.lit(1)).alias("n"))
    before = F.coalesce(F.sum("n").over(Window.partitionBy("shard").orderBy("range", "part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    starts = counts.select("shard", "range", "part", before.alias("start"))  # as many rows as ranges and parts at most
    inner = F.row_number().over(Window.partitionBy("shard", "range", "part").orderBy("digest", "k"))
    return (
        placed.withColumn("rn", inner)
        .join(F.broadcast(starts), ["shard", "range", "part"])
        .select(F.col("k").alias(key), "size", F.col("crc").alias("text_crc32"), F.lit(law).alias("law"), "shard", (F.col("start") + F.col("rn") - 1).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))
    )
