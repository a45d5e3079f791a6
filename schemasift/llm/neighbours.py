"""Approximate nearest neighbours by learned partitions.

The exact neighbour graph of a bounded sample is cut into balanced parts with few edges between them; a small network learns
the part of a vector (its neighbours' parts, as shares) and then routes: every row goes to its most probable part, every
query to its most probable parts, where all rows are compared exactly.

Equal vectors are one row of the index: only the k + 1 smallest ids of each can be among a query's k nearest, so a
vector that a third of all rows share costs no more than another. Parts are dealt over blocks by the vector's digest, queries
over blocks of their own, and a task compares one block of each.

Cases: null, zero, non-finite or null-holding vectors, and those whose length differs from the most common one, take no part, neither
as queries nor as rows; fewer candidates than k give fewer rows; equal scores go to the smaller id; a repeated row (same id
and vector) counts once; an empty table gives an empty result; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import durable

#: Vectors that the partition is learned from at most, parts, rows in a block, queries in a block.
SAMPLE, PARTS, BLOCK, QUERY_BLOCK = 6000, 16, 8192, 1024
#: A query visits its most probable parts: the fewest with which queries outside the learning rows, asked of other rows outside them,
#: found this share of their nearest.
TARGET = 0.97


def neighbour_graph(x: np.ndarray, k: int = 10) -> np.ndarray:
    """The k nearest of each unit vector, by blocks."""
    k = min(k, len(x) - 1)
    out = np.zeros((len(x), max(k, 0)), np.int64)
    for i in range(0, len(x), 1024) if k > 0 else ():
        s = x[i : i + 1024] @ x.T
        s[np.arange(len(s)), np.arange(i, i + len(s))] = -np.inf
        out[i : i + len(s)] = np.argpartition(-s, k - 1, axis=1)[:, :k]
    return out


def balanced_parts(x: np.ndarray, near: np.ndarray, parts: int = PARTS, sweeps: int = 8, slack: float = 1.05) -> np.ndarray:
    """A part for each vector: halves along principal directions, then moves to the part that holds most neighbours as
    far as the parts' capacity allows, best gains first."""
    part = np.zeros(len(x), np.int64)
    size = 1
    while size < parts:
        new = part.copy()
        for p in range(size):
            own = np.flatnonzero(part == p)
            if len(own) > 1:
                y = x[own] - x[own].mean(0)
                along = y @ np.linalg.svd(y, full_matrices=False)[2][0]
                new[own] = 2 * p + (np.argsort(np.argsort(along, kind="stable")) >= len(own) // 2)
            else:
                new[own] = 2 * p
        part, size = new, size * 2
    room = int(np.ceil(len(x) / parts * slack))
    for _ in range(sweeps):
        votes = np.zeros((len(x), parts))
        np.add.at(votes, (np.arange(len(x))[:, None], part[near]), 1.0)
        np.add.at(votes, (near, np.broadcast_to(part[:, None], near.shape)), 1.0)
        wish = votes.argmax(1)
        gain = votes[np.arange(len(x)), wish] - votes[np.arange(len(x)), part]
        held = np.bincount(part, minlength=parts)
        moved = 0
        for i in np.argsort(-gain, kind="stable"):
            if gain[i] <= 0:
                break
            if held[wish[i]] < room:
                held[wish[i]] += 1
                held[part[i]] -= 1
                part[i], moved = wish[i], moved + 1
        if not moved:
            break
    return part


class Router:
    """One hidden layer; probabilities of the parts of a unit vector."""

    def __init__(self, weights: list[np.ndarray]):
        self.weights = weights

    @staticmethod
    def learn(x: np.ndarray, wanted: np.ndarray, hidden: int = 64, epochs: int = 20, rate: float = 0.003, decay: float = 0.01, seed: int = 3) -> list[np.ndarray]:
        rng, (n, d), parts = np.random.default_rng(seed), x.shape, wanted.shape[1]
        w = [rng.normal(0, 1, (d, hidden)), np.zeros(hidden), rng.normal(0, 1 / np.sqrt(hidden), (hidden, parts)), np.zeros(parts)]
        m, v, t = [np.zeros_like(a) for a in w], [np.zeros_like(a) for a in w], 0
        for _ in range(epochs):
            order = rng.permutation(n)
            for i in range(0, n, 256):
                at = order[i : i + 256]
                h = np.maximum(x[at] @ w[0] + w[1], 0)
                g = (softmax(h @ w[2] + w[3]) - wanted[at]) / len(at)
                back = (g @ w[2].T) * (h > 0)
                t += 1
                for k, grad in enumerate((x[at].T @ back, back.sum(0), h.T @ g, g.sum(0))):
                    m[k] = 0.9 * m[k] + 0.1 * grad
                    v[k] = 0.999 * v[k] + 0.001 * grad**2
                    w[k] = w[k] * (1 - rate * decay) - rate * (m[k] / (1 - 0.9**t)) / (np.sqrt(v[k] / (1 - 0.999**t)) + 1e-8)
        return w

    @staticmethod
    def parts(weights: list[np.ndarray], x: np.ndarray) -> np.ndarray:
        return softmax(np.maximum(x @ weights[0] + weights[1], 0) @ weights[2] + weights[3])


def probes(weights: list[np.ndarray], rows: np.ndarray, asked: np.ndarray, k: int, target: float = TARGET) -> int:
    """The fewest parts to visit, by unit vectors that taught nothing."""
    parts = weights[3].shape[0]
    if len(rows) < k or not len(asked):
        return parts
    near = np.argpartition(-(asked @ rows.T), k - 1, axis=1)[:, :k]
    place = Router.parts(weights, rows).argmax(1)[near]
    order = np.argsort(np.argsort(-Router.parts(weights, asked), 1, kind="stable"), 1)
    at = np.take_along_axis(order, place, 1)
    share = [(at < m).mean() for m in range(1, parts + 1)]
    return next(m for m in range(1, parts + 1) if share[m - 1] >= target)


def softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(1, keepdims=True))
    return e / e.sum(1, keepdims=True)


def unit(x: np.ndarray) -> np.ndarray:
    return x / np.sqrt((x * x).sum(1, keepdims=True))


def usable(vector: Column) -> Column:
    wide = vector.cast("array<double>")
    finite = F.forall(wide, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf")))
    return vector.isNotNull() & (F.size(vector) > 0) & F.coalesce(finite, F.lit(False)) & F.coalesce(F.exists(wide, lambda v: v != 0), F.lit(False))


def search(df: DataFrame, is_query: Column, k: int = 5, key: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """(query_id, rank, key, score): the k nearest that are found of each query, nearest first, by cosine."""
    spark = df.sparkSession
    fair = df.where(usable(F.col(vector)) & F.col(key).isNotNull()).select(F.col(key).cast("long").alias("id"), F.col(vector).cast("array<double>").alias("v"), F.coalesce(is_query, F.lit(False)).alias("q"))
    width = fair.groupBy(F.size("v").alias("d")).agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "d").first()
    fair = fair.where(F.size("v") == (width["d"] if width else 0))
    # the k + 1 smallest ids of each vector: one partial aggregate per task bounds what is shuffled of a hot vector
    digest = F.xxhash64("v")
    some = fair.select("v", digest.alias("h"), F.pmod(F.xxhash64("id"), F.lit(64)).alias("salt"), "id").groupBy("h", "v", "salt").agg(F.slice(F.array_sort(F.collect_set("id")), 1, k + 1).alias("ids"))
    rows = durable(some.groupBy("h", "v").agg(F.slice(F.array_sort(F.array_distinct(F.flatten(F.collect_list("ids")))), 1, k + 1).alias("ids")), "ann-vectors")
    sample = np.array([r["v"] for r in rows.orderBy("h", "v").limit(SAMPLE).select("v").collect()], np.float64)
    schema = "query_id long, rank int, id long, score double"
    if len(sample) == 0:
        return spark.createDataFrame([], schema).withColumnRenamed("id", key)
    every = unit(sample)
    every = every[np.random.default_rng(5).permutation(len(every))]
    parts = PARTS if len(every) >= 40 * PARTS else 1
    learn = len(every) * 6 // 10 if parts > 1 else len(every)
    x = every[:learn]
    near = neighbour_graph(x)
    part = balanced_parts(x, near, parts)
    wanted = np.zeros((len(x), parts))
    wanted[np.arange(len(x)), part] += 1
    if near.shape[1]:
        np.add.at(wanted, (np.arange(len(x))[:, None], part[near]), 1.0 / near.shape[1])
    weights = Router.learn(x, wanted / wanted.sum(1, keepdims=True))
    asked = every[learn + (len(every) - learn) * 3 // 4 :]
    visits = probes(weights, every[learn : len(every) - len(asked)], asked, k) if parts > 1 else 1
    shared = spark.sparkContext.broadcast(weights)

    def place(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            if len(b):
                p = Router.parts(shared.value, unit(np.stack(b["v"].to_numpy())))
                yield b.assign(part=p.argmax(1).astype(np.int32))

    def route(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            if len(b):
                p = Router.parts(shared.value, unit(np.stack(b["v"].to_numpy())))
                yield b.assign(part=list(np.argsort(-p, 1, kind="stable")[:, :visits].astype(np.int32)))

    placed = durable(rows.select("h", "v", "ids").mapInPandas(place, "h long, v array<double>, ids array<long>, part int"), "ann-index")
    held = {r["part"]: -(-r["n"] // BLOCK) for r in placed.groupBy("part").agg(F.count(F.lit(1)).alias("n")).collect()}  # a row per part
    blocks = F.element_at(F.array(*(F.lit(held.get(p, 0)) for p in range(parts))), F.col("part") + 1)
    routed = fair.where("q").select("id", "v").dropDuplicates(["id"]).mapInPandas(route, "id long, v array<double>, part array<int>").select("id", "v", F.explode("part").alias("part"))
    routed = routed.where(blocks > 0).withColumn("block", F.explode(F.sequence(F.lit(0), blocks - 1)))
    groups = F.ceil(F.lit((fair.where("q").count() or 1) / QUERY_BLOCK)).cast("int")
    routed = routed.withColumn("group", F.pmod(F.xxhash64("id"), groups).cast("int"))
    left = placed.withColumn("block", F.pmod(F.xxhash64("h"), blocks).cast("int")).withColumn("group", F.explode(F.sequence(F.lit(0), groups - 1)))

    def compare(rows: pd.DataFrame, asked: pd.DataFrame) -> pd.DataFrame:
        if not len(rows) or not len(asked):
            return pd.DataFrame({"query_id": [], "id": [], "score": []})
        base, q = np.stack(rows["v"].to_numpy()), np.stack(asked["v"].to_numpy())
        norms, ids = np.sqrt((base * base).sum(1)), rows["ids"].to_list()
        first, unit_base = np.array([i[0] for i in ids]), base / norms[:, None]
        out: list[tuple[int, int, float]] = []
        take = min(len(base), k + 4)
        for me, row in zip(asked["id"], q, strict=True):
            rough = unit_base @ row
            edge = np.partition(rough, len(rough) - take)[len(rough) - take]
            at = np.flatnonzero(rough >= edge - 1e-9 * max(1.0, abs(edge)))
            # as every pair is summed alike, whichever block it is in, equal vectors get equal scores
            exact = (base[at] * row).sum(1) / (norms[at] * np.sqrt((row * row).sum()))
            found: list[tuple[float, int]] = []
            for j in np.lexsort((first[at], -exact))[: k + 4]:
                found += [(-exact[j], i) for i in ids[at[j]] if i != me]
            out += [(me, i, -s) for s, i in sorted(found)[:k]]
        return pd.DataFrame(out, columns=["query_id", "id", "score"])

    met = left.groupBy("part", "block", "group").cogroup(routed.groupBy("part", "block", "group")).applyInPandas(compare, "query_id long, id long, score double")
    best = met.groupBy("query_id").agg(F.slice(F.array_sort(F.collect_set(F.struct((-F.col("score")).alias("far"), "id"))), 1, k).alias("best"))  # k rows a block at most
    return best.select("query_id", F.posexplode("best").alias("at", "b")).select("query_id", (F.col("at") + 1).cast("int").alias("rank"), F.col("b.id").alias(key), (-F.col("b.far")).alias("score"))
